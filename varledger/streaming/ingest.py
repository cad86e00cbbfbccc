"""Profiles of arriving rows: windows, sessions, running state, versions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import classify, evidence
from ..operators.ledger import append


def windowed_profile(
    rows: DataFrame, *, value: str = "value", time: str = "ts", by: list[str] | None = None, length: str = "7 days",
    slide: str | None = None, watermark: str | None = "1 day",
) -> DataFrame:
    """Class of a variable by time window (tumbling, or sliding by ``slide``),
    on a stream with a watermark (None: it has one already) or on a batch."""
    if rows.isStreaming and watermark:
        rows = rows.withWatermark(time, watermark)
    window = F.window(time, length, slide) if slide else F.window(time, length)
    return classify.classified(evidence.profile_cells(rows.withColumn("window", window), ["window", *(by or [])], value=value))


def session_profile(rows: DataFrame, *, gap: str = "1 hour", value: str = "value", time: str = "ts", by: str = "user_id", watermark: str = "1 day") -> DataFrame:
    """Class of a variable by session of each key."""
    if rows.isStreaming:
        rows = rows.withWatermark(time, watermark)
    x = evidence.as_number(F.col(value), rows.schema[value].dataType)
    grouped = rows.groupBy(F.session_window(time, gap).alias("window"), by).agg(evidence.evidence(x).alias("e"))
    return classify.classified(evidence.with_support(grouped.withColumn("numeric", F.lit(True))))


def distinct_deliveries(rows: DataFrame, *, key: str = "event_id", time: str = "ts", watermark: str = "1 day") -> DataFrame:
    """Each delivered id once, within the watermark."""
    return rows.withWatermark(time, watermark).dropDuplicatesWithinWatermark([key])


CUMULATIVE = (
    "column string, numeric boolean, n long, nonnull long, vmin double, vmax double, n_negative long, n_unit long, all_integer boolean, "
    "mean double, variance double, skew double, complete boolean, support array<struct<value:double,count:long>>, n_distinct long"
)
_STATE = (
    "n long, nonnull long, vmin double, vmax double, n_negative long, n_unit long, all_integer boolean, mean double, m2 double, m3 double, "
    "item array<double>, times array<long>, over boolean"
)


def _merged(a: tuple, b: tuple) -> tuple:
    """Central moments (n, mean, m2, m3) of two parts together."""
    (na, ma, a2, a3), (nb, mb, b2, b3) = a, b
    n, d = na + nb, mb - ma
    if not n:
        return a
    m3 = a3 + b3 + d**3 * na * nb * (na - nb) / n**2 + 3 * d * (na * b2 - nb * a2) / n
    return n, ma + d * nb / n, a2 + b2 + d * d * na * nb / n, m3


def cumulative(rows: DataFrame, *, cap: int = 25, mode: str = "update") -> DataFrame:
    """Running profile and class of an arriving file's cells (column, value):
    three moments and at most ``cap`` values with counts of state for each
    column, whatever arrives.  NaN and infinities are missing."""

    def step(key, batches: Iterator[pd.DataFrame], state):
        first = (0, 0, float("inf"), float("-inf"), 0, 0, True, 0.0, 0.0, 0.0, [], [], False)
        n, nonnull, low, high, negative, unit, whole, mean, m2, m3, item, times, over = state.get if state.exists else first
        counts = dict(zip(item, times, strict=True))
        for pdf in batches:
            n += len(pdf)
            x = pdf["value"].to_numpy(dtype=float)
            x = x[np.isfinite(x)]
            if not len(x):
                continue
            d = x - x.mean()
            nonnull, mean, m2, m3 = _merged((nonnull, mean, m2, m3), (len(x), x.mean(), (d**2).sum(), (d**3).sum()))
            low, high = min(low, x.min()), max(high, x.max())
            negative, unit = negative + (x < 0).sum(), unit + ((x >= 0) & (x <= 1)).sum()
            whole = whole and bool((x == np.floor(x)).all())
            if not over:
                for v, c in zip(*np.unique(x, return_counts=True), strict=True):
                    counts[float(v)] = counts.get(float(v), 0) + int(c)
                if len(counts) > cap:
                    counts, over = {}, True
        item = sorted(counts)
        times = [counts[v] for v in item]
        state.update((int(n), int(nonnull), float(low), float(high), int(negative), int(unit), bool(whole), float(mean), float(m2), float(m3), item, times, bool(over)))
        some = nonnull > 0
        skew = m3 / nonnull / (m2 / nonnull) ** 1.5 if some and m2 > 0 else None
        row = (
            key[0], True, n, nonnull, low if some else None, high if some else None, negative, unit, bool(whole) and some, mean if some else None,
            m2 / nonnull if some else None, skew, not over, None if over else [{"value": v, "count": c} for v, c in zip(item, times, strict=True)],
            cap + 1 if over else len(item),
        )
        yield pd.DataFrame([row], columns=[c.split()[0] for c in _FIELDS])

    return classify.classified(rows.groupBy("column").applyInPandasWithState(step, CUMULATIVE, _STATE, mode, "NoTimeout"))


_FIELDS = ["column", "numeric", "n", "nonnull", "vmin", "vmax", "n_negative", "n_unit", "all_integer", "mean", "variance", "skew", "complete", "support", "n_distinct"]


#: Folders of a version store; a batch reads only those of its own keys.
BUCKETS = 64


def version_sink(path: str, keys: list[str]):
    """foreachBatch: append a profile version where class or evidence changed.
    A batch that is delivered again changes nothing.  Versions lie in folders by
    a hash of their keys, so a batch does not read the whole history."""

    def run(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        text = [F.col(k).cast("string") for k in keys]
        rows = batch.select(*keys, "n", "class").withColumn(
            "assertion_id", F.sha2(F.concat_ws("|", *text, *[F.col(c).cast("string") for c in ("n", "class")]), 256)
        ).withColumn("batch_id", F.lit(batch_id)).withColumn("bucket", F.pmod(F.xxhash64(*text), F.lit(BUCKETS)).cast("int"))
        rows = rows.persist()
        try:
            used = [r.bucket for r in rows.select("bucket").distinct().collect()]  # at most BUCKETS
            old = _stored(spark, path, rows).where(F.col("bucket").isin(used))
            fresh = append(old, rows).join(old.select("assertion_id"), "assertion_id", "left_anti")
            fresh.write.mode("append").partitionBy("bucket").parquet(path)
        finally:
            rows.unpersist()

    return run


def _stored(spark: SparkSession, path: str, like: DataFrame) -> DataFrame:
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    if at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).exists(at):
        return spark.read.schema(like.schema).parquet(path)
    return spark.createDataFrame([], like.schema)


def late_router(path: str, accept, *, time: str = "ts", delay: str = "1 day"):
    """foreachBatch: rows older than the latest time seen before the batch less
    ``delay`` go to ``path``/late, the queue of what is to be profiled again,
    and are counted in ``path``/counts; ``accept`` gets the others with the
    batch id.  The latest time comes from the counts, so a restart goes on, and
    a batch that is delivered again is routed as it was."""

    def run(batch: DataFrame, batch_id: int) -> None:
        spark = batch.sparkSession
        schema = spark.createDataFrame([], f"batch_id long, n long, n_late long, latest {batch.schema[time].dataType.simpleString()}")
        before = _stored(spark, f"{path}/counts", schema).where(F.col("batch_id") < batch_id).agg(F.max("latest")).first()[0]
        late = F.lit(False) if before is None else F.col(time) < F.lit(before) - F.expr(f"INTERVAL {delay}")
        batch = batch.withColumn("_late", F.coalesce(late, F.lit(False))).persist()
        try:
            batch.where("_late").drop("_late").withColumn("batch_id", F.lit(batch_id).cast("long")).write.mode("overwrite").parquet(f"{path}/late/batch={batch_id}")
            accept(batch.where("NOT _late").drop("_late"), batch_id)
            count = batch.agg(F.lit(batch_id).cast("long").alias("batch_id"), F.count("*").alias("n"), F.count_if("_late").alias("n_late"), F.max(time).alias("latest"))
            count.write.mode("overwrite").parquet(f"{path}/counts/batch={batch_id}")
        finally:
            batch.unpersist()

    return run


def alerts(profiles: DataFrame, uses: DataFrame, rules: DataFrame, *, bound: str = "7 days") -> DataFrame:
    """Alert on arrival of either side: a stream of profiles meets a stream of
    extracted uses within a time bound; the rules are static."""
    p = profiles.withWatermark("profiled_at", bound)
    u = uses.withWatermark("extracted_at", bound).withColumnRenamed("variable_id", "use_variable")
    near = F.expr(
        f"variable_id = use_variable AND extracted_at BETWEEN profiled_at - INTERVAL {bound} AND profiled_at + INTERVAL {bound}"
    )
    return p.join(u, near).join(F.broadcast(rules), ["family", "class"]).select("analysis_id", "variable_id", "family", "class", "tier")
