"""The audit wrapper: the census class stays, what it rests on is shown."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.rules import CENSUS, Gates
from .classify import classified, core_values


def declarations(rows: DataFrame, keys: list[str]) -> DataFrame:
    """(keys..., value, evidence_id) from rows of a codebook file, all text;
    rows without evidence or without a numeric value declare nothing."""
    value = F.col("value").try_cast("double")
    return rows.select(*keys, value.alias("value"), F.nullif(F.trim("evidence_id"), F.lit("")).alias("evidence_id")).where(
        "value IS NOT NULL AND evidence_id IS NOT NULL"
    )


def declared_rows(cells: DataFrame, said: DataFrame, keys: list[str], *, value: str = "value") -> DataFrame:
    """Rows of each variable that hold a declared value, however many values it
    has: keys..., dropped_rows."""
    codes = said.where("evidence_id IS NOT NULL").select(*keys, F.col("value").cast("double").alias(value)).distinct()
    return cells.withColumn(value, F.col(value).cast("double")).join(codes, [*keys, value], "left_semi").groupBy(*keys).agg(
        F.count("*").alias("dropped_rows")
    )


def audited(
    profiles: DataFrame, declarations: DataFrame | None, keys: list[str], *, cells: DataFrame | None = None, rules: Gates = CENSUS
) -> DataFrame:
    """Add audit_class, would_strip, dropped_rows, overflow and kept_values to
    profiles, which keep their support and census class.

    ``declarations`` (keys..., value, evidence_id) name codes that a codebook
    declares; only those are taken out, with their rows counted: in the support,
    or in ``cells`` for columns of more values than a support holds (without
    ``cells`` their count is null).  A class that the census reached only by
    stripping, so that the unstripped values have another, is unresolved unless
    every stripped value is declared.  Constant and all-missing columns are
    unresolved, too.
    """
    base = classified(profiles, rules=rules)
    plain = classified(profiles, rules=replace(rules, strip=False)).select(*keys, F.col("class").alias("plain_class"))
    base = base.join(plain.withColumnsRenamed({k: f"_{k}" for k in keys}), [F.col(k).eqNullSafe(F.col(f"_{k}")) for k in keys]).drop(
        *[f"_{k}" for k in keys]
    )
    none = F.array().cast("array<double>")
    if declarations is None:
        declared = base.withColumn("declared_values", none)
    else:
        codes = declarations.where("evidence_id IS NOT NULL").groupBy(*keys).agg(F.collect_set(F.col("value").cast("double")).alias("declared_values"))
        declared = base.join(codes, keys, "left").withColumn("declared_values", F.coalesce("declared_values", none))
    core = core_values(rules)
    kept = F.filter("support", lambda x: ~F.array_contains(F.col("declared_values"), x["value"]))
    gone = F.filter("support", lambda x: F.array_contains(F.col("declared_values"), x["value"]))
    counted = F.when(F.size("declared_values") == 0, F.lit(0).cast("long")).otherwise(
        F.aggregate(gone, F.lit(0).cast("long"), lambda t, x: t + x["count"])
    )
    out = declared.select(
        "*",
        F.transform(F.array_except(F.col("support"), core), lambda x: x["value"]).alias("would_strip"),
        (~F.col("complete") & F.col("numeric")).alias("overflow"),
        counted.alias("dropped_rows"),
        F.transform(kept, lambda x: x["value"]).alias("kept_values"),
    )
    if declarations is not None and cells is not None:
        beyond = declared_rows(cells, declarations, keys).withColumnRenamed("dropped_rows", "_beyond")
        out = out.join(beyond, keys, "left").withColumn(
            "dropped_rows", F.when(F.col("overflow"), F.coalesce("_beyond", F.lit(0).cast("long"))).otherwise(F.col("dropped_rows"))
        ).drop("_beyond")
    undeclared = F.size(F.array_except("stripped", "declared_values")) > 0
    only_by_stripping = undeclared & (F.col("plain_class") != F.col("class"))
    flat = (F.col("n_distinct") <= 1) | (F.col("nonnull") == 0)
    return out.withColumn(
        "audit_class", F.when(F.col("numeric") & (flat | only_by_stripping), "unresolved").otherwise(F.col("class"))
    )


def failure_hints(profiles: DataFrame) -> DataFrame:
    """Visible hints of the known failure modes; no class changes."""
    s = F.col("support")
    gaps = F.zip_with(s, F.slice(s, 2, F.greatest(F.size(s), F.lit(1))), lambda a, b: b["value"] - a["value"])
    steps = F.filter(gaps, lambda g: g.isNotNull())
    even = (F.size(steps) > 1) & (F.array_max(steps) - F.array_min(steps) < 1e-9)
    unit = F.col("n_unit") == F.col("nonnull")
    hint = (
        F.when((F.col("class") == "continuous") & (F.col("vmin") >= 0) & F.col("vmax").between(99, 100) & ~unit, "percent_scale")
        .when((F.col("class") == "ordinal") & unit & (F.col("n_distinct") > 2) & even, "evenly_spaced_share")
        .when((F.col("class") == "ordinal") & unit & (F.col("n_distinct") > 2), "coarse_share")
        .when(
            F.col("class").isin("continuous", "ordinal") & F.col("all_integer") & (F.col("vmin") >= 0)
            & (F.col("n_distinct") > 4) & (F.col("n_distinct") <= 25) & (F.abs(F.coalesce("skew", F.lit(0.0))) < 1),
            "symmetric_small_count",
        )
    )
    return profiles.withColumn("hint", F.coalesce(hint, F.lit("none")))


def with_codebook(profiles: DataFrame, codebook: DataFrame, keys: list[str]) -> DataFrame:
    """Report units and labels of a codebook beside profiles; no class changes."""
    said = codebook.select(*keys, F.col("unit").alias("codebook_unit"), F.col("kind").alias("codebook_kind"))
    out = profiles.join(said, keys, "left")
    return out.withColumn("codebook_differs", F.coalesce(F.col("codebook_kind") != F.col("class"), F.lit(False)))
