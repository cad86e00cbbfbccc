"""One-pass evidence of columns: bounded aggregates, whole or by scope."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Two more than the decision limit: one for overflow, one for a null item.
SUPPORT = 27
TRACKED = 1000
BATCH = 40


def as_number(col: Column, kind: T.DataType, *, boolean_as_01: bool = False) -> Column:
    """Value as double; NaN and infinities are missing."""
    if isinstance(kind, T.BooleanType):
        col = col.cast("int") if boolean_as_01 else F.lit(None)
    x = col.cast("double")
    return F.when(F.isnan(x) | (F.abs(x) == float("inf")), None).otherwise(x)


def is_numeric(kind: T.DataType) -> bool:
    return isinstance(kind, T.NumericType)


def evidence(value: Column) -> Column:
    """Aggregate struct of a numeric column, in one pass and bounded state.

    ``support`` holds up to 27 values with counts.  It is exact where fewer
    values occur, which the counts prove: see :func:`with_support`.
    """
    return F.struct(
        F.count(F.lit(1)).alias("n"),
        F.count(value).alias("nonnull"),
        F.min(value).alias("vmin"),
        F.max(value).alias("vmax"),
        F.count_if(value < 0).alias("n_negative"),
        F.count_if((value >= 0) & (value <= 1)).alias("n_unit"),
        F.coalesce(F.bool_and(value == F.floor(value)), F.lit(False)).alias("all_integer"),
        F.avg(value).alias("mean"),
        F.var_pop(value).alias("variance"),
        F.skewness(value).alias("skew"),
        # Nulls come back as an item here; with_support() drops it.
        F.call_function("approx_top_k", value, F.lit(SUPPORT), F.lit(TRACKED)).alias("top"),
    )


def with_support(rows: DataFrame, *, cap: int = 25) -> DataFrame:
    """Turn ``e`` (evidence struct) into columns, with the exact support sorted
    by value where it is complete, else null, and the distinct count capped at
    one over the limit."""
    top = F.filter("e.top", lambda x: x["item"].isNotNull())
    known = F.aggregate(top, F.lit(0).cast("long"), lambda t, x: t + x["count"])
    rows = rows.withColumn("_top", top).withColumn(
        "complete", (known == F.col("e.nonnull")) & (F.size(top) <= cap)
    )
    sup = F.array_sort(F.transform("_top", lambda x: F.struct(x["item"].alias("value"), x["count"].alias("count"))))
    fields = ["n", "nonnull", "vmin", "vmax", "n_negative", "n_unit", "all_integer", "mean", "variance", "skew"]
    return rows.select(
        *[c for c in rows.columns if c not in ("e", "_top", "complete")],
        *[F.col(f"e.{f}").alias(f) for f in fields],
        "complete",
        F.when(F.col("complete"), sup).alias("support"),
        F.when(F.col("complete"), F.size("_top")).otherwise(cap + 1).cast("long").alias("n_distinct"),
    )


def profile_columns(df: DataFrame, columns: list[str] | None = None, *, by: list[str] | None = None) -> DataFrame:
    """Evidence of each column of a table: (scope..., column, declared, numeric,
    evidence).  One scan for up to BATCH columns; more columns take further
    scans of their own columns only."""
    by = by or []
    columns = columns or [c for c in df.columns if c not in by]
    kinds = {f.name: f.dataType for f in df.schema.fields}
    out = None
    for lo in range(0, len(columns), BATCH):
        part = columns[lo : lo + BATCH]
        aggs = []
        for i, c in enumerate(part):
            numeric = is_numeric(kinds[c])
            x = as_number(F.col(f"`{c}`"), kinds[c]) if numeric else F.lit(None).cast("double")
            n_known = F.count(F.col(f"`{c}`"))
            aggs.append(
                F.struct(
                    F.lit(c).alias("column"),
                    F.lit(kinds[c].simpleString()).alias("declared"),
                    F.lit(numeric).alias("numeric"),
                    n_known.alias("present"),
                    evidence(x).alias("e"),
                ).alias(f"c{i}")
            )
        wide = df.groupBy(*by).agg(*aggs) if by else df.agg(*aggs)
        rows = wide.select(*by, F.inline(F.array(*[f"c{i}" for i in range(len(part))])))
        out = rows if out is None else out.unionByName(rows)
    return with_support(out)


def profile_cells(cells: DataFrame, keys: list[str], *, value: str = "value", cap: int = 25) -> DataFrame:
    """Evidence of long cells (keys..., value): one partial aggregate, one
    exchange of a row for each group and task, whatever the group sizes."""
    rows = cells.groupBy(*keys).agg(evidence(as_number(F.col(value), T.DoubleType())).alias("e"))
    return with_support(rows.withColumn("numeric", F.lit(True)), cap=cap)


def type_flags(df: DataFrame, columns: list[str] | None = None) -> DataFrame:
    """Lexical datatype of text columns: does every present value read as an
    integer, a number, a boolean or a date?"""
    columns = columns or df.columns
    structs = []
    for c in columns:
        x = F.col(f"`{c}`").cast("string")
        tests = {
            "is_integer": x.try_cast("bigint").isNotNull(),
            "is_double": x.try_cast("double").isNotNull(),
            "is_boolean": F.lower(x).isin("true", "false"),
            "is_date": x.try_cast("date").isNotNull(),
        }
        structs.append(
            F.struct(
                F.lit(c).alias("column"),
                *[F.coalesce(F.bool_and(F.when(x.isNotNull(), t)), F.lit(False)).alias(k) for k, t in tests.items()],
            )
        )
    return df.agg(F.array(*structs).alias("a")).select(F.inline("a")).withColumn("xsd_datatype", datatype())


def datatype() -> Column:
    return (
        F.when(F.col("is_integer"), "Integer").when(F.col("is_double"), "Double")
        .when(F.col("is_boolean"), "Boolean").when(F.col("is_date"), "Date").otherwise("String")
    )


def distinct_estimates(df: DataFrame, columns: list[str], *, rsd: float = 0.05) -> DataFrame:
    """HyperLogLog estimates beside exact capped support."""
    aggs = [F.struct(F.lit(c).alias("column"), F.approx_count_distinct(f"`{c}`", rsd).alias("estimate")) for c in columns]
    return df.agg(F.array(*aggs).alias("a")).select(F.inline("a"))
