"""The gate sequence from evidence to class, as one Column expression."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.rules import CENSUS, SCALE_LEVEL, Gates


def core_values(rules: Gates, support: str = "support") -> Column:
    """Support without the listed codes and what lies outside the core range."""
    codes = F.array(*[F.lit(float(s)) for s in rules.sentinels])
    return F.filter(
        F.col(support),
        lambda x: ~F.array_contains(codes, x["value"]) & (x["value"] >= rules.core_low) & (x["value"] <= rules.core_high),
    )


def gate_chain(rules: Gates) -> Column:
    """Class by the gates alone, from raw statistics."""
    integer, low = F.col("all_integer"), F.col("vmin") >= 0
    d, skew = F.col("n_distinct"), F.coalesce(F.col("skew"), F.lit(0.0))
    count = integer & low
    if rules.count_skew is not None:
        count &= skew >= rules.count_skew
    if rules.count_distinct is not None:
        count &= d > rules.count_distinct
    if rules.count_max is not None:
        count &= F.col("vmax") < rules.count_max
    unit = F.col("n_unit") == F.col("nonnull")
    chain = (
        F.when(d <= rules.binary_distinct, "binary")
        .when(integer & low & (F.col("vmax") <= rules.ordinal_max) & (d <= rules.ordinal_distinct), "ordinal")
        .when(count, "count")
    )
    if rules.unit_distinct is not None:
        chain = chain.when(unit & (d > rules.unit_distinct), "proportion").when(unit, "ordinal")
    else:
        chain = chain.when(unit, "proportion")
    return chain.when(low & (skew >= rules.heavy_skew), "heavy-tailed").otherwise("continuous")


def classified(profiles: DataFrame, *, rules: Gates = CENSUS) -> DataFrame:
    """Add class, reason, stripped (values the sentinel step leaves out) and
    rule_version to profiles (see evidence.with_support)."""
    core = core_values(rules)
    size = F.size(core)
    eligible = F.col("numeric") & F.col("all_integer") & F.col("complete") & (F.col("nonnull") > 0)
    eligible &= F.lit(rules.strip) & (size > 0)
    rated = (F.element_at(core, 1)["value"] >= 0) & (F.element_at(core, -1)["value"] <= rules.ordinal_max)
    by_core = eligible & (size <= rules.binary_distinct)
    by_rate = eligible & rated & (size <= rules.ordinal_distinct)
    missing = F.col("nonnull") == 0
    out = profiles.withColumn(
        "class",
        F.when(~F.col("numeric") | missing, "categorical").when(by_core, "binary").when(by_rate, "ordinal").otherwise(gate_chain(rules)),
    )
    out = out.withColumn(
        "reason",
        F.when(~F.col("numeric"), "not_numeric").when(missing, "all_missing").when(by_core | by_rate, "small_support").otherwise("gates"),
    )
    gone = F.transform(F.array_except(F.col("support"), core), lambda x: x["value"])
    return out.withColumn("stripped", F.when(by_core | by_rate, gone).otherwise(F.array().cast("array<double>"))).withColumn(
        "rule_version", F.lit(rules.version)
    )


def scale_level(cls: str = "class") -> Column:
    pairs = [x for k, v in SCALE_LEVEL.items() for x in (F.lit(k), F.lit(v))]
    return F.create_map(*pairs)[F.col(cls)]


def declared_datatype(declared: str = "declared") -> Column:
    d = F.col(declared)
    return (
        F.when(d.isin("tinyint", "smallint", "int", "bigint"), "Integer")
        .when(d.isin("float", "double") | d.startswith("decimal"), "Double")
        .when(d == "boolean", "Boolean").when(d == "date", "Date").when(d.startswith("timestamp"), "DateTime")
        .otherwise("String")
    )


def described(profiles: DataFrame, *, name: str = "column", datatype: Column | None = None) -> DataFrame:
    """The class beside what a stock description says, which stays: name,
    datatype, scale, class, and all of them as one JSON document."""
    kind = declared_datatype() if datatype is None else datatype
    out = profiles.select(F.col(name).alias("name"), kind.alias("datatype"), scale_level().alias("scale"), "class")
    return out.withColumn("description", F.to_json(F.struct("name", "datatype", "scale", "class")))


def structural_kind(*, share: float = 0.8) -> Column:
    """Identifier, measure, dimension or attribute from a profile with a distinct
    ``estimate``: an identifier is integral or text and differs in nearly every
    row, a dimension has few values, a measure is another number."""
    nearly_all = (F.col("estimate") >= share * F.col("present")) & (F.col("present") > 25)
    coded = ~F.col("numeric") | F.col("all_integer")
    return (
        F.when(nearly_all & coded, "identifier").when(F.col("estimate") <= 25, "dimension")
        .when(F.col("numeric"), "measure").otherwise("attribute")
    )


def transitions(first: DataFrame, second: DataFrame, keys: list[str]) -> DataFrame:
    """How many profiles move from one class to another between two rule
    tables over the same evidence."""
    a = first.select(*keys, F.col("class").alias("class_from"))
    b = second.select(*keys, F.col("class").alias("class_to"))
    return a.join(b, keys).groupBy("class_from", "class_to").agg(F.count("*").alias("n"))
