"""Screening rules over links, baselines, coverage, norms and recovery."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.rules import SCREEN_RULES


def rule_table(spark: SparkSession, rules=SCREEN_RULES) -> DataFrame:
    return spark.createDataFrame(rules, "family string, class string, tier string, stratum string")


def flagged(links: DataFrame, *, rules: DataFrame | None = None, version: str = "screen-1") -> DataFrame:
    """Flag records, one for each (deposit, estimator, outcome): deposit_id,
    estimator, family, outcome, class, tier, stratum, rule_version.

    A name that several files of a deposit hold links to each of them; the
    record takes the class of the file with most rows, ties by file.
    """
    rules = rules if rules is not None else rule_table(links.sparkSession)
    estimator = next(c for c in ("estimator", "command", "family") if c in links.columns)
    rows = [-F.col("n")] if "n" in links.columns else []
    file = [F.col("data_file")] if "data_file" in links.columns else []
    held = F.struct(*[c.alias(f"o{i}") for i, c in enumerate([*rows, *file])], F.col("class").alias("class"))
    records = links.groupBy("deposit_id", F.col(estimator).alias("estimator"), "family", F.col("column").alias("outcome")).agg(
        F.min(held)["class"].alias("class")
    )
    return records.join(F.broadcast(rules), ["family", "class"]).select(
        "deposit_id", "estimator", "family", "outcome", "class", "tier", "stratum", F.lit(version).alias("rule_version")
    )


def mismatch(family: str = "family", cls: str = "class") -> Column:
    """A linear estimator on an outcome that the screen's tiers name."""
    return (F.col(family) == "linear") & F.col(cls).isin(*[c for _, c, _, _ in SCREEN_RULES])


def baseline(kind: str) -> Column:
    """What simpler screens flag: the bare rule takes a linear fit of anything
    that is not continuous; a datatype screen only sees integers; a scale
    screen sees nominal and ordinal levels, and ratio ones as fit for it."""
    linear = F.col("family") == "linear"
    return {
        "screen": mismatch(),
        "bare": linear & (F.col("class") != "continuous"),
        "datatype": linear & F.col("all_integer"),
        "scale": linear & F.col("class").isin("binary", "categorical", "ordinal"),
    }[kind]


def confusion(cases: DataFrame, links: DataFrame, kind: str) -> DataFrame:
    """Cases by label against what a screen says of the linked outcome; a case
    without a link is not flagged."""
    said = links.withColumn("_said", baseline(kind)).groupBy("deposit_id", F.col("column").alias("outcome")).agg(
        F.bool_or("_said").alias("_said")
    )
    rows = cases.join(said, ["deposit_id", "outcome"], "left")
    truth, yes = F.col("label") == "mismatch", F.coalesce("_said", F.lit(False))
    return rows.agg(
        F.count_if(truth & yes).alias("tp"), F.count_if(~truth & yes).alias("fp"),
        F.count_if(truth & ~yes).alias("fn"), F.count_if(~truth & ~yes).alias("tn"),
    )


def norm_map(cases: DataFrame, families: list[str], *, cls: str = "class") -> DataFrame:
    """Outcome class by family, as counts."""
    return cases.groupBy(F.col(cls).alias("class")).pivot("family", families).agg(F.count(F.lit(1))).na.fill(0)


def family_norms(links: DataFrame, field: str) -> DataFrame:
    """Families used for each class within a field, with their share."""
    n = links.groupBy(field, "class", "family").agg(F.count("*").alias("n"))
    whole = F.sum("n").over(Window.partitionBy(field, "class"))
    return n.withColumn("share", F.round(F.col("n") / whole, 6))


def transformed(found: DataFrame, names: DataFrame) -> DataFrame:
    """Extension, off by default: responses that are a logged column, checked by
    a rule of their own (a log of a count with zeros)."""
    raw = F.regexp_extract("response", r"^log\(([A-Za-z_.][\w.]*)\)$", 1)
    return found.withColumn("column", raw).join(names.withColumnRenamed("name", "column"), ["deposit_id", "column"]).where(
        "class = 'count'"
    ).withColumn("alert_kind", F.lit("logged_count"))


def coverage(deposits: DataFrame, found: DataFrame, links: DataFrame) -> DataFrame:
    """Status of each deposit: none (no regression read), unmatched, flaggable.
    A lower bound on what the archive holds, since harvest and parser miss."""
    has = found.select("deposit_id").distinct().withColumn("_read", F.lit(True))
    base = links.where("family = 'linear'").select("deposit_id").distinct().withColumn("_base", F.lit(True))
    any_link = links.select("deposit_id").distinct().withColumn("_link", F.lit(True))
    out = deposits.join(has, "deposit_id", "left").join(any_link, "deposit_id", "left").join(base, "deposit_id", "left")
    status = F.when(F.col("_read").isNull(), "none").when(F.col("_link").isNull(), "unmatched").otherwise("flaggable")
    out = out.withColumn("status", status).withColumn("linear", F.col("_base").isNotNull()).drop("_read", "_link", "_base")
    return out.withColumn("limits", F.lit("lower bound"))


def recovery(cases: DataFrame, flags: DataFrame, deposits_flagged: DataFrame) -> DataFrame:
    """Of benchmark cases: whether their deposit and their exact outcome are
    flagged."""
    exact = flags.select("deposit_id", "outcome").distinct().withColumn("_exact", F.lit(True))
    some = deposits_flagged.select("deposit_id").distinct().withColumn("_some", F.lit(True))
    out = cases.join(some, "deposit_id", "left").join(exact, ["deposit_id", "outcome"], "left")
    return out.withColumn("deposit_flagged", F.col("_some").isNotNull()).withColumn(
        "outcome_flagged", F.col("_exact").isNotNull()
    ).drop("_some", "_exact")


def find_outcomes(links: DataFrame, cls: str, low: int, high: int, *, accepted: DataFrame | None = None) -> DataFrame:
    """Deposits with an outcome of a class on a number of rows in a range; with
    ``accepted`` (deposit_id, outcome of reviewed headline analyses) only those."""
    found = links.where((F.col("class") == cls) & F.col("n").between(low, high)).select(
        "deposit_id", F.col("column").alias("outcome"), "n"
    ).distinct()
    return found if accepted is None else found.join(accepted, ["deposit_id", "outcome"], "left_semi")
