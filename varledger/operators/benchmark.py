"""Benchmark cases: candidate strata, re-checks, detector and profiler scores,
and why a screen missed a case."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .screen import mismatch


def candidates(links: DataFrame) -> DataFrame:
    """Links by stratum, where both a readable table (a profiled class) and code
    that names estimator and outcome exist."""
    linear = F.col("family") == "linear"
    stratum = (
        F.when(linear & (F.col("class") == "count"), "count-linear")
        .when((F.col("family") == "count") & (F.col("class") == "count"), "count-count")
        .when(linear & (F.col("class") == "proportion"), "proportion")
        .when(linear & F.col("class").isin("binary", "ordinal"), "binary/ordinal")
        .otherwise("other fields")
    )
    return links.where("class IS NOT NULL AND command IS NOT NULL").withColumn("stratum", stratum)


def recheck(cases: DataFrame, profiles: DataFrame, links: DataFrame) -> DataFrame:
    """Per case: does its deposit resolve, does its outcome still have the
    recorded class, does code confirm the link?"""
    known = profiles.select("deposit_id").distinct().withColumn("_d", F.lit(True))
    now = profiles.select("deposit_id", F.col("name").alias("outcome"), F.col("class").alias("class_now"))
    linked = links.select("deposit_id", F.col("column").alias("outcome"), "family").distinct().withColumn("_l", F.lit(True))
    out = cases.join(known, "deposit_id", "left").join(now, ["deposit_id", "outcome"], "left").join(
        linked, ["deposit_id", "outcome", "family"], "left"
    )
    return out.select(
        *cases.columns, F.col("_d").isNotNull().alias("resolves"),
        F.col("class_now").eqNullSafe(F.col("recorded_class")).alias("same_class"), F.col("_l").isNotNull().alias("link_confirmed"),
    )


def located(cases: DataFrame, profiles: DataFrame) -> DataFrame:
    """Cases, by label, whose outcome is a profiled column of their deposit."""
    known = profiles.select("deposit_id", F.col("name").alias("outcome")).distinct().withColumn("_k", F.lit(True))
    hit = F.count("_k")
    return cases.join(known, ["deposit_id", "outcome"], "left").groupBy("label").agg(
        F.count("*").alias("n_cases"), hit.alias("n_located"), F.round(hit / F.count("*"), 6).alias("rate")
    )


def _with_class(cases: DataFrame, profiles: DataFrame) -> DataFrame:
    """Cases with the class of their outcome (one profile a deposit and name)."""
    return cases.join(profiles.select("deposit_id", F.col("name").alias("outcome"), "class"), ["deposit_id", "outcome"], "left")


def agreement(cases: DataFrame, profiles: DataFrame) -> DataFrame:
    """How many outcomes a profiler finds and classes as recorded."""
    return _with_class(cases, profiles).agg(
        F.count("*").alias("n"), F.count("class").alias("n_located"),
        F.count_if(F.col("class").eqNullSafe(F.col("recorded_class"))).alias("n_same"),
    )


def detector(cases: DataFrame, profiles: DataFrame) -> DataFrame:
    """Precision and recall of the rule on labelled cases (mismatch or control),
    given a class for each outcome; one without is not flagged."""
    rows = _with_class(cases, profiles)
    said, true = F.coalesce(mismatch(), F.lit(False)), F.col("label") == "mismatch"
    tp = F.count_if(said & true)
    return rows.agg(
        tp.alias("tp"), F.round(tp / F.nullif(F.count_if(said), F.lit(0)), 6).alias("precision"),
        F.round(tp / F.nullif(F.count_if(true), F.lit(0)), 6).alias("recall"),
    )


def misses(
    cases: DataFrame, flags: DataFrame, *, read: DataFrame, read_uncapped: DataFrame, read_prefixed: DataFrame, names: DataFrame, names_uncapped: DataFrame
) -> DataFrame:
    """Mismatch cases whose exact outcome is not flagged, with the reason.

    ``read`` are the commands of the harvest, of all files, and with more
    prefixes accepted; ``names`` the columns of the harvest and of all files.
    The first that holds: the outcome was read and stored, so its class is not
    screened (class); it is stored in a file that was skipped (data_limit) or
    nowhere (built_in_code); its command is in a script that was skipped
    (script_limit) or behind another prefix (prefix); or no command has it.
    """
    missed = cases.where("label = 'mismatch'").join(flags.select("deposit_id", "outcome").distinct(), ["deposit_id", "outcome"], "left_anti")
    sets = {
        "_read": (read, "response"), "_all": (read_uncapped, "response"), "_more": (read_prefixed, "response"),
        "_held": (names, "name"), "_any": (names_uncapped, "name"),
    }
    for mark, (rows, column) in sets.items():
        known = rows.select("deposit_id", F.col(column).alias("outcome")).distinct().withColumn(mark, F.lit(True))
        missed = missed.join(known, ["deposit_id", "outcome"], "left")
    has = lambda c: F.col(c).isNotNull()
    reason: Column = (
        F.when(has("_read") & has("_held"), "class").when(has("_read") & has("_any"), "data_limit").when(has("_read"), "built_in_code")
        .when(has("_all"), "script_limit").when(has("_more"), "prefix").otherwise("no_command")
    )
    return missed.withColumn("reason", reason).drop(*sets)


def positives(cases: DataFrame, selected: DataFrame) -> DataFrame:
    """Questions (deposit, outcome) that are a mismatch case, that the rule
    selects, or that the rubric credits (``credited`` of the selected)."""
    member = cases.where("label = 'mismatch'").select("deposit_id", "outcome").distinct().withColumn("_m", F.lit(True))
    rows = member.join(selected.withColumn("_s", F.lit(True)), ["deposit_id", "outcome"], "full_outer")
    return rows.select(
        "deposit_id", "outcome", F.col("_m").isNotNull().alias("member"), F.col("_s").isNotNull().alias("selected"),
        F.coalesce("credited", F.lit(False)).alias("credited"),
    )
