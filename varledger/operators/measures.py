"""Measures of accuracy, agreement and yield, in closed form on counts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

#: Two-sided 95% point of the normal distribution.
Z95 = 1.959963984540054


def wilson(positive: Column, n: Column, *, z: float = Z95) -> tuple[Column, Column]:
    """Bounds of the Wilson score interval."""
    p = positive / n
    middle = p + z * z / (2 * n)
    half = z * F.sqrt(p * (1 - p) / n + z * z / (4 * n * n))
    return (middle - half) / (1 + z * z / n), (middle + half) / (1 + z * z / n)


def precision(verdicts: DataFrame, by: list[str], *, positive: str = "positive") -> DataFrame:
    counts = verdicts.groupBy(*by).agg(F.count("*").alias("n"), F.count_if(F.col(positive)).alias("k"))
    low, high = wilson(F.col("k").cast("double"), F.col("n").cast("double"))
    return counts.select(
        *by, "n", "k", F.round(F.col("k") / F.col("n"), 6).alias("share"),
        F.round(low, 6).alias("low"), F.round(high, 6).alias("high"),
    )


def weighted_precision(strata: DataFrame, *, weight: str = "weight") -> DataFrame:
    """Mean of stratum precisions (k of n) under given weights."""
    w = F.col(weight)
    return strata.agg(F.round(F.sum(w * F.col("k") / F.col("n")) / F.sum(w), 6).alias("precision"), F.sum(w).alias("weight"))


def inverse_record_precision(verdicts: DataFrame, by: list[str]) -> DataFrame:
    """Each record counts one over the records of its question."""
    w = 1 / F.col("n_records")
    return verdicts.groupBy(*by).agg(F.round(F.sum(w * F.col("positive").cast("double")) / F.sum(w), 6).alias("precision"))


def kappa(pairs: DataFrame, a: str, b: str) -> DataFrame:
    """Raw agreement and Cohen's kappa of two 0/1 raters."""
    x, y = F.col(a).cast("double"), F.col(b).cast("double")
    m = pairs.agg(F.count("*").alias("n"), F.avg((x == y).cast("double")).alias("po"), F.avg(x).alias("pa"), F.avg(y).alias("pb"))
    pe = F.col("pa") * F.col("pb") + (1 - F.col("pa")) * (1 - F.col("pb"))
    return m.select("n", F.round("po", 6).alias("agreement"), F.round((F.col("po") - pe) / (1 - pe), 6).alias("kappa"))


def collapse(verdicts: DataFrame, *, favourable: bool) -> DataFrame:
    """One verdict of each (session, question): a session at odds with itself
    counts as positive if favourable, else as null (a disagreement)."""
    agg = verdicts.groupBy("session", "question_id").agg(F.max("positive").alias("hi"), F.min("positive").alias("lo"))
    odd = F.col("hi") != F.col("lo")
    return agg.select("session", "question_id", F.when(odd, F.lit(True if favourable else None)).otherwise(F.col("hi")).alias("positive"))


def stratified_draw(rows: DataFrame, stratum: str, key: str, size: int) -> DataFrame:
    """The ``size`` rows of each stratum whose keys have the lowest MD5: the
    same draw at any partitioning."""
    order = Window.partitionBy(stratum).orderBy(F.md5(F.col(key).cast("string")), key)
    return rows.withColumn("draw", F.row_number().over(order)).where(F.col("draw") <= size)
