"""Derived variables with the steps they come from, checked on all rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def derive(df: DataFrame, name: str, op: str, inputs: list[str], expression: Column) -> tuple[DataFrame, DataFrame]:
    """The table with the derived column, and its lineage edges."""
    spark = df.sparkSession
    edges = [(name, f"{op}:{name}", op, c, i) for i, c in enumerate(inputs)]
    lineage = spark.createDataFrame(
        edges, "derived_variable string, step_id string, op string, input_variable string, position int"
    )
    return df.withColumn(name, expression), lineage


def verify(df: DataFrame, name: str, expression: Column) -> DataFrame:
    """Rows and rows on which the stored column differs from the step."""
    return df.agg(
        F.lit(name).alias("derived_variable"),
        F.count("*").alias("n_rows"),
        F.count_if(~F.col(name).eqNullSafe(expression)).alias("n_mismatch"),
        F.count_if(F.col(name) < 0).alias("n_negative"),
    )
