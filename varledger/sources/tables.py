"""Given tables, delimited files and derived columns of the workloads."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = (
    "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations"
).split()


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def delimited(spark: SparkSession, path: str, *, sep: str = ",") -> DataFrame:
    """A headered text table with every column as text, for lexical typing."""
    return spark.read.option("header", True).option("sep", sep).option("inferSchema", False).csv(path)


def order_quantities(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Per order: bulk units (quantity on lines of 45 and more), total and mean
    quantity, share of bulk and of returned lines, and lines."""
    q = F.col("l_quantity")
    bulk = F.sum(F.when(q >= 45, q).otherwise(0.0))
    return (
        table(spark, sf_dir, "lineitem").select("l_orderkey", "l_quantity", "l_returnflag").groupBy("l_orderkey")
        .agg(
            bulk.cast("long").alias("bulk_units"),
            F.sum(q).alias("total_quantity"),
            F.avg(q).alias("mean_quantity"),
            (bulk / F.sum(q)).alias("bulk_share"),
            F.avg((F.col("l_returnflag") == "R").cast("double")).alias("returned_share"),
            F.count("*").alias("lines"),
        )
    )


ORDER_QUANTITIES_SQL = """
SELECT l_orderkey, CAST(sum(CASE WHEN l_quantity >= 45 THEN l_quantity ELSE 0 END) AS BIGINT) AS bulk_units,
       sum(l_quantity) AS total_quantity, avg(l_quantity) AS mean_quantity,
       sum(CASE WHEN l_quantity >= 45 THEN l_quantity ELSE 0 END) / sum(l_quantity) AS bulk_share,
       avg(CASE WHEN l_returnflag = 'R' THEN 1.0 ELSE 0.0 END) AS returned_share, count(*) AS lines
FROM lineitem GROUP BY l_orderkey
"""


def priority_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Order priority digit with planted codes 99 and -9."""
    key = F.col("o_orderkey")
    digit = F.substring("o_orderpriority", 1, 1).cast("double")
    return table(spark, sf_dir, "orders").select(
        F.lit("priority").alias("col"),
        F.when(key % 50 == 0, 99.0).when(key % 50 == 1, -9.0).otherwise(digit).alias("value"),
    )


PRIORITY_SQL = """
SELECT 'priority' AS col, CASE WHEN o_orderkey % 50 = 0 THEN 99.0 WHEN o_orderkey % 50 = 1 THEN -9.0
       ELSE CAST(substring(o_orderpriority, 1, 1) AS DOUBLE) END AS v FROM orders
"""
