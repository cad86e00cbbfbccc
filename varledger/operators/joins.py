"""How tables that grow with the archive are joined."""

from __future__ import annotations

from pyspark.sql import DataFrame


def grown(rows: DataFrame) -> DataFrame:
    """A side that has a row for each deposit or more, for a join that merges.
    The optimizer sizes texts built from a key by the scan of that key, and
    would send millions of them through the driver."""
    return rows.hint("merge")
