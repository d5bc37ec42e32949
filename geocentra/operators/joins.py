"""Joins by other conditions than equality."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def dominated(rows: DataFrame, a: str, b: str) -> DataFrame:
    """node, better: how many rows are larger in both columns, for nodes with any.

    Only distinct pairs of values meet, with how often each occurs.
    """
    values = rows.groupBy(a, b).agg(F.count(F.lit(1)).alias("n"))
    larger = values.select(F.col(a).alias("a2"), F.col(b).alias("b2"), "n")
    better = values.select(a, b).join(larger, (F.col("a2") > F.col(a)) & (F.col("b2") > F.col(b))).groupBy(a, b).agg(F.sum("n").alias("better"))
    return rows.join(better, [a, b]).select("node", "better")
