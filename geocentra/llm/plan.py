"""Sizes from the data, not from constants, and where lineage is cut."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geocentra.plans.checkpoint import cut, cut_by, cut_dealt, shared_folder, small_batches

__all__ = ["cut", "cut_by", "cut_dealt", "load", "parts_for", "shared_folder", "small_batches", "text_bytes"]


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def text_bytes(docs: DataFrame, text: str) -> int:
    """All bytes of a text column: one scan of that column, one row to the driver."""
    return docs.agg(F.sum(F.octet_length(text)).alias("n")).first()["n"] or 0


def parts_for(spark: SparkSession, size: int, each: int) -> int:
    """Enough parts that one holds about `each` bytes, and no fewer than the session's shuffle partitions."""
    return max(int(spark.conf.get("spark.sql.shuffle.partitions")), math.ceil(size / each))
