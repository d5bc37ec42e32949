"""Edge lists in and out: explicit schemas, malformed rows set aside, buckets, adjacency rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geocentra.graph.model import Graph

SCHEMA = "src long, dst long"


def read_edges(spark: SparkSession, path: str, format: str = "csv", sep: str = ",") -> tuple[DataFrame, DataFrame]:
    """(arcs, rejected): rows that fit the schema, and the raw lines of those that do not. Nothing is inferred."""
    if format == "text":
        lines = spark.read.text(path)
        ends = F.split(F.trim("value"), r"\s+")
        parsed = lines.select("value", F.expr("try_cast(split(trim(value), '\\\\s+')[0] AS long)").alias("src"), F.expr("try_cast(split(trim(value), '\\\\s+')[1] AS long)").alias("dst"), F.size(ends).alias("k"))
        good = F.col("src").isNotNull() & F.col("dst").isNotNull() & (F.col("k") == 2)
        return parsed.where(good).select("src", "dst"), parsed.where(~good).select("value")
    options = {"mode": "PERMISSIVE", "columnNameOfCorruptRecord": "rejected"}
    reader = spark.read.schema(SCHEMA + ", rejected string").options(**options)
    rows = reader.csv(path, sep=sep) if format == "csv" else reader.json(path) if format == "json" else spark.read.format(format).schema(SCHEMA).load(path).withColumn("rejected", F.lit(None).cast("string"))
    bad = F.col("rejected").isNotNull() | F.col("src").isNull() | F.col("dst").isNull()
    return rows.where(~bad).select("src", "dst"), rows.where(bad).select(F.col("rejected").alias("value"))


def write_edges(arcs: DataFrame, path: str, format: str = "parquet", sep: str = ",") -> None:
    """An edge list as parquet, orc, csv, json or text."""
    rows = arcs.select("src", "dst")
    if format == "text":
        rows.select(F.concat_ws(" ", F.col("src").cast("string"), F.col("dst").cast("string"))).write.mode("overwrite").text(path)
    elif format == "csv":
        rows.write.mode("overwrite").csv(path, sep=sep)
    else:
        rows.write.mode("overwrite").format(format).save(path)


def write_partitioned(arcs: DataFrame, path: str, parts: int = 4) -> None:
    """Parquet partitioned by a hash of the sender, sorted within files, so that row groups are narrow."""
    rows = arcs.select("src", "dst", F.pmod(F.xxhash64("src"), F.lit(parts)).cast("int").alias("part"))
    rows.repartition(parts, "part").sortWithinPartitions("src", "dst").write.mode("overwrite").partitionBy("part").parquet(path)


def write_bucketed(graph: Graph, name: str, by: str = "src", buckets: int = 8) -> DataFrame:
    """A managed table of arcs bucketed and sorted by the sending end: rounds then read it without a shuffle."""
    graph.arcs.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(name)
    return graph.arcs.sparkSession.table(name)


def adjacency(arcs: DataFrame) -> DataFrame:
    """node, successors (ascending), degree. For nodes of bounded degree: a hub's list is one row."""
    return arcs.groupBy(F.col("src").alias("node")).agg(F.sort_array(F.collect_list("dst")).alias("successors")).select("node", "successors", F.size("successors").alias("degree"))
