"""Orders of whole tables and of groups without a bound, without a window over either."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from geocentra.plans.checkpoint import cut


def clean_arcs(arcs: DataFrame) -> DataFrame:
    return arcs.where("src is not null and dst is not null and src <> dst").distinct()


def succession(rows: DataFrame, group: list[Column], order: list[str], node: str) -> DataFrame:
    """node -> the node of the next row of its group: windows are per group, never global."""
    following = F.lead(node).over(Window.partitionBy(*group).orderBy(*order))
    return clean_arcs(rows.select(F.col(node).alias("src"), following.alias("dst")))


def succession_in_steps(rows: DataFrame, group: Column, step: Column, order: list[str], node: str) -> DataFrame:
    """As succession for groups without a bound: windows are over steps of a group, then over its steps.

    `step` must not decrease with `order`. The last row of a step is followed by the
    first of the group's next step, and only steps, not rows, are ordered within a group.
    """
    placed = rows.select(group.alias("grp"), step.alias("step"), *order, F.col(node).alias("node"))
    key = F.struct(*order, "node")
    first = placed.groupBy("grp", "step").agg(F.min(key).alias("first"), F.max(key).alias("last"))
    after = F.lead("first").over(Window.partitionBy("grp").orderBy("step"))
    across = first.select(F.col("last.node").alias("src"), after.alias("f")).select("src", F.col("f.node").alias("dst"))
    within = placed.select(F.col("node").alias("src"), F.lead("node").over(Window.partitionBy("grp", "step").orderBy(*order, "node")).alias("dst"))
    return clean_arcs(within.unionByName(across))


def numbered(rows: DataFrame, order: list[Column], name: str) -> DataFrame:
    """The rows with their place (from 1) in a global order: ranges are sorted apart, and their sizes added up."""
    placed = cut(rows.orderBy(*order).withColumn(name, F.monotonically_increasing_id()))
    part = F.shiftright(name, 33)
    sizes = placed.groupBy(part.alias("part")).agg(F.count(F.lit(1)).alias("k"))
    # One row a partition.
    before = sizes.select("part", (F.sum("k").over(Window.orderBy("part")) - F.col("k")).alias("before"))
    return placed.withColumn("part", part).join(F.broadcast(before), "part").withColumn(name, F.col("before") + F.col(name).bitwiseAND(F.lit((1 << 33) - 1)) + 1).drop("part", "before")
