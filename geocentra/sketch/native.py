"""Balls by Spark's own sketches: convenient, not portable, and rounded to whole numbers."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from geocentra.errors import ParameterError
from geocentra.graph.model import Graph
from geocentra.plans.checkpoint import cut
from geocentra.propagate.fixpoint import oriented


#: The mode (the low two bits of a counter's eighth byte) in which it holds registers, not a list of what it met.
REGISTERS = 2
#: Rounds of one plan: a job makes so many, and only after it is it asked which was the last that changed anything.
ROUNDS_A_JOB = 8


def _differ(now: Column, was: Column) -> Column:
    """Whether a counter met anything new. Lists keep no fixed order, so that their sizes, which are exact, are compared."""
    lists = F.conv(F.hex(F.substring(now, 8, 1)), 16, 10).cast("int").bitwiseAND(3) != REGISTERS
    return F.when(lists, F.hll_sketch_estimate(now) != F.hll_sketch_estimate(was)).otherwise(now != was)


def native_balls(graph: Graph, lg_k: int = 6, direction: str = "in", max_iter: int | None = None) -> DataFrame:
    """node, t, size: estimates for every radius at which a counter changes, by whole rounds until none does.

    A counter meets itself after each round: registers then no longer carry the estimate
    that depends on the order in which they were met. A node's own counter reaches it along an arc to itself, and brings the counters of
    the job's earlier rounds with it. A `max_iter` that is reached first is an error: the
    result would be cut short.
    """
    vertices = graph.vertices.select(F.col("id").alias("tx"), F.col("id").alias("rx"))
    arcs = cut(oriented(graph, direction).select("tx", "rx").unionByName(vertices).distinct())
    own = F.col("tx") == F.col("rx")
    nodes = arcs.where(own).select(F.col("tx").alias("node"))
    state = cut(nodes.groupBy("node").agg(F.hll_sketch_agg("node", F.lit(lg_k)).alias("sk")))
    profile = state.select("node", F.lit(0).alias("t"), F.hll_sketch_estimate("sk").alias("size"))
    t = 0
    while True:
        steps = state.select("node", "sk", F.array("sk").alias("sks"))
        for _ in range(ROUNDS_A_JOB):
            sent = steps.join(arcs, F.col("node") == F.col("tx")).select(F.col("rx").alias("node"), "sk", F.when(own, F.col("sks")).alias("sks"))
            then = sent.groupBy("node").agg(F.hll_union_agg("sk").alias("sk"), F.max("sks").alias("sks"))
            then = then.select("node", F.hll_union("sk", "sk").alias("sk"), "sks")
            steps = then.select("node", "sk", F.concat("sks", F.array("sk")).alias("sks"))
        steps = cut(steps)
        # The counters themselves, not their rounded sizes, tell whether a round changed anything.
        each = steps.select("node", F.explode(F.transform(F.sequence(F.lit(1), F.lit(ROUNDS_A_JOB)), lambda i: F.struct(i.alias("i"), F.element_at("sks", i).alias("was"), F.element_at("sks", i + 1).alias("now")))).alias("s"))
        rose = each.where(_differ(F.col("s.now"), F.col("s.was"))).select("node", (F.col("s.i") + t).alias("t"), F.hll_sketch_estimate("s.now").alias("size"))
        changed = {r["t"] for r in rose.select("t").distinct().collect()}
        last = t
        while last + 1 in changed:
            last += 1
        if max_iter is not None and last > max_iter:
            raise ParameterError(f"counters still change after max_iter={max_iter} rounds")
        profile = profile.unionByName(rose.where(F.col("t") <= last))
        if last < t + ROUNDS_A_JOB:
            return profile
        t, state = last, steps.select("node", "sk")
