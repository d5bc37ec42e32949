"""Baselines by traversal: exact distances, sampled pivots, and all-distances sketches."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from geocentra.graph.model import Graph
from geocentra.plans.checkpoint import cut
from geocentra.propagate import local as L
from geocentra.propagate import sweep
from geocentra.propagate.fixpoint import PRESENCE, Rounds, fixpoint, oriented
from geocentra.sketch.registers import MD5_BITS, md5_bits


@dataclass
class ExactRun:
    """Visits in rounds of tables; or, where the arcs fit in a task, visits that each use makes anew.

    Such visits start at all nodes against the arcs, so that a node's distances are found
    in one task (`back`), or at the given sources along them.
    """

    rounds: Rounds | None = None
    roots: DataFrame | None = None
    blob: DataFrame | None = None
    back: bool = False

    def _visits(self, kind: str, schema: str, step: int = 0) -> DataFrame:
        return L.dealt(self.roots, self.blob, L.n_tasks(self.roots.sparkSession), sweep.visits(kind, schema, step), schema)

    def pairs(self) -> DataFrame:
        """node, source, dist for all sources from which a node is reached, itself included."""
        if self.rounds is not None:
            return self.rounds.changes.select("node", F.col("item").alias("source"), F.col("t").alias("dist"))
        node, source = ("root", "found") if self.back else ("found", "root")
        return self._visits("pairs", L.PAIRS).select(F.col(node).alias("node"), F.col(source).alias("source"), "dist")

    def counts(self) -> DataFrame:
        """node, run, t, n: how many sources lie at each distance. With visits from all nodes no pair becomes a row."""
        if self.back:
            return self._visits("counts", L.COUNTS).select(F.col("root").alias("node"), F.lit(0).alias("run"), "t", F.col("n").cast("double").alias("n"))
        return self.pairs().groupBy("node", F.lit(0).alias("run"), F.col("dist").alias("t")).agg(F.count(F.lit(1)).cast("double").alias("n"))

    def sums(self) -> DataFrame:
        """node, run, sum_dist, harmonic, coreach: what `counts` add up to. With visits from all nodes no distance becomes a row either."""
        if self.back:
            return self._visits("sums", L.SUMS).select(F.col("root").alias("node"), F.lit(0).alias("run"), "sum_dist", "harmonic", "coreach")
        t, n = F.col("t"), F.col("n")
        return self.counts().groupBy("node", "run").agg(F.sum(n * t).alias("sum_dist"), F.coalesce(F.sum(F.when(t > 0, n / t)), F.lit(0.0)).alias("harmonic"), F.sum("n").alias("coreach"))

    def outermost(self, step: int) -> DataFrame:
        """node, source, dist: pairs among which are, of all pairs of a node, one of the largest dist * step - source and the nearest."""
        if self.back:
            return self._visits("outermost", L.PAIRS, step).select(F.col("root").alias("node"), F.col("found").alias("source"), "dist")
        return self.pairs()


def exact_pairs(graph: Graph, sources: DataFrame | None = None, direction: str = "in") -> ExactRun:
    """Breadth-first visits from all `sources` (id; default every node) at once, by frontiers.

    If the arcs fit in a task, pairs are found anew by each use and are not stored. Else
    they cost a row each in tables of the shared folder; pairs that are not reached cost
    nothing.
    """
    nodes = graph.vertices.select("id") if sources is None else sources.select("id")
    seeds = nodes.select(F.col("id").cast("long").alias("node"), F.lit(0).alias("run"), F.col("id").cast("long").alias("item"), F.lit(0).cast("long").alias("value"))
    arcs = cut(oriented(graph, direction))
    if arcs.count() > L.LOCAL_ARCS:
        return ExactRun(fixpoint(seeds, Graph(graph.vertices, arcs.select(F.col("tx").alias("src"), F.col("rx").alias("dst"))), PRESENCE))
    back = sources is None
    along = arcs.select(F.col("rx").alias("tx"), F.col("tx").alias("rx")) if back else arcs
    return ExactRun(roots=cut(seeds), blob=cut(L.packed_graph(along)), back=back)


def pivots(graph: Graph, k: int, seed: int = 0) -> DataFrame:
    """The k nodes of least hash: a uniform sample that does not depend on the partitioning."""
    h = md5_bits(F.concat_ws(":", F.lit(seed), F.col("id").cast("string")))
    return graph.vertices.select("id", h.alias("h")).orderBy("h", "id").limit(k).select("id")


def sampled_bfs(graph: Graph, k: int, seed: int = 0, direction: str = "in") -> DataFrame:
    """node, sum_dist, harmonic, coreach scaled up from k pivots; their guarantees are weak if the graph is disconnected."""
    chosen = pivots(graph, k, seed)
    pairs = exact_pairs(graph, chosen, direction).pairs()
    scale = F.lit(float(graph.vertices.count())) / k
    found = pairs.groupBy("node").agg(
        (scale * F.sum("dist")).alias("sum_dist"), (scale * F.sum(F.when(F.col("dist") > 0, 1 / F.col("dist")).otherwise(0.0))).alias("harmonic"), (scale * F.count(F.lit(1))).alias("coreach")
    )
    zero = F.lit(0.0)
    return graph.vertices.select(F.col("id").alias("node")).join(found, "node", "left").select("node", *(F.coalesce(c, zero).alias(c) for c in ("sum_dist", "harmonic", "coreach")))


def all_distances_sketch(graph: Graph, k: int = 16, seed: int = 0, direction: str = "in") -> DataFrame:
    """node, source, dist, rank, tau: bottom-k all-distances sketches.

    A source enters a node's sketch if fewer than k of those at no larger distance have a
    smaller rank; tau, the kth smallest rank before it (1 if there are fewer), is the
    probability with which it enters. Ranks are hashes scaled to (0, 1).
    """
    h = lambda c: md5_bits(F.concat_ws(":", F.lit(seed), F.col(c).cast("string")))

    def smallest(changed: DataFrame, state: DataFrame, t: int) -> DataFrame:
        both = changed.select("node", "run", "item", "new", "old", F.lit(1).alias("late")).unionByName(state.select("node", "run", "item", F.lit(None).cast("long").alias("new"), F.lit(None).cast("long").alias("old"), F.lit(0).alias("late")))
        w = Window.partitionBy("node").orderBy(h("item"), "item")
        return both.withColumn("place", F.row_number().over(w)).where((F.col("late") == 1) & (F.col("place") <= k)).select("node", "run", "item", "new", "old")

    seeds = graph.vertices.select(F.col("id").alias("node"), F.lit(0).alias("run"), F.col("id").alias("item"), F.lit(0).alias("value"))
    rounds = fixpoint(seeds, graph, PRESENCE, direction, prune=smallest)
    entries = rounds.changes.select("node", F.col("item").alias("source"), F.col("t").alias("dist"), h("item").alias("h"))
    # In a sketch an entry's forerunners are those nearer, or as near and of smaller rank.
    before = Window.partitionBy("node").orderBy("dist", "h", "source").rowsBetween(Window.unboundedPreceding, -1)
    earlier = F.array_sort(F.collect_list("h").over(before))
    tau = F.when(F.size(earlier) < k, F.lit(1.0)).otherwise(F.element_at(earlier, k) / F.lit(float(1 << MD5_BITS)))
    return entries.select("node", "source", "dist", (F.col("h") / F.lit(float(1 << MD5_BITS))).alias("rank"), tau.alias("tau"))


def ads_estimate(sketch: DataFrame, f=None) -> DataFrame:
    """node, value: the sum of f(dist) over all sources but the node, by inverse probabilities; f defaults to 1/dist."""
    gain = (F.lit(1.0) / F.col("dist")) if f is None else f(F.col("dist"))
    return sketch.groupBy("node").agg(F.coalesce(F.sum(F.when(F.col("dist") > 0, gain / F.col("tau"))), F.lit(0.0)).alias("value"))
