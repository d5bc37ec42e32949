"""Ball sketches: one counter per node, grown until no register changes, and the sizes that they pass through."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from geocentra.errors import ParameterError
from geocentra.graph.model import Graph
from geocentra.propagate.fixpoint import BITS, MAXIMUM, LocalRounds, Rounds, rounds_of
from geocentra.sketch.registers import MD5_BITS, estimate, log2_registers, md5_bits, rank, register_of


@dataclass
class BallRun:
    """The result of a propagation: its rounds and how sizes are read off the counters."""

    rounds: Rounds | LocalRounds
    p: int
    runs: int
    kind: str = "hll"

    @property
    def truncated(self) -> bool:
        return self.rounds.truncated

    def registers(self) -> DataFrame:
        """node, run, reg, rho after the last round."""
        return self.rounds.final().select("node", "run", F.col("item").cast("int").alias("reg"), F.col("value").cast("int").alias("rho"))

    def profile(self) -> DataFrame:
        """node, run, t, size: a row for t = 0 and for each later t at which a register rose.

        Sums of 2**-rho are dyadic, so that running sums are exact and in any order.
        """
        changes = self.rounds.changes
        w = Window.partitionBy("node", "run").orderBy("t")
        if self.kind == "hll":
            half = lambda c: F.pow(F.lit(2.0), -F.col(c))
            step = changes.groupBy("node", "run", "t").agg(F.sum(half("value") - F.coalesce(half("old"), F.lit(1.0))).alias("s"), F.sum(F.col("old").isNull().cast("int")).alias("z"))
            s, z = F.lit(float(self.p)) + F.sum("s").over(w), F.lit(self.p) - F.sum("z").over(w)
            sums = step.select("node", "run", "t", s.alias("s"), z.alias("z"))
            return sums.select("node", "run", "t", estimate(F.col("s"), F.col("z"), self.p).alias("size"))
        # Bit patterns: the mean place of the lowest zero bit over p patterns.
        step = changes.groupBy("node", "run", "t").agg(F.sum(_lowest_zero("value") - F.when(F.col("old").isNull(), F.lit(0)).otherwise(_lowest_zero("old"))).alias("r"))
        mean = F.sum("r").over(w) / self.p
        size = F.pow(F.lit(2.0), mean) / PATTERN_BIAS
        return step.select("node", "run", "t", (size * self.p if self.kind == "fm_stochastic" else size).alias("size"))


# Fixed value: the published correction of bit-pattern counting.
PATTERN_BIAS = 0.77351


def _lowest_zero(column: str) -> F.Column:
    """The place of the lowest zero bit: with x the pattern, the ones of x & ~(x + 1)."""
    x = F.col(column)
    return F.bit_count(x.bitwiseAND(F.bitwise_not(x + 1)))


def seed_items(graph: Graph, runs: int, weighted: bool) -> DataFrame:
    """node, run, text: what each node's counter starts with. A node of weight w stands for w replicas."""
    nodes = graph.vertices.select(F.col("id").alias("node"), "weight", F.explode(F.sequence(F.lit(0), F.lit(runs - 1))).alias("run"))
    text = F.concat_ws(":", F.col("run").cast("string"), F.col("node").cast("string"))
    if not weighted:
        return nodes.select("node", "run", text.alias("text"))
    graph.check_weights()
    return nodes.select("node", "run", text.alias("text"), F.explode(F.sequence(F.lit(1), F.col("weight").cast("int"))).alias("i")).select("node", "run", F.concat_ws(":", "text", F.col("i").cast("string")).alias("text"))


def ball_sketches(graph: Graph, p: int = 64, runs: int = 1, direction: str = "in", hash: str = "md5", weighted: bool = False, propagation: str = "delta", max_iter: int | None = None) -> BallRun:
    """Counters of p registers for the balls around every node, in `runs` independent runs at once.

    Distances are those of other nodes to a node (direction="in") or from it ("out").
    All runs share one scan of the arcs in a round. Run k is seeded with k.
    """
    return BallRun(rounds_of(rank_seeds(graph, p, runs, hash, weighted), graph, MAXIMUM, direction, propagation, max_iter), p, runs)


def rank_seeds(graph: Graph, p: int, runs: int = 1, hash: str = "md5", weighted: bool = False) -> DataFrame:
    """node, run, item, value: the register and rank with which each counter starts."""
    log2_registers(p)
    if runs < 1:
        raise ParameterError(f"runs must be at least 1, not {runs}")
    reg, rho = register_of(F.col("text"), p, hash)
    return seed_items(graph, runs, weighted).select("node", "run", reg.alias("item"), rho.alias("value"))


def pattern_balls(graph: Graph, patterns: int = 32, runs: int = 1, direction: str = "in", averaging: str = "independent", propagation: str = "full", max_iter: int | None = None) -> BallRun:
    """The baseline of bit-pattern counters: whole-state rounds, union by bitwise or.

    averaging="independent" puts every item into every pattern (each with a hash of its
    own); "stochastic" puts it into one.
    """
    seeds, kind = pattern_seeds(graph, patterns, runs, averaging)
    return BallRun(rounds_of(seeds, graph, BITS, direction, propagation, max_iter), patterns, runs, kind)


def pattern_seeds(graph: Graph, patterns: int, runs: int = 1, averaging: str = "independent") -> tuple[DataFrame, str]:
    """node, run, item, value: the patterns with which each counter starts; and how sizes are read off them."""
    items = seed_items(graph, runs, False)
    if averaging == "independent":
        each = items.select("node", "run", "text", F.explode(F.sequence(F.lit(0), F.lit(patterns - 1))).alias("item"))
        h = md5_bits(F.concat_ws(":", "text", F.concat(F.lit("k"), F.col("item").cast("string"))))
        return each.select("node", "run", "item", _bit(rank(h, MD5_BITS)).alias("value")), "fm"
    if averaging == "stochastic":
        reg, rho = register_of(F.col("text"), max(16, patterns), "md5")
        return items.select("node", "run", (reg % patterns).alias("item"), _bit(rho).alias("value")), "fm_stochastic"
    raise ParameterError(f"averaging must be 'independent' or 'stochastic', not {averaging!r}")


def _bit(rho: F.Column) -> F.Column:
    return F.expr("1L") * F.pow(F.lit(2.0), rho - 1).cast("long")
