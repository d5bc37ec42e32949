"""Centralities from distance counts (node, run, t, n): how many nodes, or how much weight, lie at distance t.

Exact traversals and ball sketches both give distance counts, and every measure is one
aggregation over them. A missing t counts nothing. t = 0 is the node itself.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from geocentra.errors import ParameterError
from geocentra.operators.ordered import numbered
from geocentra.plans.checkpoint import cut
from geocentra.propagate.balls import BallRun
from geocentra.propagate.exact import ExactRun

Discount = Callable[[Column], Column]


def reciprocal(t: Column) -> Column:
    return 1.0 / t


def logarithmic(t: Column) -> Column:
    return 1.0 / F.log2(t + 1)


def quadratic(t: Column) -> Column:
    return 1.0 / (t * t)


def constant(t: Column) -> Column:
    return F.lit(1.0)


def exponential(base: float) -> Discount:
    return lambda t: F.pow(F.lit(base), t)


DISCOUNTS: dict[str, Discount] = {"reciprocal": reciprocal, "logarithmic": logarithmic, "quadratic": quadratic, "constant": constant, "exponential": exponential(0.5)}


def sketch_counts(run: BallRun, clamp: bool = False) -> DataFrame:
    """node, run, t, n from a sketch: differences of the sizes of consecutive balls.

    They may be slightly negative where the size estimator switches; `clamp` cuts them
    off at 0, at the price of sums that no longer telescope.
    """
    size = F.col("size")
    n = size - F.coalesce(F.lag("size").over(Window.partitionBy("node", "run").orderBy("t")), F.lit(0.0))
    return run.profile().select("node", "run", "t", (F.greatest(n, F.lit(0.0)) if clamp else n).alias("n"))


def exact_counts(pairs: DataFrame, weights: DataFrame | None = None) -> DataFrame:
    """node, run, t, n from exact pairs; with weights (id, weight) n is the weight of the sources."""
    if weights is None:
        return pairs.groupBy("node", F.lit(0).alias("run"), F.col("dist").alias("t")).agg(F.count(F.lit(1)).cast("double").alias("n"))
    w = weights.select(F.col("id").alias("source"), "weight")
    return pairs.join(w, "source").groupBy("node", F.lit(0).alias("run"), F.col("dist").alias("t")).agg(F.sum("weight").cast("double").alias("n"))


def ingredients(counts: DataFrame | ExactRun, discounts: dict[str, Discount] | None = None) -> DataFrame:
    """node, run, sum_dist, harmonic, coreach and one column per discount. Without discounts an exact run adds its counts up where it finds them."""
    if isinstance(counts, ExactRun):
        if not discounts:
            return counts.sums()
        counts = counts.counts()
    t, n = F.col("t"), F.col("n")
    gain = lambda f: F.coalesce(F.sum(F.when(t > 0, n * f(t))), F.lit(0.0))
    extra = [gain(f).alias(name) for name, f in (discounts or {}).items()]
    return counts.groupBy("node", "run").agg(F.sum(n * t).alias("sum_dist"), gain(reciprocal).alias("harmonic"), F.sum("n").alias("coreach"), *extra)


def closeness(sum_dist: Column) -> Column:
    """1 over the sum of finite distances; 0 if nobody else coreaches the node."""
    return F.when(sum_dist > 0, 1.0 / sum_dist).otherwise(0.0)


def lin(coreach: Column, sum_dist: Column) -> Column:
    """The squared number of coreachable nodes over the sum of their distances; 1 if there is none but the node."""
    return F.when(sum_dist > 0, coreach * coreach / sum_dist).otherwise(1.0)


def centralities(counts: DataFrame | ExactRun, discounts: dict[str, Discount] | None = None) -> DataFrame:
    """node, run, coreach, sum_dist, closeness (patched), lin, harmonic and one column per discount."""
    sums = ingredients(counts, discounts)
    s, c = F.col("sum_dist"), F.col("coreach")
    return sums.select("node", "run", "coreach", "sum_dist", closeness(s).alias("closeness"), lin(c, s).alias("lin"), "harmonic", *(discounts or {}))


def centralities_of_sums(sums: DataFrame) -> DataFrame:
    """The same columns from a run that kept sums (node, run, coreach, sum_dist, harmonic, further gains)."""
    s, c = F.col("sum_dist"), F.col("coreach")
    more = [x for x in sums.columns if x not in ("node", "run", "coreach", "sum_dist", "harmonic")]
    return sums.select("node", "run", "coreach", "sum_dist", closeness(s).alias("closeness"), lin(c, s).alias("lin"), "harmonic", *more)


def diameter_bound(counts: DataFrame) -> DataFrame:
    """run, diameter: the last round in which a ball grew; a lower bound for sketches, and exact for exact counts."""
    return counts.groupBy("run").agg(F.max("t").alias("diameter"))


def strict_closeness_exact(counts: DataFrame, n_nodes: int) -> DataFrame:
    """node, run, closeness_strict: 0 unless every node coreaches."""
    sums = ingredients(counts)
    return sums.select("node", "run", F.when((F.col("coreach") >= n_nodes) & (F.col("sum_dist") > 0), 1.0 / F.col("sum_dist")).otherwise(0.0).alias("closeness_strict"))


def strict_closeness_sketch(run: BallRun) -> DataFrame:
    """node, run, closeness_strict from a sketch: a node that all coreach has the union of all counters.

    Equality of registers is necessary and, with high probability, sufficient. The
    union is p rows a run, so it may be broadcast.
    """
    registers = run.registers()
    whole = registers.groupBy("run", "reg").agg(F.max("rho").alias("top"))
    need = whole.groupBy("run").agg(F.count(F.lit(1)).alias("need"))
    have = registers.join(F.broadcast(whole), ["run", "reg"]).where("rho = top").groupBy("node", "run").agg(F.count(F.lit(1)).alias("have"))
    full = have.join(F.broadcast(need), "run").where("have = need").select("node", "run", F.lit(True).alias("full"))
    sums = ingredients(sketch_counts(run)).join(full, ["node", "run"], "left")
    return sums.select("node", "run", F.when(F.col("full") & (F.col("sum_dist") > 0), 1.0 / F.col("sum_dist")).otherwise(0.0).alias("closeness_strict"))


def discounted(counts: DataFrame, f: Discount, name: str = "gain") -> DataFrame:
    """node, run, name: the sum of f over the distances of all other coreachable nodes (times their weight)."""
    return ingredients(counts, {name: f}).select("node", "run", name)


def discounted_by_table(counts: DataFrame, values: DataFrame, name: str = "gain") -> DataFrame:
    """As `discounted`, with f given as rows (t, f); f must not increase. Distances beyond the table gain nothing."""
    check_discount(values)
    joined = counts.join(values.select("t", "f"), "t", "left")
    return joined.groupBy("node", "run").agg(F.coalesce(F.sum(F.when(F.col("t") > 0, F.col("n") * F.coalesce("f", F.lit(0.0)))), F.lit(0.0)).alias(name))


def check_discount(values: DataFrame) -> None:
    """A table (t, f) must not increase in t. It holds one row a distance, and is small."""
    rows = values.select("t", "f").orderBy("t").collect()
    for a, b in zip(rows, rows[1:], strict=False):
        if b["f"] > a["f"]:
            raise ParameterError(f"the discount rises from t={a['t']} to t={b['t']}")


def average_runs(measures: DataFrame, names: list[str], level: float = 0.95) -> DataFrame:
    """node, and for each measure its mean over runs, its empirical standard deviation, and the half width of its confidence interval."""
    z = {0.9: 1.6449, 0.95: 1.96, 0.99: 2.5758}.get(level)
    if z is None:
        raise ParameterError("level must be 0.9, 0.95 or 0.99")
    out = []
    for name in names:
        sd = F.coalesce(F.stddev_samp(name), F.lit(0.0))
        out += [F.avg(name).alias(f"{name}_mean"), sd.alias(f"{name}_sd"), (z * sd / F.sqrt(F.count(F.lit(1)))).alias(f"{name}_half_width")]
    return measures.groupBy("node").agg(*out)


def neighbourhood_function(counts: DataFrame) -> DataFrame:
    """run, t, pairs: how many pairs lie within distance t. Sums by t come first, so the window is over distances only."""
    by_t = counts.groupBy("run", "t").agg(F.sum("n").alias("n"))
    return by_t.select("run", "t", F.sum("n").over(Window.partitionBy("run").orderBy("t")).alias("pairs"))


def distance_distribution(counts: DataFrame) -> DataFrame:
    """run, t, share: how the distances of distinct reachable pairs are distributed."""
    by_t = counts.where("t > 0").groupBy("run", "t").agg(F.sum("n").alias("n"))
    return by_t.select("run", "t", (F.col("n") / F.sum("n").over(Window.partitionBy("run"))).alias("share"))


def distance_summary(counts: DataFrame, n_nodes: int) -> DataFrame:
    """run, average distance, harmonic diameter n(n-1) / sum of 1/d, and its inverse, the mean of 1/d."""
    t, n = F.col("t"), F.col("n")
    sums = counts.where("t > 0").groupBy("run").agg(F.sum(n * t).alias("d"), F.sum(n).alias("k"), F.sum(n / t).alias("h"))
    every = float(n_nodes) * (n_nodes - 1)
    return sums.select("run", (F.col("d") / F.col("k")).alias("average_distance"), (every / F.col("h")).alias("harmonic_diameter"), (F.col("h") / every).alias("mean_reciprocal"))


def effective_radius(counts: DataFrame, q: float = 0.9) -> DataFrame:
    """node, run, radius: the interpolated distance within which a share q of the coreachable nodes lies; 0 if there is none but the node."""
    w = Window.partitionBy("node", "run").orderBy("t")
    whole = Window.partitionBy("node", "run")
    sized = counts.select("node", "run", "t", F.sum("n").over(w).alias("size"), F.sum("n").over(whole).alias("total"))
    near = sized.select("*", F.lag("size").over(w).alias("size_before"))
    # Between recorded distances the ball does not grow, so the step lies between t - 1 and t.
    hit = near.where(F.col("size") >= q * F.col("total"))
    first = hit.groupBy("node", "run").agg(F.min(F.struct("t", "size", "size_before", "total")).alias("m")).select("node", "run", "m.*")
    step = (q * F.col("total") - F.col("size_before")) / (F.col("size") - F.col("size_before"))
    return first.select("node", "run", F.when(F.col("t") == 0, 0.0).otherwise(F.col("t") - 1 + step).alias("radius"))


def eccentricity(counts: DataFrame) -> DataFrame:
    """node, run, eccentricity: the largest recorded distance; a lower bound for sketches."""
    return counts.groupBy("node", "run").agg(F.max("t").alias("eccentricity"))


def katz(graph, beta: float, length: int) -> DataFrame:
    """node, katz: paths of up to `length` arcs into a node, each arc of a path weighing beta. A contrast, not a geometric measure."""
    now = graph.vertices.select(F.col("id").alias("node"), F.lit(1.0).alias("paths"))
    total = graph.vertices.select(F.col("id").alias("node"), F.lit(0.0).alias("gain"))
    for _ in range(length):
        now = cut(now.join(graph.arcs, F.col("node") == F.col("src")).groupBy(F.col("dst").alias("node")).agg((F.lit(beta) * F.sum("paths")).alias("paths")))
        total = total.unionByName(now.select("node", F.col("paths").alias("gain")))
    return total.groupBy("node").agg(F.sum("gain").alias("katz"))


def ranking(measures: DataFrame, name: str, k: int | None = None) -> DataFrame:
    """node, value and place by decreasing value, ties to the smaller node; the k best if asked for."""
    rows = measures.select("node", F.col(name).alias("value"))
    if k is not None:
        best = rows.orderBy(F.desc("value"), "node").limit(k)
        return best.withColumn("place", F.row_number().over(Window.orderBy(F.desc("value"), "node")))
    return numbered(rows, [F.desc("value"), F.col("node")], "place")
