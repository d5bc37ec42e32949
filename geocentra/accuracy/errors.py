"""Relative errors, their distribution, and agreement of rankings."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from geocentra.plans.checkpoint import cut


def _long(df: DataFrame, keys: list[str], names: list[str], value: str) -> DataFrame:
    return df.select(*keys, F.explode(F.array(*[F.struct(F.lit(n).alias("measure"), F.col(n).alias(value)) for n in names])).alias("x")).select(*keys, "x.*")


def relative_errors(approx: DataFrame, exact: DataFrame, names: list[str], keys: list[str] | None = None) -> DataFrame:
    """keys, node, measure, approx, exact, error (signed) for nodes with an exact value above 0."""
    keys = keys or []
    a, e = _long(approx, [*keys, "node"], names, "approx"), _long(exact, ["node"], names, "exact")
    return a.join(e, ["node", "measure"]).where("exact > 0").withColumn("error", (F.col("approx") - F.col("exact")) / F.col("exact"))


def run_errors(runs: DataFrame, exact: DataFrame, names: list[str]) -> DataFrame:
    """Errors of every run by itself."""
    return relative_errors(runs, exact, names, ["run"])


def convergence(runs: DataFrame, exact: DataFrame, names: list[str], ks: list[int]) -> DataFrame:
    """Errors of the averages of the first k runs, for each k (column runs)."""
    k = F.explode(F.array(*[F.lit(x) for x in ks])).alias("runs")
    averaged = runs.select("node", "run", *names, k).where("run < runs").groupBy("runs", "node").agg(*[F.avg(n).alias(n) for n in names])
    return relative_errors(averaged, exact, names, ["runs"])


def rms(errors: DataFrame) -> DataFrame:
    return errors.groupBy("runs", "measure").agg(F.sqrt(F.avg(F.col("error") * F.col("error"))).alias("rms"))


def error_boxes(errors: DataFrame, by: list[str]) -> DataFrame:
    """Quartiles of the errors, their mean, and whiskers that span two standard deviations around it."""
    sd = F.stddev_samp("error")
    quartile = lambda q: F.percentile("error", F.lit(q))
    return errors.groupBy(*by).agg(quartile(0.25).alias("q1"), quartile(0.5).alias("median"), quartile(0.75).alias("q3"), F.avg("error").alias("mean"), (F.avg("error") - sd).alias("low"), (F.avg("error") + sd).alias("high"))


def _mean_ranks(values: DataFrame, name: str, rank: str) -> DataFrame:
    """name, rank: the mean place of each distinct value, from how often each occurs; windows are over ranges of values."""
    each = cut(values.groupBy(name).agg(F.sum("n").alias("k")).orderBy(name).withColumn("part", F.shiftright(F.monotonically_increasing_id(), 33)))
    sizes = each.groupBy("part").agg(F.sum("k").alias("whole"))
    before = sizes.select("part", (F.sum("whole").over(Window.orderBy("part")) - F.col("whole")).alias("before"))
    within = F.sum("k").over(Window.partitionBy("part").orderBy(name)) - F.col("k")
    return each.select(name, "part", "k", within.alias("within")).join(F.broadcast(before), "part").select(name, (F.col("before") + F.col("within") + (F.col("k") + 1) / 2).alias(rank))


def spearman(measures: DataFrame, a: str, b: str) -> DataFrame:
    """Correlation of ranks, ties at their mean. Rows are first counted by pairs of values, so a frequent value is one row."""
    pairs = cut(measures.groupBy(F.col(a).alias("a"), F.col(b).alias("b")).agg(F.count(F.lit(1)).alias("n")))
    ranked = pairs.join(_mean_ranks(pairs, "a", "x"), "a").join(_mean_ranks(pairs, "b", "y"), "b")
    n, x, y = F.col("n"), F.col("x"), F.col("y")
    # Mean ranks are half the number of rows and one more.
    mean = pairs.agg(((F.sum("n") + 1) / 2).alias("mean"))
    at = ranked.crossJoin(F.broadcast(mean)).withColumns({"x": x - F.col("mean"), "y": y - F.col("mean")})
    return at.agg((F.sum(n * x * y) / F.sqrt(F.sum(n * x * x) * F.sum(n * y * y))).alias("spearman"))


def overlap(measures: DataFrame, a: str, b: str, k: int) -> DataFrame:
    """The share of nodes among the k best by both measures."""
    best = lambda name: measures.select("node", name).orderBy(F.desc(name), "node").limit(k).select("node")
    return best(a).join(best(b), "node").agg((F.count(F.lit(1)) / float(k)).alias("overlap"))


def kendall(measures: DataFrame, a: str, b: str, sample: int | None = None) -> DataFrame:
    """Kendall's tau-a over all nodes, from counts of distinct pairs of values; or on a sample of nodes by hash."""
    rows = measures.select("node", F.col(a).alias("a"), F.col(b).alias("b"))
    if sample is not None:
        rows = rows.orderBy(F.md5(F.col("node").cast("string").cast("binary")), "node").limit(sample)
    pairs = cut(rows.groupBy("a", "b").agg(F.count(F.lit(1)).cast("double").alias("n")))
    other = pairs.select(F.col("a").alias("a2"), F.col("b").alias("b2"), F.col("n").alias("n2"))
    signs = pairs.join(other, F.col("a") < F.col("a2")).agg(F.coalesce(F.sum(F.col("n") * F.col("n2") * F.signum(F.col("b2") - F.col("b"))), F.lit(0.0)).alias("s"))
    whole = pairs.agg(F.sum("n").alias("m"))
    return signs.crossJoin(whole).select((F.col("s") / (F.col("m") * (F.col("m") - 1) / 2)).alias("tau"))


def bias_report(measures: DataFrame, names: list[str], k: int = 10) -> DataFrame:
    """measure, its correlation with the coreachable count, and the share of its k best with a count below the median."""
    measures = cut(measures.select("node", "coreach", *names))
    median = measures.agg(F.percentile("coreach", F.lit(0.5)).alias("median"))
    out = None
    for name in names:
        correlation = measures.agg(F.corr(name, "coreach").alias("correlation"))
        best = measures.select("node", name, "coreach").orderBy(F.desc(name), "node").limit(k).crossJoin(median)
        share = best.agg((F.sum((F.col("coreach") < F.col("median")).cast("int")) / float(k)).alias("low_share"))
        row = correlation.crossJoin(share).select(F.lit(name).alias("measure"), "correlation", "low_share")
        out = row if out is None else out.unionByName(row)
    return out


def by_membership(errors: DataFrame, members: DataFrame) -> DataFrame:
    """The errors with `inside`: whether the node is one of `members` (node)."""
    return errors.join(members.select("node", F.lit(True).alias("inside")), "node", "left").withColumn("inside", F.coalesce("inside", F.lit(False)))


def rmse(errors: DataFrame, by: list[str]) -> DataFrame:
    """by, rmse: the root of the mean squared relative error."""
    return errors.groupBy(*by).agg(F.sqrt(F.avg(F.col("error") * F.col("error"))).alias("rmse"))
