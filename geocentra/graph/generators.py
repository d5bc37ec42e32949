"""Graphs from rules: paths, cycles, stars, grids, complete graphs and Kronecker graphs."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from geocentra.errors import ParameterError
from geocentra.graph.model import Graph
from geocentra.operators.ordered import succession_in_steps
from geocentra.sketch.registers import md5_bits

#: A draw is a hash modulo this.
_DRAWS = 1 << 30


def _graph(arcs: DataFrame, spark: SparkSession, n: int) -> Graph:
    return Graph(spark.range(n).select("id", F.lit(1).alias("weight")), arcs.select(F.col("src").cast("long"), F.col("dst").cast("long")))


def path(spark: SparkSession, n: int) -> Graph:
    return _graph(spark.range(max(0, n - 1)).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst")), spark, n)


def path_of(ids: DataFrame, name: str) -> DataFrame:
    """src, dst: each id of a table -> the next larger one, without a window over the table."""
    return succession_in_steps(ids.select(name, F.col(name).alias("path_node")), F.lit(0), F.shiftright(name, 12), [name], "path_node")


def cycle(spark: SparkSession, n: int) -> Graph:
    return _graph(spark.range(n).select(F.col("id").alias("src"), ((F.col("id") + 1) % n).alias("dst")).where("src <> dst"), spark, n)


def star(spark: SparkSession, n: int, inward: bool = False) -> Graph:
    """Node 0 and n - 1 leaves; arcs go out from the centre, or into it."""
    arcs = spark.range(1, n).select(F.lit(0).alias("src"), F.col("id").alias("dst"))
    g = _graph(arcs, spark, n)
    return g.transpose() if inward else g


def complete(spark: SparkSession, n: int) -> Graph:
    arcs = spark.range(n * n).select(F.floor(F.col("id") / n).alias("src"), (F.col("id") % n).alias("dst")).where("src <> dst")
    return _graph(arcs, spark, n)


def grid(spark: SparkSession, rows: int, columns: int) -> Graph:
    """Arcs to the right and down."""
    node = spark.range(rows * columns).select("id", (F.col("id") % columns).alias("c"), F.floor(F.col("id") / columns).alias("r"))
    right = node.where(F.col("c") < columns - 1).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"))
    down = node.where(F.col("r") < rows - 1).select(F.col("id").alias("src"), (F.col("id") + columns).alias("dst"))
    return _graph(right.unionByName(down), spark, rows * columns)


def _mixed(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values (the public splitmix64 finaliser)."""
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _draws(bounds: list[int], s: int, k: int, seed: int):
    """Arcs by number -> their ends: k cells each, from hashes of (seed, number, level)."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            h = _mixed(batch.column("id").to_numpy().astype(np.uint64) + np.uint64(seed * 0x9E3779B97F4A7C15 % (1 << 64)))
            src, dst = np.zeros(len(h), np.int64), np.zeros(len(h), np.int64)
            for level in range(1, k + 1):
                cell = np.searchsorted(bounds, (_mixed(h + np.uint64(level)) % np.uint64(_DRAWS)).astype(np.int64), side="right")
                src, dst = src * s + cell // s, dst * s + cell % s
            yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(dst)], names=["src", "dst"])

    return run


def kronecker(spark: SparkSession, initiator: list[list[float]], k: int, arcs: int = 0, seed: int = 0, portable: bool = False, numbers: DataFrame | None = None) -> Graph:
    """A stochastic Kronecker graph of s**k nodes: each arc draws k cells of the s x s initiator.

    Every draw is a hash of (seed, arc, level), so that the graph does not depend on
    the partitioning; a `portable` graph draws from md5 and is the same in any engine.
    Repeats and loops go, so there are somewhat fewer arcs. With `numbers` (id) each of
    its rows is the number of an arc, in place of 0 to `arcs`.
    """
    s = len(initiator)
    flat = [float(x) for row in initiator for x in row]
    if s < 2 or any(len(row) != s for row in initiator) or min(flat) < 0 or sum(flat) <= 0:
        raise ParameterError("initiator must be a square of at least 2 x 2 non-negative numbers")
    if numbers is None:
        numbers = spark.range(arcs)
    bounds = [round(sum(flat[: i + 1]) / sum(flat) * _DRAWS) for i in range(len(flat) - 1)]
    if not portable:
        return _graph(numbers.mapInArrow(_draws(bounds, s, k, seed), "src long, dst long").where("src <> dst").distinct(), spark, s**k)

    def cell(level: int) -> Column:
        u = F.pmod(md5_bits(F.concat_ws(":", F.lit(seed), F.col("id").cast("string"), F.lit(level))), F.lit(_DRAWS))
        return sum((F.when(u >= b, 1).otherwise(0) for b in bounds), F.lit(0))

    drawn = numbers.select(F.array(*[cell(level) for level in range(1, k + 1)]).alias("cells"))
    end = lambda part: F.aggregate("cells", F.lit(0).cast("long"), lambda acc, c: acc * s + part(c))
    ends = drawn.select(end(lambda c: F.floor(c / s)).alias("src"), end(lambda c: c % s).alias("dst"))
    return _graph(ends.where("src <> dst").distinct(), spark, s**k)
