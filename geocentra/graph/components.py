"""Weak and strong components."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geocentra.graph.model import Graph
from geocentra.plans.checkpoint import cut
from geocentra.propagate import local as L
from geocentra.propagate.fixpoint import MAXIMUM, PRESENCE, fixpoint


def smallest_of(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nodes, the smallest node that each is connected to) of links held in memory."""
    nodes, at = np.unique(np.concatenate((a, b)), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    root = np.arange(len(nodes))
    while len(x):
        x, y = root[x], root[y]
        apart = x != y
        x, y = x[apart], y[apart]
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while (up := root[root]).tobytes() != root.tobytes():
            root = up
    return nodes, nodes[root]


def _in_a_task(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held = [(b.column("a").to_numpy(), b.column("b").to_numpy()) for b in batches if b.num_rows]
    if not held:
        return
    nodes, component = smallest_of(*(np.concatenate(x) for x in zip(*held, strict=True)))
    for lo in range(0, len(nodes), L.OUT_ROWS):
        yield pa.RecordBatch.from_arrays([pa.array(x[lo : lo + L.OUT_ROWS]) for x in (nodes, component)], names=["node", "component"])


def connected(links: DataFrame) -> DataFrame:
    """node, component (its smallest node) for every node of `links` (a, b), directions ignored.

    Links that fit in a task, from the start or after some steps, are followed there, and
    no round is a job. Else alternates the published large-star and small-star steps, which move every link to
    ever smaller nodes until each component is a star around its smallest one. The
    only group operation is a minimum, which is computed before rows are shuffled, so a
    node with very many links costs one row a task.
    """
    now = cut(links.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    done = False
    while not done:
        if now.count() <= L.LOCAL_ARCS:
            return cut(now.coalesce(1).mapInArrow(_in_a_task, "node long, component long"))
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        # large star: the larger neighbours of a node go to the smallest around it
        large = both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        # small star: the smaller neighbours of a node, and it, go to the smallest of them
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a")
        now = cut(small.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b"))).distinct())
        several = now.groupBy("a").agg(F.count(F.lit(1)).alias("k")).where("k > 1").select("a").limit(1)
        inner = now.select("b").join(now.select(F.col("a").alias("b")), "b", "left_semi").limit(1)
        done = several.unionAll(inner).isEmpty()
    return now.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())


def weak_components(graph: Graph) -> DataFrame:
    """node, component (its smallest node) of every vertex, directions ignored."""
    found = connected(graph.arcs.select(F.col("src").alias("a"), F.col("dst").alias("b")))
    return graph.vertices.select(F.col("id").alias("node")).join(found, "node", "left").select("node", F.coalesce("component", "node").alias("component"))


def strong_components(graph: Graph) -> DataFrame:
    """node, component (its smallest node): nodes that reach each other.

    Every node takes the largest name that reaches it; a node that keeps its own is the
    root of a component, which are the nodes of its name that reach it. These go, and
    the rest begins again. A step costs a row a node, not one a pair.
    """
    nodes = cut(graph.vertices.select(F.col("id").alias("node")))
    arcs = cut(graph.arcs.where("src <> dst").select("src", "dst"))
    found = None
    while not nodes.isEmpty():
        names = nodes.select("node", F.lit(0).alias("run"), F.lit(0).alias("item"), F.col("node").alias("value"))
        color = cut(fixpoint(names, Graph(nodes.select(F.col("node").alias("id"), F.lit(1).alias("weight")), arcs), MAXIMUM).final().select("node", F.col("value").alias("name")))
        a, b = (color.select(F.col("node").alias(x), F.col("name").alias(f"{x}_name")) for x in ("src", "dst"))
        inner = cut(arcs.join(a, "src").join(b, "dst").where("src_name = dst_name").select("src", "dst"))
        roots = color.where("node = name").select("node", F.lit(0).alias("run"), F.lit(0).alias("item"), F.lit(0).alias("value"))
        back = cut(fixpoint(roots, Graph(nodes.select(F.col("node").alias("id"), F.lit(1).alias("weight")), inner), PRESENCE, direction="out").final().select("node"))
        mine = back.join(color, "node")
        least = mine.groupBy("name").agg(F.min("node").alias("component"))
        part = cut(mine.join(least, "name").select("node", "component"))
        found = part if found is None else cut(found.unionByName(part))
        nodes = cut(nodes.join(back, "node", "left_anti"))
        arcs = cut(arcs.join(back.withColumnRenamed("node", "src"), "src", "left_anti").join(back.withColumnRenamed("node", "dst"), "dst", "left_anti"))
    return graph.vertices.select(F.col("id").alias("node"), F.col("id").alias("component")) if found is None else found


def giant_share(components: DataFrame) -> DataFrame:
    """share: the part of all nodes that the largest component holds."""
    sizes = components.groupBy("component").agg(F.count(F.lit(1)).alias("k"))
    return sizes.agg((F.max("k") / F.sum("k")).alias("share"))
