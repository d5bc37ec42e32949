"""Exact distances by classes: nodes with the same arcs are followed once, and only results name each of them.

Between two classes either every member of the one has an arc to every member of the
other, or none has. Members of one class are one step apart. So distances of classes
are those of their members, however many copies there are: a shortest path never
visits a class twice.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from geocentra.graph.model import Graph
from geocentra.plans.checkpoint import cut
from geocentra.propagate import local as L
from geocentra.propagate.exact import ExactRun, exact_pairs

#: Members in one row; two such rows are unfolded into pairs where they meet.
CHUNK = 1024
#: Sources that follow each other for one node, and then again for the next node: a short repetition, which files keep in few bytes.
RUN = 256
#: Pairs that a task unfolds, so that a file has few different nodes and keeps its dictionaries.
TASK_PAIRS = 1 << 25


@dataclass
class Classes:
    """`members` (id, class), and the graph of classes with their sizes (`weight`); a class alone and without arcs is no vertex."""

    members: DataFrame
    graph: Graph


def classes_of(keyed: DataFrame) -> Classes:
    """Classes of nodes (id, gives, takes): a node has an arc to every other node that takes what it gives, and takes are among its gives."""
    key = F.sha2(F.to_json(F.struct("gives", "takes")), 256)
    named = cut(keyed.where(F.size("takes") > 0).select("id", "gives", "takes", key.alias("key")))
    found = cut(named.groupBy("key").agg(F.min("id").alias("class"), F.count(F.lit(1)).alias("size"), F.first("gives").alias("gives"), F.first("takes").alias("takes")))
    out = found.select(F.col("class").alias("src"), F.explode("gives").alias("what"))
    to = found.select(F.col("class").alias("dst"), F.explode("takes").alias("what"))
    arcs = cut(out.join(to, "what").where("src <> dst").select("src", "dst").distinct())
    ends = arcs.select(F.explode(F.array("src", "dst")).alias("class")).distinct()
    used = cut(found.join(ends.withColumn("touched", F.lit(True)), "class", "left").where("size > 1 or touched").select("class", "key", "size"))
    members = cut(named.select("id", "key").join(used.select("key", "class"), "key").select("id", "class"))
    return Classes(members, Graph(used.select(F.col("class").alias("id"), F.col("size").alias("weight")), arcs))


@dataclass
class ClassRun:
    classes: Classes
    run: ExactRun

    def pairs(self) -> DataFrame:
        """node, source, dist as of the members' own graph. Pairs are unfolded last and are neither stored nor dealt."""
        sizes = self.classes.graph.vertices.select(F.col("id").alias("class"), F.col("weight").alias("size"))
        part = F.pmod(F.xxhash64("id"), F.ceil(F.col("size") / CHUNK))
        chunks = cut(self.classes.members.join(sizes, "class").groupBy("class", part.alias("part")).agg(F.collect_list("id").alias("ids")).select("class", "ids"))
        met = self.run.pairs().join(chunks.select(F.col("class").alias("node"), F.col("ids").alias("nodes")), "node").join(chunks.select(F.col("class").alias("source"), F.col("ids").alias("sources")), "source")
        spread = met.select("nodes", "sources", "dist").repartition(max(L.n_tasks(met.sparkSession), -(-self.n_pairs() // TASK_PAIRS)))
        runs = F.transform(F.sequence(F.lit(0), F.floor((F.size("sources") - 1) / RUN)), lambda i: F.slice("sources", (i * RUN + 1).cast("int"), F.lit(RUN)))
        by_run = spread.select(F.explode(runs).alias("run"), "nodes", "dist").select(F.explode("nodes").alias("node"), "run", "dist")
        unfolded = by_run.select("node", F.explode("run").alias("source"), "dist")
        # Classes at distance 0 are one and the same: its members are one step apart.
        return unfolded.select("node", "source", F.when((F.col("dist") == 0) & (F.col("node") != F.col("source")), 1).otherwise(F.col("dist")).alias("dist"))

    def n_pairs(self) -> int:
        """How many rows `pairs` has, from the sizes of classes."""
        sizes = self.classes.graph.vertices.select("id", F.col("weight").cast("double").alias("size"))
        both = self.run.pairs().join(sizes.select(F.col("id").alias("node"), F.col("size").alias("a")), "node").join(sizes.select(F.col("id").alias("source"), F.col("size").alias("b")), "source")
        return int(both.agg(F.sum(F.col("a") * F.col("b"))).first()[0] or 0)

    def counts(self) -> DataFrame:
        """node, run, t, n: how many sources lie at each distance. No pair of members becomes a row."""
        sizes = self.classes.graph.vertices.select(F.col("id").alias("source"), F.col("weight").alias("size"))
        far = self.run.pairs().join(sizes, "source")
        own = F.array(F.struct(F.lit(0).alias("t"), F.lit(1).cast("long").alias("k")), F.struct(F.lit(1).alias("t"), (F.col("size") - 1).alias("k")))
        there = F.when(F.col("dist") == 0, own).otherwise(F.array(F.struct(F.col("dist").alias("t"), F.col("size").alias("k"))))
        by_class = far.select(F.col("node").alias("class"), F.explode(there).alias("x")).where("x.k > 0").groupBy("class", "x.t").agg(F.sum("x.k").cast("double").alias("n"))
        return self.classes.members.join(cut(by_class), "class").select(F.col("id").alias("node"), F.lit(0).alias("run"), "t", "n")


def exact_pairs_of_classes(classes: Classes, direction: str = "in") -> ClassRun:
    """As `exact_pairs` from all nodes, by one visit a class."""
    return ClassRun(classes, exact_pairs(classes.graph, direction=direction))
