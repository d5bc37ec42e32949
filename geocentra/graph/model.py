"""The graph: vertices (id, weight) and arcs (src, dst), validated and without loops or repeats."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from geocentra.errors import GraphError, WeightError

_INTEGERS = (T.LongType, T.IntegerType, T.ShortType, T.ByteType)

# The kinds of nodes that share one graph; id = kind << 56 | key.
KINDS = {"customer": 1, "supplier": 2, "part": 3, "nation": 4, "region": 5, "user": 6, "page": 7, "host": 8, "term": 9, "doc": 10, "item": 11, "vector": 12, "turn": 13}


def node_id(kind: str, key: F.Column | str) -> F.Column:
    """A node id that is unique across kinds."""
    return (F.lit(KINDS[kind] << 56) + F.col(key) if isinstance(key, str) else F.lit(KINDS[kind] << 56) + key).cast("long")


def _require(df: DataFrame, columns: tuple[str, ...], what: str) -> None:
    for c in columns:
        if c not in df.columns:
            raise GraphError(f"{what} has no column {c!r}")
        if not isinstance(df.schema[c].dataType, _INTEGERS):
            raise GraphError(f"column {c!r} of {what} is {df.schema[c].dataType.simpleString()}, not an integer type")


@dataclass(frozen=True)
class Graph:
    vertices: DataFrame
    arcs: DataFrame

    @classmethod
    def from_arcs(cls, arcs: DataFrame, vertices: DataFrame | None = None, dangling: str = "error") -> Graph:
        """A graph from any relation with src and dst.

        Loops never change a ball and repeats are idempotent: both go, and so do arcs
        with a null end. Without `vertices` the nodes are the ends of arcs. With them,
        an arc to an unknown node is an error, or dropped with dangling="drop".
        """
        _require(arcs, ("src", "dst"), "arcs")
        clean = arcs.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")).where("src is not null and dst is not null and src <> dst").distinct()
        if vertices is None:
            nodes = clean.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
            return cls(nodes.select("id", F.lit(1).alias("weight")), clean)
        _require(vertices, ("id",), "vertices")
        weight = F.col("weight") if "weight" in vertices.columns else F.lit(1)
        nodes = vertices.select(F.col("id").cast("long").alias("id"), weight.cast("int").alias("weight")).where("id is not null").dropDuplicates(["id"])
        known = nodes.select(F.col("id").alias("known_id"))
        if dangling == "drop":
            for end in ("src", "dst"):
                clean = clean.join(known, F.col(end) == F.col("known_id"), "left_semi")
        elif not dangling_arcs(clean, nodes).isEmpty():
            raise GraphError("arcs have an end that is not in vertices; pass dangling='drop' to leave them out")
        return cls(nodes, clean)

    def transpose(self) -> Graph:
        return Graph(self.vertices, self.arcs.select(F.col("dst").alias("src"), F.col("src").alias("dst")))

    def symmetrise(self) -> Graph:
        return Graph(self.vertices, self.arcs.unionByName(self.transpose().arcs).distinct())

    def with_weights(self, weights: DataFrame) -> Graph:
        """Node weights from (id, weight); nodes without one weigh 1."""
        given = weights.select(F.col("id").alias("given_id"), F.col("weight").alias("given"))
        joined = self.vertices.join(given, F.col("id") == F.col("given_id"), "left")
        return Graph(joined.select("id", F.coalesce(F.col("given"), F.lit(1)).alias("weight")), self.arcs)

    def check_weights(self) -> None:
        """Weights must be integers of at least 1."""
        kind = self.vertices.schema["weight"].dataType
        wrong = F.col("weight").isNull() | (F.col("weight") < 1)
        if not isinstance(kind, _INTEGERS):
            wrong = wrong | (F.col("weight") != F.floor("weight"))
        if not self.vertices.where(wrong).limit(1).isEmpty():
            raise WeightError("column 'weight' must hold integers of at least 1")


def dangling_arcs(arcs: DataFrame, vertices: DataFrame) -> DataFrame:
    """Arcs with an end that is no vertex."""
    known = vertices.select(F.col("id").alias("known_id"))
    lost = [arcs.join(known, F.col(end) == F.col("known_id"), "left_anti") for end in ("src", "dst")]
    return lost[0].unionByName(lost[1]).distinct()


def scale_weights(df: DataFrame, column: str, levels: int) -> DataFrame:
    """Real weights as integers 1..levels, in proportion to the largest."""
    top = df.agg(F.max(column).alias("top"))
    return df.crossJoin(F.broadcast(top)).select(*df.columns, F.greatest(F.lit(1), F.ceil(F.col(column) * levels / F.col("top"))).cast("int").alias("weight"))


def degrees(graph: Graph) -> DataFrame:
    """node, n_in, n_out for every vertex: one aggregation over the arcs' ends."""
    ends = graph.arcs.select(F.explode(F.array(F.struct(F.col("src").alias("node"), F.lit(0).alias("i"), F.lit(1).alias("o")), F.struct(F.col("dst").alias("node"), F.lit(1).alias("i"), F.lit(0).alias("o")))).alias("e")).select("e.*")
    counted = ends.groupBy("node").agg(F.sum("i").alias("n_in"), F.sum("o").alias("n_out"))
    return graph.vertices.select(F.col("id").alias("node")).join(counted, "node", "left").select("node", F.coalesce("n_in", F.lit(0)).alias("n_in"), F.coalesce("n_out", F.lit(0)).alias("n_out"))


def indegree(graph: Graph) -> DataFrame:
    """node, indegree: the elementary measure, the ball of radius 1."""
    return degrees(graph).select("node", F.col("n_in").alias("indegree"))


def graph_stats(graph: Graph) -> DataFrame:
    """One row: nodes, arcs, average degree, density, largest degrees."""
    d = degrees(graph).agg(F.count(F.lit(1)).alias("nodes"), F.sum("n_out").alias("arcs"), F.max("n_in").alias("max_in"), F.max("n_out").alias("max_out"))
    return d.select("nodes", "arcs", (F.col("arcs") / F.col("nodes")).alias("avg_degree"), (F.col("arcs") / (F.col("nodes") * (F.col("nodes") - 1))).alias("density"), "max_in", "max_out")
