"""Graphs that the given tables hold: each view is a function (spark, sf_dir) -> arcs (src, dst)."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from geocentra.graph.model import KINDS, Graph
from geocentra.operators.ordered import clean_arcs, succession, succession_in_steps
from geocentra.plans.checkpoint import cut

#: Vectors of one block; blocks are compared with each other.
KNN_BLOCK = 4096
#: Turns of one conversation that have ids of their own, and those of them with ids next to each other.
MAX_TURNS, SHORT = 1 << 20, 1000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _kind(kind: str, key: Column | str) -> Column:
    return (F.lit(KINDS[kind]).cast("long") * F.lit(1 << 56) + (F.col(key) if isinstance(key, str) else key).cast("long")).cast("long")


def text_id(kind: str, text: Column) -> Column:
    """An id for a string node: 56 bits of its md5 below its kind."""
    return _kind(kind, F.conv(F.substring(F.md5(text.cast("binary")), 1, 14), 16, 10).cast("long"))


def part_succession(spark: SparkSession, sf_dir: str) -> DataFrame:
    return succession(table(spark, sf_dir, "lineitem"), [F.col("l_orderkey")], ["l_linenumber", "l_partkey", "l_suppkey"], "l_partkey")


def sparse_part_succession(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").where("l_returnflag = 'R' and l_quantity <= 15")
    return succession(lines, [F.col("l_orderkey")], ["l_linenumber", "l_partkey", "l_suppkey"], "l_partkey")


def customer_supplier(spark: SparkSession, sf_dir: str) -> DataFrame:
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    return clean_arcs(orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey")).select(_kind("customer", "o_custkey").alias("src"), _kind("supplier", "l_suppkey").alias("dst")))


def _handoff(events: DataFrame) -> DataFrame:
    """A day's events by the second: a day is no window, and may hold any number of events."""
    return succession_in_steps(events, F.to_date("ts"), F.date_trunc("second", "ts"), ["ts", "event_id"], "user_id")


def user_handoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _handoff(table(spark, sf_dir, "events"))


def error_handoff(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _handoff(table(spark, sf_dir, "events").where("event_type = 'error'"))


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page_id, url, links: the targets of a page's links, in order."""
    return table(spark, sf_dir, "pages").select("page_id", "url", F.regexp_extract_all("html", F.lit('href="([^"]*)"'), 1).alias("links"))


def page_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = page_links(spark, sf_dir).select("page_id", F.explode("links").alias("link"))
    return clean_arcs(rows.select(_kind("page", "page_id").alias("src"), text_id("term", F.col("link")).alias("dst")))


def host_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = page_links(spark, sf_dir).select(F.regexp_extract("url", "://([^/?#]*)", 1).alias("host"), F.explode("links").alias("link"))
    return clean_arcs(rows.select(text_id("host", F.col("host")).alias("src"), text_id("term", F.col("link")).alias("dst")))


def page_page(spark: SparkSession, sf_dir: str) -> DataFrame:
    """page -> another page whose last link is among the first page's links."""
    links = page_links(spark, sf_dir)
    out = links.select(F.col("page_id").alias("src"), F.explode("links").alias("link")).distinct()
    last = links.where(F.size("links") > 0).select(F.col("page_id").alias("dst"), F.element_at("links", -1).alias("link"))
    return clean_arcs(out.join(last, "link").select("src", "dst"))


def page_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    """id, gives, takes of page_page: what a page links to, and its last link. Pages of equal links are one class of nodes."""
    links = page_links(spark, sf_dir).where("page_id is not null").select(F.col("page_id").cast("long").alias("id"), F.explode("links").alias("link"), F.element_at("links", -1).alias("last"))
    return links.groupBy("id").agg(F.array_sort(F.collect_set("link")).alias("gives"), F.array_sort(F.collect_set("last")).alias("takes"))


def turn_node(conv: Column, turn: Column) -> Column:
    """The node of a conversation's turn. Turns from SHORT on have negative ids; what has no id of its own is an error."""
    short, long = (turn >= 0) & (turn < SHORT), (turn >= SHORT) & (turn < MAX_TURNS)
    wrong = F.raise_error(F.lit(f"a conversation below 0, or a turn beyond {MAX_TURNS}")).cast("long")
    return F.when((conv >= 0) & short, conv * SHORT + turn).when((conv >= 0) & long, -(conv * MAX_TURNS + turn)).otherwise(wrong)


def turn_of(node: Column) -> Column:
    return F.when(node >= 0, node % SHORT).otherwise(-node % MAX_TURNS)


def turn_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations").select(turn_node(F.col("conv_id"), F.col("turn")).alias("node"), "conv_id", "turn")
    return succession(turns, [F.col("conv_id")], ["turn"], "node")


def shared_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lower -> next higher id of the documents that hold a line of 40 characters or more: a chain for each line.

    A line that k documents hold gives k - 1 arcs, however many they are, and joins them all.
    """
    found = F.explode(F.array_distinct(F.split("text", "\n"))).alias("line")
    lines = table(spark, sf_dir, "documents").select("doc_id", found).where(F.length("line") >= 40)
    placed = lines.select("doc_id", F.unhex(F.md5(F.col("line").cast("binary"))).alias("line"), F.shiftright("doc_id", 16).alias("step"))
    # Dealt once, by what the groups below ask for.
    rows = placed.repartition("line", "step").distinct()
    return succession_in_steps(rows.withColumn("node", F.col("doc_id")), F.col("line"), F.col("step"), ["doc_id"], "node")


def geo_tree(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, s, n = (table(spark, sf_dir, x) for x in ("customer", "supplier", "nation"))
    return clean_arcs(
        c.select(_kind("customer", "c_custkey").alias("src"), _kind("nation", "c_nationkey").alias("dst"))
        .unionByName(s.select(_kind("supplier", "s_suppkey").alias("src"), _kind("nation", "s_nationkey").alias("dst")))
        .unionByName(n.select(_kind("nation", "n_nationkey").alias("src"), _kind("region", "n_regionkey").alias("dst")))
    )


def vector_knn(spark: SparkSession, sf_dir: str, k: int = 3) -> DataFrame:
    """vector -> its k most similar others by cosine, ties to the smaller id; rounded so that engines agree.

    Vectors meet in pairs of blocks of about KNN_BLOCK; each pair of blocks gives k rows a vector.
    """
    rows = table(spark, sf_dir, "embeddings").select("vec_id", F.col("embedding").cast("array<double>").alias("v")).where("vec_id is not null and v is not null")
    n = max(1, -(-rows.count() // KNN_BLOCK))
    dealt = rows.withColumn("block", F.pmod(F.xxhash64("vec_id"), F.lit(n)).cast("int"))
    packed = dealt.groupBy("block").applyInArrow(_vector_block, "block int, ids binary, vectors binary, width int")
    other = packed.select(F.col("block").alias("other"), F.col("ids").alias("ids2"), F.col("vectors").alias("vectors2"))
    pairs = packed.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(n - 1)))).join(other, "other")
    near = pairs.groupBy("block", "other").applyInArrow(_nearest(k), "src long, dst long, sim double")
    return near.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("sim"), "dst"))).where(F.col("r") <= k).select("src", "dst")


def _vector_block(table_of: pa.Table) -> pa.Table:
    ids, v = table_of.column("vec_id").to_numpy(), np.stack(table_of.column("v").to_numpy(zero_copy_only=False))
    return pa.table({"block": table_of.column("block").slice(0, 1), "ids": pa.array([ids.tobytes()], pa.binary()), "vectors": pa.array([v.tobytes()], pa.binary()), "width": pa.array([v.shape[1]], pa.int32())})


def _nearest(k: int):
    def run(pair: pa.Table) -> pa.Table:
        row = pair.slice(0, 1).to_pylist()[0]
        a, b = (np.frombuffer(row[c], np.int64) for c in ("ids", "ids2"))
        v, w = (np.frombuffer(row[c]).reshape(-1, row["width"]) for c in ("vectors", "vectors2"))
        by_id = np.argsort(b, kind="stable")
        b, w = b[by_id], w[by_id]
        out = []
        for lo in range(0, len(a), 512):
            norms = np.sqrt((v[lo : lo + 512] ** 2).sum(axis=1))[:, None] * np.sqrt((w**2).sum(axis=1))[None]
            sim = np.round(v[lo : lo + 512] @ w.T / norms, 9)
            sim[a[lo : lo + 512, None] == b[None]] = -np.inf
            best = np.argsort(-sim, axis=1, kind="stable")[:, :k]
            out.append((np.repeat(a[lo : lo + 512], best.shape[1]), b[best].ravel(), np.take_along_axis(sim, best, axis=1).ravel()))
        src, dst, sim = (np.concatenate(x) for x in zip(*out, strict=True))
        use = np.isfinite(sim)
        return pa.table({"src": src[use], "dst": dst[use], "sim": sim[use]})

    return run


def shingles(df: DataFrame, key: str, text: str, n: int) -> DataFrame:
    """key, shingle: the distinct runs of n words."""
    words = F.filter(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), lambda w: w != "")
    starts = F.when(F.size("w") >= n, F.sequence(F.lit(1), F.size("w") - n + 1)).otherwise(F.array().cast("array<int>"))
    return df.select(key, words.alias("w")).select(key, F.explode(F.transform(starts, lambda i: F.md5(F.array_join(F.slice("w", i, n), " ").cast("binary")))).alias("shingle")).distinct()


def doc_item(spark: SparkSession, sf_dir: str, n: int = 8) -> DataFrame:
    """document -> benchmark item with which it shares a run of n words."""
    docs = shingles(table(spark, sf_dir, "documents"), "doc_id", "text", n)
    items = shingles(table(spark, sf_dir, "benchmark"), "item_id", "text", n)
    return clean_arcs(docs.join(items, "shingle").select(_kind("doc", "doc_id").alias("src"), _kind("item", "item_id").alias("dst")))


VIEWS: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "g1": part_succession,
    "g2": sparse_part_succession,
    "g3": customer_supplier,
    "g4": user_handoff,
    "g5": error_handoff,
    "g6": page_terms,
    "g7": host_terms,
    "g8": page_page,
    "g9": turn_chain,
    "g10": shared_lines,
    "g11": geo_tree,
    "g12": vector_knn,
    "g13": doc_item,
}

#: Views whose arcs are read off whole texts: found once, not for vertices and arcs apart.
KEPT = {"g10"}
#: Views whose nodes' arcs follow from a key each (id, gives, takes), so that equal nodes need not be told apart.
KEYS: dict[str, Callable[[SparkSession, str], DataFrame]] = {"g8": page_keys}


def graph(spark: SparkSession, sf_dir: str, view: str) -> Graph:
    """A view as a graph on the nodes that touch an arc."""
    arcs = VIEWS[view](spark, sf_dir)
    return Graph.from_arcs(cut(arcs) if view in KEPT else arcs)
