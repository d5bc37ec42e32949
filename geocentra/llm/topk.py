"""Exact top-k inner-product search: the threshold algorithm over sorted per-dimension lists."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from geocentra.llm import blocks as B
from geocentra.llm.plan import cut, load, small_batches

SHARD_ROWS = 4096
QUERY_BLOCK = 2048
STEP = 64


def _matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks) if column.num_chunks else pa.array([], pa.list_(pa.int64()))
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 0)


class SortedLists:
    """Vectors of one shard with, for each dimension, their order by that component."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray):
        by_id = np.argsort(ids, kind="stable")
        self.ids, self.vectors = ids[by_id], vectors[by_id]
        self.order = np.argsort(self.vectors, axis=0, kind="stable")
        self.values = np.take_along_axis(self.vectors, self.order, axis=0)

    def search(self, query: np.ndarray, k: int, skip: int | None) -> tuple[np.ndarray, np.ndarray]:
        """The k best (place, score), ties to the smaller id. Lists are read from the end that favours the
        query's sign, `STEP` entries at a time; every vector met is scored in full; reading stops when no
        unread vector can reach the kth score (reaching it would still matter, for the smaller id)."""
        n = len(self.ids)
        used = np.flatnonzero(query)
        seen = np.zeros(n, bool)
        best_at, best = np.zeros(0, np.int64), np.zeros(0, np.int64)
        down = query[used] > 0
        depth = 0
        while depth < n:
            to = min(n, depth + STEP)
            rows = np.where(down[:, None], n - 1 - np.arange(depth, to), np.arange(depth, to)) if len(used) else np.arange(depth, to)[None]
            met = self.order[rows, used[:, None]].ravel() if len(used) else rows.ravel()
            fresh = np.zeros(n, bool)
            fresh[met] = True
            fresh &= ~seen
            seen |= fresh
            at = np.flatnonzero(fresh)
            if skip is not None:
                at = at[self.ids[at] != skip]
            if len(at):
                score = self.vectors[at] @ query
                if len(best) >= k:  # of the new, only those that can enter
                    good = score >= best[-1]
                    at, score = at[good], score[good]
                best_at, best = np.concatenate((best_at, at)), np.concatenate((best, score))
                keep = np.lexsort((self.ids[best_at], -best))[:k]
                best_at, best = best_at[keep], best[keep]
            depth = to
            if seen.all():
                break
            if len(best) >= k and len(used):
                edge = np.where(down, n - depth, depth - 1)
                if int((self.values[edge, used] * query[used]).sum()) < best[-1]:
                    break
        return best_at, best


    def packed(self) -> bytes:
        return B.pack(self.ids, self.vectors.ravel(), self.order.ravel().astype(np.int32))

    @classmethod
    def unpacked(cls, blob: bytes) -> SortedLists:
        self = cls.__new__(cls)
        self.ids, vectors, order = B.unpack(blob)
        n = len(self.ids)
        self.vectors, self.order = vectors.reshape(n, -1), order.reshape(n, -1).astype(np.int64)
        self.values = np.take_along_axis(self.vectors, self.order, axis=0)
        return self


_BLOB = "shard int, kind int, dims int, blob binary"


def _blob(shard: int, kind: int, dims: int, blob: bytes) -> pa.Table:
    return pa.table({"shard": pa.array([shard], pa.int32()), "kind": pa.array([kind], pa.int32()), "dims": pa.array([dims], pa.int32()), "blob": pa.array([blob], pa.binary())})


def _build_shard(table: pa.Table) -> pa.Table:
    lists = SortedLists(table.column("vec_id").to_numpy(), _matrix(table.column("v")))
    return _blob(table.column("shard")[0].as_py(), -1, table.column("dims")[0].as_py(), lists.packed())


def _build_block(table: pa.Table) -> pa.Table:
    return _blob(-1, table.column("kind")[0].as_py(), table.column("dims")[0].as_py(), B.pack(table.column("vec_id").to_numpy(), _matrix(table.column("v")).ravel()))


def _search_shard(k: int):
    """A shard's lists, which come first, and all blocks of queries, one after another."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lists: dict[int, SortedLists] = {}
        for batch in batches:
            for i in range(batch.num_rows):
                shard, kind, dims, blob = (batch.column(c)[i].as_py() for c in ("shard", "kind", "dims", "blob"))
                if kind < 0:
                    lists[dims] = SortedLists.unpacked(blob)
                    continue
                if dims not in lists:
                    continue
                asked, wanted = B.unpack(blob)
                out = []
                for q, vector in zip(asked.tolist(), wanted.reshape(len(asked), -1), strict=True):
                    at, score = lists[dims].search(vector, k, q)
                    out.append((np.full(len(at), q), lists[dims].ids[at], score))
                got = [np.concatenate(x) for x in zip(*out, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(got[0]), shard), pa.int32()), *[pa.array(x, pa.int64()) for x in got]], names=["shard", "query_id", "vec_id", "score"])

    return run


def integer_vectors(vectors: DataFrame, id_col: str, vector_col: str, scale: int) -> DataFrame:
    """vec_id, v: floor(scale * x) of each component; rows with a null or non-finite component, or no id, are left out."""
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vector_col).cast("array<double>").alias("v")).where("vec_id is not null and v is not null")
    fine = F.forall("v", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return rows.where(fine).select("vec_id", F.transform("v", lambda x: F.floor(x * scale)).alias("v"))


def top_k(vectors: DataFrame, is_query, id_col: str = "vec_id", vector_col: str = "embedding", k: int = 5, scale: int = 256) -> DataFrame:
    """The k best inner products of each query row among all rows of other ids.

    `is_query` is a condition on the column vec_id. Returns query_id, rank (from 1),
    vec_id, score; ties go to the smaller id. Components become floor(scale * x).

    Rows with a null id or vector, or with a null or non-finite component, take no
    part. Vectors of another length than the query's are no candidates of it. Of rows
    that repeat an id the one with the least vector counts. With fewer than k
    candidates all are returned; an empty table gives no rows.

    Vectors are dealt once to shards of about `SHARD_ROWS` by a hash of their id and
    written as sorted lists. Queries are written as blocks of about `QUERY_BLOCK` and
    stream through every shard, a block at a time; one plan serves any number of them.
    Each shard returns at most k rows a query.
    """
    spark = vectors.sparkSession
    rows = cut(integer_vectors(vectors, id_col, vector_col, scale).groupBy("vec_id").agg(F.min("v").alias("v")).select("vec_id", "v", F.size("v").alias("dims")))
    n_shards = max(1, math.ceil(rows.count() / SHARD_ROWS))
    asked = rows.where(is_query)
    n_blocks = max(1, math.ceil(asked.count() / QUERY_BLOCK))
    spread = lambda n, seed: F.pmod(F.xxhash64("vec_id", F.lit(seed)), F.lit(n)).cast("int")
    shards = rows.withColumn("shard", spread(n_shards, 3)).groupBy("shard", "dims").applyInArrow(_build_shard, _BLOB)
    blocks = cut(asked.withColumn("kind", spread(n_blocks, 7)).groupBy("kind", "dims").applyInArrow(_build_block, _BLOB))
    everywhere = blocks.withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(n_shards - 1)))).select("shard", "kind", "dims", "blob")
    with small_batches(spark, 16):
        met = shards.unionByName(everywhere).repartition(n_shards, "shard").sortWithinPartitions("shard", "kind").groupBy("shard")
        found = cut(met.applyInArrow(_search_shard(k), "shard int, query_id long, vec_id long, score long"))
    # The k best of some shards' lists, then of these: never more than a few hundred rows of one query together.
    width = math.isqrt(n_shards) + 1
    if n_shards > 64:
        found = _best(found.withColumn("shard", (F.col("shard") / width).cast("int")), ["query_id", "shard"], k)
    return _best(found, ["query_id"], k).select("query_id", F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")).alias("rank"), "vec_id", "score")


def _best(found: DataFrame, by: list[str], k: int) -> DataFrame:
    top = F.slice(F.array_sort(F.collect_list(F.struct((-F.col("score")).alias("s"), "vec_id"))), 1, k)
    return found.groupBy(*by).agg(top.alias("best")).select(*by, F.explode("best").alias("x")).select(*by, "x.vec_id", (-F.col("x.s")).alias("score"))


def op10_top_k(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_k(load(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


ORACLE = r"""
WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::BIGINT) AS v FROM embeddings WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
p AS (SELECT q.vec_id AS query_id, c.vec_id, list_sum(list_transform(list_zip(q.v, c.v), lambda z: z[1] * z[2]))::BIGINT AS score FROM e q JOIN e c ON q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0),
r AS (SELECT query_id, row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS rank, vec_id, score FROM p)
SELECT query_id, rank::INTEGER AS rank, vec_id, score FROM r WHERE rank <= 5
"""
