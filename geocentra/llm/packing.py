"""Best-fit packing under conflicts: residual-ordered bins that carry source and duplicate-cluster bitmaps."""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from geocentra.llm import blocks as B
from geocentra.llm.minhash import near_duplicates
from geocentra.llm.plan import load, parts_for

GROUP_ROWS = 2048
LOOK = 64


class Bins:
    """Open bins in order of what is left in them, with a bitmap of sources and one of clusters each."""

    def __init__(self, capacity: int, n_sources: int, n_clusters: int):
        self.capacity = capacity
        self.left = np.zeros(0, np.int64)  # ascending, ties in order of opening
        self.bin = np.zeros(0, np.int64)
        self.sources = np.zeros((0, max(1, -(-n_sources // 64))), np.uint64)
        self.clusters = np.zeros((0, max(1, -(-n_clusters // 64))), np.uint64)
        self.count = 0

    def place(self, size: int, source: int, cluster: int) -> int:
        """The bin in which the piece leaves the least room among those it may enter, or a new one.

        -1 as a source or cluster conflicts with nothing. From the first bin that is wide
        enough the search goes on to the next wider ones until one has neither.
        """
        at = int(np.searchsorted(self.left, size))
        n = len(self.left)
        while at < n:
            block = self.bin[at : at + LOOK]
            free = np.ones(len(block), bool)
            if source >= 0:
                free &= (self.sources[block, source >> 6] >> np.uint64(source & 63)) & np.uint64(1) == 0
            if cluster >= 0:
                free &= (self.clusters[block, cluster >> 6] >> np.uint64(cluster & 63)) & np.uint64(1) == 0
            hit = int(free.argmax())
            if free[hit]:
                at += hit
                break
            at += LOOK
        if at < n:
            b, left = int(self.bin[at]), int(self.left[at]) - size
            self.left, self.bin = np.delete(self.left, at), np.delete(self.bin, at)
        else:
            b, left = self.count, self.capacity - size
            self.count += 1
            if b == len(self.sources):
                grown = max(256, 2 * b)
                self.sources = np.concatenate((self.sources, np.zeros((grown - b, self.sources.shape[1]), np.uint64)))
                self.clusters = np.concatenate((self.clusters, np.zeros((grown - b, self.clusters.shape[1]), np.uint64)))
        if source >= 0:
            self.sources[b, source >> 6] |= np.uint64(1) << np.uint64(source & 63)
        if cluster >= 0:
            self.clusters[b, cluster >> 6] |= np.uint64(1) << np.uint64(cluster & 63)
        if left > 0:
            to = int(np.searchsorted(self.left, left, side="right"))
            self.left, self.bin = np.insert(self.left, to, left), np.insert(self.bin, to, b)
        return b


def _codes(values: pa.ChunkedArray, repeated_only: bool) -> np.ndarray:
    """Small numbers for equal values; -1 for null and, if asked, for values that occur once."""
    codes = values.combine_chunks().dictionary_encode()
    codes = (codes.combine_chunks() if isinstance(codes, pa.ChunkedArray) else codes).indices.fill_null(-1).to_numpy(zero_copy_only=False).astype(np.int64)
    if repeated_only and len(codes):
        times = np.bincount(codes[codes >= 0], minlength=1)
        number = np.where(times > 1, np.cumsum(times > 1) - 1, -1)
        codes = np.where(codes >= 0, number[np.maximum(codes, 0)], -1)
    return codes


def _pack(capacity: int):
    def run(table: pa.Table) -> pa.Table:
        n = table.num_rows
        size = table.column("n_tokens").to_numpy()
        source, cluster = _codes(table.column("source"), False), _codes(table.column("cluster"), True)
        row = np.repeat(np.arange(n), np.maximum(1, -(-size // capacity)))
        first = np.concatenate(([0], np.flatnonzero(row[1:] != row[:-1]) + 1)) if n else np.zeros(0, np.int64)
        piece = np.arange(len(row)) - np.repeat(first, np.diff(np.concatenate((first, [len(row)]))))
        begin = piece * capacity
        length = np.minimum(size[row] - begin, capacity)
        text = table.column("order").to_numpy()[row]
        order = np.lexsort((piece, text, -length))
        bins = Bins(capacity, int(source.max(initial=-1)) + 1, int(cluster.max(initial=-1)) + 1)
        placed = np.zeros(len(row), np.int64)
        for i in order.tolist():
            placed[i] = bins.place(int(length[i]), int(source[row[i]]), int(cluster[row[i]]))
        # Empty texts take no room and conflict as others do; each piece's place in its bin is by length.
        rank = np.lexsort((np.arange(len(row)), -length, placed))
        slot, start = np.zeros(len(row), np.int64), np.zeros(len(row), np.int64)
        if len(row):
            b = placed[rank]
            head = np.concatenate(([0], np.flatnonzero(b[1:] != b[:-1]) + 1))
            reps = np.diff(np.concatenate((head, [len(b)])))
            total = np.cumsum(length[rank]) - length[rank]
            slot[rank] = np.arange(len(b)) - np.repeat(head, reps)
            start[rank] = total - np.repeat(total[head], reps)
        pick = pa.array(row)
        group = table.column("g").to_numpy()[row].astype(np.int64)
        return pa.table(
            {
                "id": table.column("id").take(pick),
                "piece": pa.array(piece, pa.int64()),
                "first_token": pa.array(begin, pa.int64()),
                "n_tokens": pa.array(length, pa.int64()),
                "bin": pa.array((group << 32) + placed, pa.int64()),
                "slot": pa.array(slot, pa.int64()),
                "start": pa.array(start, pa.int64()),
                "source": table.column("source").take(pick),
                "cluster": table.column("cluster").take(pick),
            }
        )

    return run


def _count_words(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows with the number of words, runs without white space, in place of their text."""
    for piece in B.chunks(batches, "n_tokens"):
        raw, offs = B.text_block(piece.column("n_tokens"))
        by_text = B.words(raw, offs, B.NON_SPACE)[2]
        yield piece.set_column(piece.schema.get_field_index("n_tokens"), "n_tokens", pa.array(np.diff(by_text), pa.int64()))


def pack_best_fit(
    docs: DataFrame, capacity: int = 2048, id_col: str = "doc_id", text_col: str = "text", source_col: str | None = "source", n_tokens: Column | None = None, cluster: Column | None = None, group_rows: int = GROUP_ROWS, clusters: DataFrame | None = None
) -> DataFrame:
    """Pack texts into bins of `capacity` tokens, best fit by decreasing length.

    No bin holds two texts of one source, nor two of one duplicate cluster. `n_tokens`
    is a column of lengths (default: words) and `cluster` one of cluster names
    (default: a hash of the text). `clusters` (id, version, component; see
    near_cluster_names) names the clusters of texts by id and hash of the text, and goes
    before `cluster`. A text longer than a bin is cut into pieces of full
    bins and a rest. Returns one row a piece: id, piece, first_token, n_tokens, bin,
    slot, start (the piece's place in the bin), source, cluster.

    Texts are dealt by a hash of id and text (without an id: of their place in the input) to groups of about `group_rows`, and each
    group packs its own bins; so a frequent source or cluster is spread evenly, and
    bins left open are a vanishing share. Null texts are empty; empty texts become one
    piece of no tokens. A null source or cluster conflicts with nothing. Null and
    repeated ids and repeated rows are packed as any other row (pieces of one text
    conflict through its source or cluster, and so stay apart). An empty table gives no rows.
    """
    spark = docs.sparkSession
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(
        F.col(id_col).cast("long").alias("id"),
        (n_tokens.cast("long") if n_tokens is not None else text).alias("n_tokens"),
        (F.col(source_col).cast("string") if source_col else F.lit(None).cast("string")).alias("source"),
        (cluster if cluster is not None else F.when(F.length(text) > 0, F.xxhash64(text))).cast("long").alias("cluster"),
        # Rows without an id, which may all be equal, are spread by their place in the input.
        F.when(F.col(id_col).isNull(), F.xxhash64(F.monotonically_increasing_id())).otherwise(F.xxhash64(id_col, text_col)).alias("order"),
        F.xxhash64(F.col(text_col).cast("string")).alias("version"),
    )
    if n_tokens is None:
        rows = rows.mapInArrow(_count_words, "id long, n_tokens long, source string, cluster long, order long, version long")
    if clusters is not None:
        rows = _renamed(rows, clusters)
    n_groups = parts_for(spark, docs.count(), group_rows)
    return rows.drop("version").withColumn("g", F.pmod("order", F.lit(n_groups)).cast("int")).groupBy("g").applyInArrow(
        _pack(capacity), "id long, piece long, first_token long, n_tokens long, bin long, slot long, start long, source string, cluster long"
    )


def near_cluster_names(docs: DataFrame) -> DataFrame:
    """id, version, component: the groups of near copies (five words, similarity 0.8), exact copies included."""
    return near_duplicates(docs, width=5, percent=80).where("id is not null and n_shingles > 0").select("id", "version", "component")


def _renamed(rows: DataFrame, clusters: DataFrame) -> DataFrame:
    """Rows with their clusters: by id and version; if these are not named, by version alone, and else as they are.

    Rows already named ask for a version by a hash of their own, so that no version has many rows in the second join.
    """
    by_text = clusters.groupBy("version").agg(F.min("component").alias("same")).withColumnRenamed("version", "asked")
    named = rows.join(clusters.dropDuplicates(["id"]), ["id", "version"], "left")
    asked = F.when(F.col("component").isNull() & F.col("cluster").isNotNull(), F.col("version")).otherwise(F.xxhash64("order", F.lit(17)))
    found = named.withColumn("asked", asked).join(by_text, "asked", "left")
    return found.withColumn("cluster", F.coalesce("component", F.when(F.col("cluster").isNotNull() & (F.col("asked") == F.col("version")), F.col("same")), "cluster")).drop("component", "asked", "same")


def op5_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents")
    return pack_best_fit(docs, clusters=near_cluster_names(docs)).withColumnRenamed("id", "doc_id")
