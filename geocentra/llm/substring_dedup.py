"""Substring dedup: rolling hashes of all token windows; repeated windows become removal intervals."""

from __future__ import annotations

from collections.abc import Iterable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from geocentra.llm import blocks as B
from geocentra.llm.exchange import doc_table, slices
from geocentra.llm.plan import load, parts_for, text_bytes

BUCKET_BYTES = 16 << 20
GROUP_BYTES = 8 << 20
PIECE_BYTES = 8 << 20
#: Bytes of a second, independent hash that travel with the seven of the first.
CHECK_BYTES = 2


def _send_windows(width: int, n_buckets: int):
    """Map side: every window hash of a piece of text once, and what is already a repeat inside the piece."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        turn = 0
        for piece in B.chunks(batches, "text", PIECE_BYTES):
            ids = piece.column("id").to_numpy(zero_copy_only=False)
            order = np.argsort(ids, kind="stable")
            piece, ids = piece.take(pa.array(order)), ids[order]
            group = piece.column("g").to_numpy(zero_copy_only=False)
            raw, offs = B.text_block(piece.column("text"))
            starts, ends, by_doc = B.words(raw, offs, B.NON_SPACE)
            at = B.window_starts(by_doc, width)
            if not len(at):
                continue
            h = B.window_hashes(B.word_hashes(raw, starts, ends), width)[at]
            check = B.window_hashes(B.word_hashes(raw, starts, ends, second=True), width, second=True)[at]
            doc = np.searchsorted(by_doc, at, side="right") - 1
            pos = at - by_doc[doc]
            tied = bool((ids[1:] == ids[:-1]).any())
            if tied:  # versions of one document: order by position across them
                order = np.lexsort((pos, ids[doc]))
                h, check, doc, pos = h[order], check[order], doc[order], pos[order]
            order = B.sorted_with_index(h)
            again = np.concatenate(([False], (h[order[1:]] == h[order[:-1]]) & (check[order[1:]] == check[order[:-1]])))
            if tied:
                head = np.maximum.accumulate(np.where(again, 0, np.arange(len(order))))
                again &= (ids[doc[order]] != ids[doc[order[head]]]) | (pos[order] != pos[order[head]])
            sent, local = order[~again], np.sort(order[again])
            part, blobs = [], []
            for k, piece_of in slices(B.bucket_of(h[sent], n_buckets), n_buckets):
                w = np.sort(sent[piece_of])
                first, count = doc_table(doc[w])
                d = doc[w[first]]
                part.append(k)
                blobs.append(B.pack(ids[d], group[d], count.astype(np.int32), B.gaps(pos[w], count), np.concatenate((B.low_bytes(h[w]), B.low_bytes(check[w], CHECK_BYTES)), axis=1)))
            if len(local):
                first, count = doc_table(doc[local])
                d = doc[local[first]]
                part.append(turn % n_buckets)
                blobs.append(B.pack(ids[d], group[d], count.astype(np.int32), B.gaps(pos[local], count)))
                turn += 1
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), pa.array(blobs, pa.binary())], names=["bucket", "blob"])

    return run


def _judge(table: pa.Table) -> pa.Table:
    """One bucket of hashes: all but the earliest start of each; by group of documents."""
    B.release()
    known, late = [], []
    for blob in table.column("blob").to_pylist():
        ids, group, count, gap, *h = B.unpack(blob)
        count = count.astype(np.int64)
        row = (np.repeat(ids, count), np.repeat(group, count), B.ungaps(gap, count))
        if h:
            known.append((*row, B.from_bytes(h[0][:, :-CHECK_BYTES]), B.from_bytes(h[0][:, -CHECK_BYTES:])))
        else:
            late.append(row)
    if known:
        doc, group, pos, h, check = (np.concatenate(x) for x in zip(*known, strict=True))
        order = np.argsort(h)
        hs = h[order]
        same = hs[1:] == hs[:-1]
        shared = order[np.concatenate((same, [False])) | np.concatenate(([False], same))]
        shared = shared[np.lexsort((pos[shared], doc[shared], check[shared], h[shared]))]
        if len(shared):
            again = np.concatenate(([False], (h[shared[1:]] == h[shared[:-1]]) & (check[shared[1:]] == check[shared[:-1]])))
            head = shared[np.maximum.accumulate(np.where(again, 0, np.arange(len(shared))))]
            gone = shared[again & ((doc[shared] != doc[head]) | (pos[shared] != pos[head]))]
            late.append((doc[gone], group[gone], pos[gone]))
    if not late:
        return pa.table({"g": pa.array([], pa.int32()), "blob": pa.array([], pa.binary())})
    doc, group, pos = (np.concatenate(x) for x in zip(*late, strict=True))
    order = np.lexsort((pos, doc, group))
    doc, group, pos = doc[order], group[order], pos[order]
    g, blobs = [], []
    first, count = doc_table(group)
    for a, n in zip(first.tolist(), count.tolist(), strict=True):
        f, c = doc_table(doc[a : a + n])
        g.append(int(group[a]))
        blobs.append(B.pack(doc[a : a + n][f], c.astype(np.int32), B.gaps(pos[a : a + n], c)))
    return pa.table({"g": pa.array(g, pa.int32()), "blob": pa.array(blobs, pa.binary())})


def found_positions(blobs: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(document id, position) pairs of several blobs, by id."""
    rows = []
    for blob in blobs:
        ids, count, gap = B.unpack(blob)
        count = count.astype(np.int64)
        rows.append((np.repeat(ids, count), B.ungaps(gap, count)))
    if not rows:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    doc, pos = (np.concatenate(x) for x in zip(*rows, strict=True))
    order = np.argsort(doc, kind="stable")
    return doc[order], pos[order]


def positions_of(ids: pa.Array, doc: np.ndarray, pos: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each row, by its id, the positions found: as (row, position) pairs. A null id has none."""
    known = ids.is_valid().to_numpy(zero_copy_only=False)
    value = ids.fill_null(0).to_numpy(zero_copy_only=False)
    lo, hi = np.searchsorted(doc, value, side="left"), np.searchsorted(doc, value, side="right")
    count = np.where(known, hi - lo, 0)
    return np.repeat(np.arange(len(value)), count), pos[B.ranges(lo, count)]


def _remove(width: int, in_place: bool):
    def run(docs: pa.Table, late: pa.Table) -> pa.Table:
        B.release()
        doc, pos = found_positions(late.column("blob").to_pylist())
        out = []
        for piece in B.chunks(docs.combine_chunks().to_batches(), "text", PIECE_BYTES):
            n = piece.num_rows
            raw, offs = B.text_block(piece.column("text"))
            starts, ends, by_doc = B.words(raw, offs, B.NON_SPACE)
            row, at = positions_of(piece.column("id"), doc, pos)
            first = at + by_doc[row]
            fits = first < by_doc[row + 1]
            row, first = row[fits], first[fits]
            gone = B.covered(first, np.minimum(first + width, by_doc[row + 1]), len(starts))
            total = np.diff(by_doc)
            before = np.concatenate(([0], np.cumsum(gone)))
            removed = before[by_doc[1:]] - before[by_doc[:-1]]
            a, z, own = B.runs_by_text(gone, by_doc)
            out.append(
                pa.table(
                    {
                        "id": piece.column("id"),
                        "n_words": pa.array(total, pa.int64()),
                        "n_removed": pa.array(removed, pa.int64()),
                        "kept_text": B.without(raw, offs, starts[a], ends[z - 1]) if in_place else B.joined(raw, starts[~gone], ends[~gone], total - removed),
                        "spans": B.span_lists(a - by_doc[own], z - by_doc[own], own, n),
                        "carried": piece.column("carried"),
                    }
                )
            )
        return pa.concat_tables(out)

    def whole(docs: pa.Table, late: pa.Table) -> pa.Table:
        if docs.num_rows:
            return run(docs, late)
        empty = pa.array([], pa.int64())
        spans = B.span_lists(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64), 0)
        return pa.table({"id": empty, "n_words": empty, "n_removed": empty, "kept_text": pa.array([], pa.string()), "spans": spans, "carried": pa.array([], docs.schema.field("carried").type)})

    return whole


def _group(size: int):
    """A group number that spreads documents evenly; those without an id, which may all be equal, by their place in the input."""
    return F.pmod(F.when(F.col("id").isNull(), F.xxhash64(F.monotonically_increasing_id())).otherwise(F.xxhash64("id")), F.lit(size)).cast("int")


def substring_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", width: int = 20, carry: Sequence[str] = (), in_place: bool = False) -> DataFrame:
    """Remove every word that a repeated window of `width` words covers.

    A window is removed if its word sequence also starts earlier: in a document of a
    smaller id, or earlier in the same document. Windows are judged on the input.
    Returns id, n_words, n_removed, kept_text (kept words joined by one space; with
    `in_place` the text as it was, but for what lies from the first to the last word of
    each removed interval), spans (maximal removed word intervals) and carried (a
    struct of the columns in `carry`, so that clashing names stay apart).

    Null or empty texts have no words. Rows without an id cannot be ordered: they lose
    nothing and protect nothing. Rows that repeat an id are versions of one document:
    what is found at a position holds for all of them. An empty table gives no rows.

    Each piece of text sends a hash once, however often it holds it, so that a window
    found everywhere costs one record a piece. Windows are equal if 56 bits of one rolling
    hash and 16 of another, over words hashed with other bases, agree within a bucket that
    fixes up to 8 more: of 10**12 different windows less than one is taken for a copy.
    """
    spark = docs.sparkSession
    size = text_bytes(docs, text_col)
    n_buckets, n_groups = parts_for(spark, size, BUCKET_BYTES), parts_for(spark, size, GROUP_BYTES)
    carried = F.struct(*[F.col(c) for c in carry]) if carry else F.struct(F.lit(True).alias("none"))
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"), carried.alias("carried"))
    rows = rows.select("id", "text", "carried", _group(n_groups).alias("g"))
    sent = rows.where("id is not null").select("id", "g", "text").mapInArrow(_send_windows(width, n_buckets), "bucket int, blob binary")
    late = sent.groupBy("bucket").applyInArrow(_judge, "g int, blob binary")
    out = T.StructType(
        [
            T.StructField("id", T.LongType()),
            T.StructField("n_words", T.LongType()),
            T.StructField("n_removed", T.LongType()),
            T.StructField("kept_text", T.StringType()),
            T.StructField("spans", T.ArrayType(T.StructType([T.StructField("start", T.LongType()), T.StructField("end", T.LongType())]))),
            T.StructField("carried", rows.schema["carried"].dataType),
        ]
    )
    return rows.groupBy("g").cogroup(late.groupBy("g")).applyInArrow(_remove(width, in_place), out)


def op1_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = substring_dedup(load(spark, sf_dir, "documents"))
    return got.select(F.col("id").alias("doc_id"), "n_words", "n_removed", F.sha2("kept_text", 256).alias("kept_sha256"))


ORACLE = r"""
WITH t AS (SELECT doc_id, coalesce(regexp_extract_all(text, '[^\x20\x09-\x0D]+'), []) AS ws FROM documents),
windows AS (SELECT doc_id, i AS pos, array_to_string(ws[i : i + 19], ' ') AS seq FROM (SELECT doc_id, ws, unnest(range(1, len(ws) - 18)) AS i FROM t WHERE len(ws) >= 20)),
late AS (SELECT doc_id, pos FROM (SELECT doc_id, pos, row_number() OVER (PARTITION BY seq ORDER BY doc_id, pos) AS k FROM windows) WHERE k > 1),
gone AS (SELECT DISTINCT doc_id, pos + k AS pos FROM late, (SELECT unnest(range(20)) AS k)),
placed AS (SELECT doc_id, unnest(ws) AS word, unnest(range(1, len(ws) + 1)) AS pos FROM t),
judged AS (SELECT p.doc_id, p.word, p.pos, g.pos IS NOT NULL AS lost FROM placed p LEFT JOIN gone g ON p.doc_id = g.doc_id AND p.pos = g.pos),
digest AS (SELECT doc_id, count(*) AS n_words, count(*) FILTER (WHERE lost) AS n_removed, coalesce(string_agg(word, ' ' ORDER BY pos) FILTER (WHERE NOT lost), '') AS kept FROM judged GROUP BY doc_id)
SELECT d.doc_id, coalesce(g.n_words, 0) AS n_words, coalesce(g.n_removed, 0) AS n_removed, sha256(coalesce(g.kept, '')) AS kept_sha256
FROM documents d LEFT JOIN digest g ON d.doc_id = g.doc_id
"""
