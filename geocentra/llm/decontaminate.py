"""Benchmark decontamination: a prefix-filtered join of item windows with document words."""

from __future__ import annotations

import math
from collections.abc import Iterable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from geocentra.llm import blocks as B
from geocentra.llm.plan import load, text_bytes

BLOCK_BYTES = 8 << 20
PIECE_BYTES = 4 << 20


def _folded_words(column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    raw, offs = B.text_block(column)
    raw = B.LOWER[raw]
    starts, ends, by_text = B.words(raw, offs, B.ALNUM)
    return raw, starts, ends, by_text, B.word_hashes(raw, starts, ends)


def _count_known(known):
    """How often each benchmark word occurs in the corpus: one row per word and piece."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = known.value
        total = np.zeros(len(vocabulary), np.int64)
        for piece in B.chunks(batches, "text", PIECE_BYTES):
            h = _folded_words(piece.column("text"))[4]
            at = _find(vocabulary, h)
            total += np.bincount(at[at >= 0], minlength=len(vocabulary))
        hit = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(vocabulary[hit].view(np.int64)), pa.array(total[hit])], names=["word", "n"])

    return run


def _find(sorted_values: np.ndarray, wanted: np.ndarray) -> np.ndarray:
    """The place of each wanted value, or -1. A table of the high 16 bits turns most searches away."""
    if not len(sorted_values):
        return np.full(len(wanted), -1, np.int64)
    there = np.zeros(1 << 16, bool)
    there[(sorted_values >> B.U64(48)).astype(np.int64)] = True
    maybe = np.flatnonzero(there[(wanted >> B.U64(48)).astype(np.int64)])
    at = np.searchsorted(sorted_values, wanted[maybe])
    at[at == len(sorted_values)] = 0
    out = np.full(len(wanted), -1, np.int64)
    same = sorted_values[at] == wanted[maybe]
    out[maybe[same]] = at[same]
    return out


class ItemIndex:
    """All windows of a block of items, found by the rarest word of each.

    The join asks for containment of a whole window, so the necessary prefix of its
    words in rarity order is one word: a document can hold the window only where it
    holds that word. Where the word stands in the window says where the window would
    start, and so whether it fits into the document at all; what is left is compared
    word by word. Equal windows are one entry with a list of items.
    """

    def __init__(self, ids: np.ndarray, by_item: np.ndarray, words: np.ndarray, width: int, vocabulary: np.ndarray, frequency: np.ndarray):
        size = np.diff(by_item)
        starts = B.window_starts(by_item, width)
        length = np.full(len(starts), width, np.int64)
        short = np.flatnonzero((size > 0) & (size < width))
        starts, length = np.concatenate((starts, by_item[short])), np.concatenate((length, size[short]))
        owner = np.searchsorted(by_item, starts, side="right") - 1
        # One row of `width` words per window; shorter ones are filled with zeros.
        offset = np.arange(width)
        inside = offset < length[:, None]
        table = np.where(inside, words[np.minimum(starts[:, None] + offset, max(0, len(words) - 1))], B.U64(0)) if len(starts) else np.zeros((0, width), B.U64)
        table, back = np.unique(np.concatenate((table, length[:, None].astype(B.U64)), axis=1), axis=0, return_inverse=True)
        self.width, self.length, self.words = width, table[:, width].astype(np.int64), np.ascontiguousarray(table[:, :width])
        pair = np.unique(np.stack((back.ravel(), owner), axis=1), axis=0) if len(starts) else np.zeros((0, 2), np.int64)
        self.item_offsets, self.items = np.searchsorted(pair[:, 0], np.arange(len(table) + 1)), ids[pair[:, 1]]
        at = np.searchsorted(vocabulary, self.words)
        at[at == len(vocabulary)] = 0
        rank = np.where(offset < self.length[:, None], frequency[at] if len(frequency) else 0, np.iinfo(np.int64).max)
        lead = rank.argmin(axis=1) if len(rank) else np.zeros(0, np.int64)
        key = self.words[np.arange(len(lead)), lead]
        order = np.argsort(key, kind="stable")
        self.keys, first = np.unique(key[order], return_index=True)
        self.first = np.concatenate((first, [len(order)])).astype(np.int64)
        self.window, self.lead = order, lead[order]

    def occurrences(self, words: np.ndarray, by_text: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(text, first word, window) of every occurrence."""
        at = _find(self.keys, words)
        place = np.flatnonzero(at >= 0)
        k = at[place]
        count = self.first[k + 1] - self.first[k]
        entry = B.ranges(self.first[k], count)
        place = np.repeat(place, count)
        text = np.searchsorted(by_text, place, side="right") - 1
        start, window = place - self.lead[entry], self.window[entry]
        fits = (start >= by_text[text]) & (start + self.length[window] <= by_text[text + 1])
        text, start, window = text[fits], start[fits], window[fits]
        for j in range(self.width):  # fewer are left with each word
            live = (j >= self.length[window]) | (words[np.minimum(start + j, len(words) - 1)] == self.words[window, j])
            text, start, window = text[live], start[live], window[live]
        return text, start, window


def _apply(index, carry_text: bool):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ix = index.value
        for piece in B.chunks(batches, "text", PIECE_BYTES):
            n = piece.num_rows
            raw, starts, ends, by_text, h = _folded_words(piece.column("text"))
            text, start, window = ix.occurrences(h, by_text)
            hit = B.covered(start, start + ix.length[window], len(starts))
            before = np.concatenate(([0], np.cumsum(hit)))
            count = ix.item_offsets[window + 1] - ix.item_offsets[window]
            pair = np.unique(np.stack((np.repeat(text, count), ix.items[B.ranges(ix.item_offsets[window], count)]), axis=1), axis=0) if len(text) else np.zeros((0, 2), np.int64)
            offsets = np.searchsorted(pair[:, 0], np.arange(n + 1)).astype(np.int32)
            items = pa.ListArray.from_arrays(pa.array(offsets), pa.array(pair[:, 1], pa.int64()))
            first, last, owner = B.runs_by_text(hit, by_text)
            spans = B.span_lists(first - by_text[owner], last - by_text[owner], owner, n)
            if carry_text:
                clean = B.without(*B.text_block(piece.column("text")), starts[first], ends[last - 1])
            else:
                clean = pa.nulls(n, pa.string())
            yield pa.RecordBatch.from_arrays(
                [piece.column("id"), pa.array(np.diff(by_text), pa.int64()), pa.array(before[by_text[1:]] - before[by_text[:-1]], pa.int64()), items, spans, clean, piece.column("carried")],
                names=["id", "n_words", "n_hit", "items", "spans", "clean_text", "carried"],
            )

    return run


def decontaminate(
    docs: DataFrame,
    items: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    item_col: str = "item_id",
    item_text_col: str = "text",
    width: int = 10,
    carry: Sequence[str] = (),
    clean_text: bool = False,
) -> DataFrame:
    """Find every window of `width` item words in the documents, A-Z folded.

    Returns id, n_words, n_hit (words inside any occurrence), items (ids of the items
    whose windows occur), spans (maximal hit word intervals), clean_text (the text
    without these, if asked for) and carried (a struct of the columns in `carry`).
    An item of fewer words than `width`, but not none, is one window of its own length.

    Null or empty texts have no words and no hits, null ids stay null, repeated rows
    are each judged, items without an id or words match nothing, and an empty
    benchmark finds nothing.

    Windows are compared word by word by 64-bit word hashes. Word frequencies are
    counted over the whole corpus. The index of the items goes to the tasks in blocks
    of at most `BLOCK_BYTES` of item text, one scan of the documents for each block,
    so that its size is bounded however large the benchmark is.
    """
    spark = docs.sparkSession
    sc = spark.sparkContext
    carried = F.struct(*[F.col(c) for c in carry]) if carry else F.struct(F.lit(True).alias("none"))
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).cast("string").alias("text"), carried.alias("carried"))
    known_items = items.select(F.col(item_col).cast("long").alias("item"), F.col(item_text_col).cast("string").alias("text")).where("item is not null and text is not null")
    n_blocks = max(1, math.ceil(text_bytes(known_items, "text") / BLOCK_BYTES))
    block = F.pmod(F.xxhash64("item"), F.lit(n_blocks))
    out = T.StructType(
        [
            T.StructField("id", T.LongType()),
            T.StructField("n_words", T.LongType()),
            T.StructField("n_hit", T.LongType()),
            T.StructField("items", T.ArrayType(T.LongType())),
            T.StructField("spans", T.ArrayType(T.StructType([T.StructField("start", T.LongType()), T.StructField("end", T.LongType())]))),
            T.StructField("clean_text", T.StringType()),
            T.StructField("carried", rows.schema["carried"].dataType),
        ]
    )
    if n_blocks > 1:
        return _by_blocks(rows, known_items, block, n_blocks, width, clean_text, out)
    return rows.mapInArrow(_apply(sc.broadcast(_index(rows, known_items, width)), clean_text), out)


def _index(rows: DataFrame, items: DataFrame, width: int) -> ItemIndex:
    """The index of one block of items; its size is bounded by the block's."""
    sc = rows.sparkSession.sparkContext
    got = items.toArrow()
    ids = got.column("item").to_numpy()
    _, _, _, by_item, h = _folded_words(got.column("text"))
    vocabulary = np.unique(h)
    counted = rows.select("text").mapInArrow(_count_known(sc.broadcast(vocabulary)), "word long, n long").groupBy("word").agg(F.sum("n").alias("n")).toArrow()
    frequency = np.zeros(len(vocabulary), np.int64)
    frequency[np.searchsorted(vocabulary, counted.column("word").to_numpy().view(B.U64))] = counted.column("n").to_numpy()
    return ItemIndex(ids, by_item, h, width, vocabulary, frequency)


def _by_blocks(rows: DataFrame, items: DataFrame, block, n_blocks: int, width: int, clean_text: bool, out: T.StructType) -> DataFrame:
    """Items that exceed one block: each block's index scans the rows in turn and adds to their spans and items."""
    sc = rows.sparkSession.sparkContext
    found = rows.select("*", F.array().cast("array<long>").alias("so_far"), F.array().cast("array<struct<start:long,end:long>>").alias("spanned"))
    for k in range(n_blocks):
        index = sc.broadcast(_index(rows, items.where(block == k), width))
        packed = found.select("id", "text", F.struct("text", "carried", "so_far", "spanned").alias("carried"))
        schema = T.StructType([T.StructField("carried", packed.schema["carried"].dataType) if f.name == "carried" else f for f in out])
        step = packed.mapInArrow(_apply(index, False), schema)
        found = step.select("id", "carried.text", "carried.carried", F.array_union("carried.so_far", "items").alias("so_far"), F.concat("carried.spanned", "spans").alias("spanned"))
    packed = found.select("id", "text", F.struct("carried", "so_far", "spanned").alias("carried"))
    return packed.mapInArrow(_merge(clean_text), out)


def _merge(carry_text: bool):
    """The union of the spans that several blocks found."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in B.chunks(batches, "text", PIECE_BYTES):
            n = piece.num_rows
            raw, starts, ends, by_text, _ = _folded_words(piece.column("text"))
            inside = piece.column("carried")
            lists = inside.field("spanned")
            owner = np.repeat(np.arange(n), np.diff(np.asarray(lists.offsets)))
            flat = lists.flatten()
            a = flat.field("start").to_numpy(zero_copy_only=False).astype(np.int64) + by_text[owner]
            z = flat.field("end").to_numpy(zero_copy_only=False).astype(np.int64) + by_text[owner]
            hit = B.covered(a, z, len(starts))
            before = np.concatenate(([0], np.cumsum(hit)))
            first, last, whose = B.runs_by_text(hit, by_text)
            clean = B.without(*B.text_block(piece.column("text")), starts[first], ends[last - 1]) if carry_text else pa.nulls(n, pa.string())
            yield pa.RecordBatch.from_arrays(
                [piece.column("id"), pa.array(np.diff(by_text), pa.int64()), pa.array(before[by_text[1:]] - before[by_text[:-1]], pa.int64()), inside.field("so_far"), B.span_lists(first - by_text[whose], last - by_text[whose], whose, n), clean, inside.field("carried")],
                names=["id", "n_words", "n_hit", "items", "spans", "clean_text", "carried"],
            )

    return run


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = decontaminate(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark"))
    names = F.array_join(F.array_sort(F.transform("items", lambda x: x.cast("string"))), ",")
    return got.select(F.col("id").alias("doc_id"), "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(names, 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


ORACLE = r"""
WITH d AS (SELECT doc_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), []) AS ws FROM documents),
b AS (SELECT item_id, coalesce(regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+'), []) AS ws FROM benchmark),
item_windows AS (SELECT DISTINCT item_id, least(10, len(ws)) AS n, array_to_string(ws[i : i + 9], ' ') AS seq FROM (SELECT item_id, ws, unnest(range(1, greatest(len(ws) - 9, 1) + 1)) AS i FROM b WHERE len(ws) > 0)),
sizes AS (SELECT DISTINCT n FROM item_windows),
doc_windows AS (SELECT doc_id, n, i AS pos, array_to_string(ws[i : i + n - 1], ' ') AS seq FROM (SELECT doc_id, ws, n, unnest(range(1, len(ws) - n + 2)) AS i FROM d, sizes WHERE len(ws) >= n)),
found AS (SELECT w.doc_id, w.pos, w.n, i.item_id FROM doc_windows w JOIN item_windows i ON w.seq = i.seq AND w.n = i.n),
hit AS (SELECT doc_id, count(DISTINCT pos + k) AS n_hit FROM (SELECT DISTINCT doc_id, pos, n FROM found), (SELECT unnest(range(10)) AS k) WHERE k < n GROUP BY doc_id),
named AS (SELECT doc_id, count(*) AS n_items, string_agg(name, ',' ORDER BY name) AS names FROM (SELECT DISTINCT doc_id, item_id::VARCHAR AS name FROM found) GROUP BY doc_id)
SELECT d.doc_id, len(d.ws)::BIGINT AS n_words, coalesce(h.n_hit, 0) AS n_hit, coalesce(n.n_items, 0) AS n_items, sha256(coalesce(n.names, '')) AS items_sha256, coalesce(h.n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN hit h ON d.doc_id = h.doc_id LEFT JOIN named n ON d.doc_id = n.doc_id
"""
