"""Quality classifier: perplexity under an interpolated modified Kneser-Ney model of trusted text."""

from __future__ import annotations

import math
from collections.abc import Iterable, Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from geocentra.llm import blocks as B
from geocentra.llm.exchange import slices
from geocentra.llm.plan import cut, load, parts_for, text_bytes
from geocentra.llm.substring_dedup import _group

#: Tokens are bytes; the model is of this order. A gram of ORDER bytes is one exact integer.
ORDER = 5
N_SHARDS = 64
GROUP_BYTES = 8 << 20
PIECE_BYTES = 1 << 19
#: Per language, at most this many trusted texts train the model: the documented bound of the training sample.
MAX_TRAINING_TEXTS = 4000
#: A shard of the model answers the groups of so much text; beyond it the shard is copied for other groups.
SALT_BYTES = 16 << 30
#: A threshold comes from texts within 0, 1 or 2 doublings of a length: the narrowest with so many, else from all of the language.
MIN_CALIBRATION = 30
WIDTHS = (0, 1, 2)
WHOLE = 3


def byte_grams(raw: np.ndarray, offs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The ORDER bytes that end at each byte of each text, as integers; a text begins after zero bytes.

    A zero byte ends each text and is predicted too. Also the number of grams of each text.
    """
    size = np.diff(offs) + 1
    total = int(size.sum())
    pad = ORDER - 1
    line = np.zeros(total + pad * len(size), np.uint8)
    first = np.cumsum(size + pad) - (size + pad)
    line[B.ranges(first + pad, size - 1)] = np.maximum(raw, 1)
    at = B.ranges(first, size)
    gram = np.zeros(total, np.int64)
    for j in range(ORDER):
        gram = (gram << 8) | line[at + j]
    return gram, size


def shard_of(language: np.ndarray | int, gram: np.ndarray) -> np.ndarray:
    """By language and the two bytes before the last: all that backing off from a gram looks up is in one shard."""
    return (B.mix((gram >> 8 & 0xFFFF).astype(np.uint64) + np.asarray(language, np.int64).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) % np.uint64(N_SHARDS)).astype(np.int64)


def _packed_rows(language: int, gram: np.ndarray, *columns: np.ndarray) -> list[tuple[int, bytes]]:
    shard = shard_of(language, gram)
    order = np.argsort(shard, kind="stable")
    out = []
    for k, s in slices(shard[order], N_SHARDS):
        at = order[s]
        out.append((k, B.pack(np.diff(gram[at], prepend=0), *(c[at] for c in columns))))
    return out


def _languages(piece: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    lang = piece.column("lang").to_numpy(zero_copy_only=False)
    return np.unique(lang), lang


def _count_grams(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for piece in B.chunks(batches, "text", PIECE_BYTES):
        for one in _languages(piece)[0].tolist():
            mine = piece.filter(pa.array(piece.column("lang").to_numpy(zero_copy_only=False) == one))
            gram, _ = byte_grams(*B.text_block(mine.column("text")))
            gram, n = np.unique(gram, return_counts=True)
            rows = _packed_rows(one, gram, n.astype(np.int64))
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([one] * len(rows), pa.int64()), pa.array([r[1] for r in rows], pa.binary())], names=["shard", "lang", "blob"])


def _merge_counts(table: pa.Table) -> pa.Table:
    """One shard and language: gram counts, and the sums that are needed from all shards.

    `kind` 0 rows hold the counts. Kind k in 3..ORDER: number of grams with (adjusted)
    count 1, 2, 3, 4 at order k, in key 1..4. Kind 2: continuation counts of two-byte
    grams (key), as far as this shard sees them.
    """
    shard, lang = table.column("shard")[0].as_py(), table.column("lang")[0].as_py()
    gram, n = [], []
    for blob in table.column("blob").to_pylist():
        g, c = B.unpack(blob)
        gram.append(np.cumsum(g))
        n.append(c)
    gram, back = np.unique(np.concatenate(gram), return_inverse=True)
    n = np.bincount(back, weights=np.concatenate(n)).astype(np.int64)
    kind, key, value = [0], [0], [0]
    level, count = gram, n
    for k in range(ORDER, 2, -1):
        for r in range(1, 5):
            kind.append(k)
            key.append(r)
            value.append(int((count == r).sum()))
        level, count = np.unique(level & ((1 << 8 * (k - 1)) - 1), return_counts=True)
    kind += [2] * len(level)
    key += level.tolist()
    value += count.tolist()
    m = len(kind)
    return pa.table(
        {
            "shard": pa.array([shard] * m, pa.int32()),
            "lang": pa.array([lang] * m, pa.int64()),
            "kind": pa.array(kind, pa.int32()),
            "key": pa.array(key, pa.int64()),
            "value": pa.array(value, pa.int64()),
            "blob": pa.array([B.pack(np.diff(gram, prepend=0), n)] + [None] * (m - 1), pa.binary()),
        }
    )


def modified_discounts(n: Sequence[int]) -> np.ndarray:
    """Discounts for counts 0, 1, 2 and 3 or more from the numbers of grams with count 1..4; 1/2 where these are too thin."""
    n1, n2, n3, n4 = n
    if min(n1, n2, n3) <= 0:
        return np.array([0, 0.5, 0.5, 0.5])
    y = n1 / (n1 + 2 * n2)
    d = np.array([0, 1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3])
    return np.where((d > 0) & (d < np.arange(4)), d, np.array([0, 0.5, 0.5, 0.5]))


class LowOrders:
    """What every shard needs of a language: discounts of all orders, and the one- and two-byte levels (at most 65,536 entries)."""

    def __init__(self, counts_of_counts: dict[int, list[int]], pairs: np.ndarray, pair_counts: np.ndarray):
        self.discount = {k: modified_discounts(counts_of_counts.get(k, [0] * 4)) for k in range(3, ORDER + 1)}
        adjusted = np.zeros((256, 256))
        adjusted[pairs >> 8, pairs & 255] = pair_counts
        ones = (adjusted > 0).sum(axis=0).astype(float)
        self.two = self._level(adjusted, self._level(ones[None], np.full((1, 256), 1 / 256)))

    def packed(self) -> bytes:
        return B.pack(np.concatenate([self.discount[k] for k in range(3, ORDER + 1)]), self.two.astype(np.float32).ravel())

    @classmethod
    def read(cls, blob: bytes) -> LowOrders:
        self = cls.__new__(cls)
        discount, two = B.unpack(blob)
        self.discount = {k: discount[4 * (k - 3) : 4 * (k - 2)] for k in range(3, ORDER + 1)}
        self.two = two.reshape(256, 256).astype(float)
        return self

    @staticmethod
    def _level(adjusted: np.ndarray, lower: np.ndarray) -> np.ndarray:
        """Interpolated probabilities of each row's continuations over the next lower level."""
        whole = adjusted[adjusted > 0]
        d = modified_discounts([int((whole == r).sum()) for r in range(1, 5)])
        cut_ = d[np.minimum(adjusted, 3).astype(np.int64)]
        total = adjusted.sum(axis=1, keepdims=True)
        gamma = np.where(total > 0, cut_.sum(axis=1, keepdims=True) / np.maximum(total, 1), 1.0)
        return np.where(total > 0, np.maximum(adjusted - cut_, 0) / np.maximum(total, 1), 0) + gamma * lower


def shard_scores(gram: np.ndarray, count: np.ndarray, low: LowOrders, asked: np.ndarray) -> np.ndarray:
    """log10 probabilities of asked grams from one shard's counts, from two bytes up."""
    p = low.two[asked >> 8 & 255, asked & 255]
    levels = {}
    level, n = gram, count
    for k in range(ORDER, 2, -1):
        levels[k] = (level, n)
        level, n = np.unique(level & ((1 << 8 * (k - 1)) - 1), return_counts=True)
    for k in range(3, ORDER + 1):
        level, n = levels[k]
        d = low.discount[k]
        taken = d[np.minimum(n, 3)]
        history, at = np.unique(level >> 8, return_inverse=True)
        total = np.bincount(at, weights=n, minlength=len(history))
        gamma = np.bincount(at, weights=taken, minlength=len(history)) / np.maximum(total, 1)
        wanted = asked & ((1 << 8 * k) - 1)
        i, j = np.searchsorted(level, wanted), np.searchsorted(history, wanted >> 8)
        i, j = np.minimum(i, max(0, len(level) - 1)), np.minimum(j, max(0, len(history) - 1))
        known = history[j] == wanted >> 8 if len(history) else np.zeros(len(wanted), bool)
        seen = level[i] == wanted if len(level) else known
        direct = np.where(seen, (n[i] - taken[i]), 0) / total[j] if len(history) else 0
        p = np.where(known, direct + (gamma[j] if len(history) else 0) * p, p)
    return np.log10(p)


def _shrink(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for piece in B.chunks(batches, "text", PIECE_BYTES):
        raw, offs = B.text_block(piece.column("text"))
        z = [B.pack(raw[a:b]) for a, b in zip(offs[:-1].tolist(), offs[1:].tolist(), strict=True)]
        yield pa.RecordBatch.from_arrays([piece.column("id"), pa.array(z, pa.binary()), piece.column("lang"), piece.column("g"), piece.column("carried")], names=["id", "z", "lang", "g", "carried"])


def _expanded(table: pa.Table) -> pa.Table:
    """A group with its texts again; its size is bounded by GROUP_BYTES on average."""
    texts = [B.unpack(z)[0] for z in table.column("z").to_pylist()]
    offs = np.concatenate(([0], np.cumsum([len(t) for t in texts], dtype=np.int64)))
    raw = np.concatenate(texts) if texts else np.zeros(0, np.uint8)
    return table.drop_columns(["z"]).append_column("text", B.strings(raw, offs))


def _ask_grams(table: pa.Table) -> pa.Table:
    """A group's distinct grams, to their shards."""
    B.release()
    out = []
    if table.num_rows:
        g = table.column("g")[0].as_py()
        for one, gram in _group_grams(_expanded(table)):
            out += [(k, one, g, blob) for k, blob in _packed_rows(one, gram)]
    shard, lang, g, blob = zip(*out, strict=True) if out else ((), (), (), ())
    return pa.table({"shard": pa.array(shard, pa.int32()), "lang": pa.array(lang, pa.int64()), "g": pa.array(g, pa.int32()), "blob": pa.array(blob, pa.binary())})


def _group_grams(table: pa.Table) -> Iterator[tuple[int, np.ndarray]]:
    """Each language of a group and its distinct grams."""
    found: dict[int, np.ndarray] = {}
    for piece in B.chunks(table.combine_chunks().to_batches(), "text", PIECE_BYTES):
        for one in _languages(piece)[0].tolist():
            mine = piece.filter(pa.array(piece.column("lang").to_numpy(zero_copy_only=False) == one))
            gram = np.unique(byte_grams(*B.text_block(mine.column("text")))[0])
            found[one] = np.union1d(found[one], gram) if one in found else gram
    yield from sorted(found.items())


def _answer(model: pa.Table, asked: pa.Table) -> pa.Table:
    """Join of one shard's counts with all groups that ask this copy of it."""
    B.release()
    counts = {}
    none = np.zeros(0, np.int64)
    for one, b, low in zip(*(model.column(c).to_pylist() for c in ("lang", "blob", "low")), strict=True):
        gram, n = B.unpack(b) if b is not None else (none, none)
        counts[one] = np.cumsum(gram), n, LowOrders.read(low)
    blob = [B.pack(shard_scores(*counts[one], np.cumsum(B.unpack(b)[0])).astype(np.float32)) if one in counts else None for one, b in zip(asked.column("lang").to_pylist(), asked.column("blob").to_pylist(), strict=True)]
    return pa.table({"g": asked.column("g"), "lang": asked.column("lang"), "shard": asked.column("shard"), "blob": pa.array(blob, pa.binary())})


def _score(docs: pa.Table, answers: pa.Table) -> pa.Table:
    """log10 probability of each text of a group; null where its language has no model."""
    B.release()
    told: dict[int, dict[int, bytes]] = {}
    for one, k, b in zip(*(answers.column(c).to_pylist() for c in ("lang", "shard", "blob")), strict=True):
        told.setdefault(one, {})[k] = b
    tables: dict[int, tuple[np.ndarray, np.ndarray] | None] = {}
    docs = _expanded(docs)
    for one, gram in _group_grams(docs) if docs.num_rows else ():
        got = told.get(one, {})
        if any(b is None for b in got.values()) or not got:
            tables[one] = None
            continue
        shard = shard_of(one, gram)
        value = np.empty(len(gram), np.float32)
        order = np.argsort(shard, kind="stable")
        for k, s in slices(shard[order], N_SHARDS):
            value[order[s]] = B.unpack(got[k])[0]
        tables[one] = gram, value
    out = []
    for piece in B.chunks(docs.combine_chunks().to_batches(), "text", PIECE_BYTES):
        lang = _languages(piece)[1]
        total, known = np.zeros(piece.num_rows), np.zeros(piece.num_rows, bool)
        size = np.zeros(piece.num_rows, np.int64)
        for one in np.unique(lang).tolist():
            rows = np.flatnonzero(lang == one)
            gram, n = byte_grams(*B.text_block(piece.column("text").take(pa.array(rows))))
            size[rows] = n
            if tables[one] is not None:
                at = np.searchsorted(tables[one][0], gram)
                total[rows] = np.add.reduceat(tables[one][1][at].astype(np.float64), np.cumsum(n) - n)
                known[rows] = True
        out.append(pa.table({"id": piece.column("id"), "n_tokens": pa.array(size), "score": pa.array(total, mask=~known), "carried": piece.column("carried")}))
    if not out:
        return pa.table({"id": pa.array([], pa.int64()), "n_tokens": pa.array([], pa.int64()), "score": pa.array([], pa.float64()), "carried": pa.array([], docs.schema.field("carried").type)})
    return pa.concat_tables(out)


def score_texts(rows: DataFrame, trusted: DataFrame) -> DataFrame:
    """For rows of id, text, lang (a 64-bit name) and carried: id, n_tokens, score (log10 probability), carried.

    The score is null if the language has no trusted text (`trusted`: text, lang). The
    count table of the model is spread over shards; groups of documents send each shard
    their distinct grams, which meet the shard's counts there and are answered in the
    same order.
    """
    counted = trusted.mapInArrow(_count_grams, "shard int, lang long, blob binary").groupBy("shard", "lang").applyInArrow(_merge_counts, "shard int, lang long, kind int, key long, value long, blob binary")
    model = cut(counted)
    # The low orders of each language, at most 65,536 numbers, beside each of its shards.
    sums = model.where("kind > 0").groupBy("lang", "kind", "key").agg(F.sum("value").alias("value"))
    low = sums.groupBy("lang").applyInArrow(_low_orders, "lang long, low binary").withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(N_SHARDS - 1))))
    size = text_bytes(rows, "text")
    n_salts = math.ceil(size / SALT_BYTES) or 1
    shards = low.join(model.where("kind = 0").select("shard", "lang", "blob"), ["shard", "lang"], "left").withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(n_salts - 1))))
    n_groups = parts_for(rows.sparkSession, size, GROUP_BYTES)
    # Texts are compressed before they are dealt to groups.
    plain = rows.select("id", "text", "lang", "carried", _group(n_groups).alias("g"))
    kinds = T.StructType([T.StructField("id", T.LongType()), T.StructField("z", T.BinaryType()), T.StructField("lang", T.LongType()), T.StructField("g", T.IntegerType()), T.StructField("carried", rows.schema["carried"].dataType)])
    grouped = plain.mapInArrow(_shrink, kinds)
    asked = grouped.groupBy("g").applyInArrow(_ask_grams, "shard int, lang long, g int, blob binary")
    asked = asked.withColumn("salt", F.pmod("g", F.lit(n_salts)))
    told = shards.select("shard", "salt", "lang", "blob", "low").groupBy("shard", "salt").cogroup(asked.groupBy("shard", "salt")).applyInArrow(_answer, "g int, lang long, shard int, blob binary")
    out = T.StructType([T.StructField("id", T.LongType()), T.StructField("n_tokens", T.LongType()), T.StructField("score", T.DoubleType()), T.StructField("carried", rows.schema["carried"].dataType)])
    return grouped.groupBy("g").cogroup(told.groupBy("g")).applyInArrow(_score, out)


def _low_orders(sums: pa.Table) -> pa.Table:
    """The low orders of one language."""
    kind, key, value = (sums.column(c).to_numpy() for c in ("kind", "key", "value"))
    counts = {k: [0] * 4 for k in range(3, ORDER + 1)}
    for i in np.flatnonzero(kind > 2).tolist():
        counts[int(kind[i])][int(key[i]) - 1] = int(value[i])
    pairs = kind == 2
    return pa.table({"lang": sums.column("lang").slice(0, 1), "low": pa.array([LowOrders(counts, key[pairs], value[pairs]).packed()], pa.binary())})


def classify(
    docs: DataFrame,
    labels: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    lang_col: str = "lang",
    quantile: float = 0.999,
    slack: float = 0.02,
    max_training_texts: int = MAX_TRAINING_TEXTS,
) -> DataFrame:
    """Judge every text by its perplexity under a model of trusted text of its language.

    `labels` (doc_id, quality, toxic) names trusted documents: quality 1 and not toxic.
    Half of them, by a hash of the id, train the model (at most `max_training_texts` a
    language, those with the least hashes); the other half set the thresholds, the
    given quantile of the log perplexity of those of about the same length, plus
    `slack`: rates of short texts vary more, and are allowed to. There is no lower
    threshold, as trained texts and their copies have low perplexity too.

    Returns id, version (the xxhash64 of the text), lang, n_tokens (bytes and one end),
    score (log10 probability), perplexity, rate (-log10 a token), threshold and
    kept. Empty texts are kept. Languages without trusted text have no threshold and keep
    all. Models are rows of tables by language and shard, however many languages there are.

    Null texts are empty, a null language is a language of its own; null or repeated
    ids and repeated rows are judged row by row; empty tables are fine.
    """
    trusted = labels.where((F.col("quality") == 1) & (F.coalesce(F.col("toxic"), F.lit(0)) == 0)).select(F.col("doc_id").cast("long").alias("id")).distinct()
    name = F.xxhash64(F.coalesce(F.col(lang_col).cast("string"), F.lit("")))
    text = F.col(text_col).cast("string")
    rows = docs.select(F.col(id_col).cast("long").alias("id"), text.alias("text"), name.alias("lang"), F.struct(name.alias("name"), F.col(lang_col).alias("lang"), F.xxhash64(text).alias("version")).alias("carried"))
    half = F.pmod(F.xxhash64("id", F.lit(11)), F.lit(2))
    # The bound on the sample: a share of each language by hash, and so spread over all data.
    candidates = rows.select("id", "lang").join(trusted.where(half == 0), "id")
    share = candidates.groupBy("lang").agg(F.least(F.lit(1.0), F.lit(float(max_training_texts)) / F.count(F.lit(1))).alias("share"))
    mark = F.pmod(F.xxhash64("id", F.lit(13)), F.lit(1 << 20))
    chosen = cut(candidates.join(share, "lang").where(mark < F.ceil(F.col("share") * (1 << 20))).select("id").distinct())
    sample = rows.where(half == 0).select("id", "text", "lang").join(chosen, "id").select("text", "lang")
    scored = cut(score_texts(rows, sample).select("id", "n_tokens", "score", "carried.*"))
    rate = -F.col("score") / F.col("n_tokens")
    judged = scored.withColumn("rate", rate).withColumn("octave", _octave(F.col("n_tokens")))
    limits = _thresholds(judged.join(trusted.where(half == 1), "id").where("score is not null"), quantile, slack)
    told = judged.join(limits, ["name", "octave"], "left")
    perplexity = F.pow(F.lit(10.0), rate)
    kept = F.coalesce((F.col("rate") <= F.col("threshold")) | (F.col("n_tokens") <= 1), F.lit(True))
    return told.select("id", "version", "lang", "n_tokens", "score", perplexity.alias("perplexity"), "rate", "threshold", kept.alias("kept"))


def _octave(n_tokens: Column) -> Column:
    return F.floor(F.log2(n_tokens)).cast("int")


def _thresholds(calibration: DataFrame, quantile: float, slack: float) -> DataFrame:
    """name, octave, threshold: for every length of every language of `calibration` (name, octave, rate), 64 rows a language."""
    near = [F.struct(F.lit(w).alias("w"), (F.col("octave") + k).alias("o")) for w in WIDTHS for k in range(-w, w + 1)]
    spread = calibration.select("name", "rate", F.explode(F.array(*near, F.struct(F.lit(WHOLE).alias("w"), F.lit(0).alias("o")))).alias("x")).select("name", "rate", "x.*")
    found = spread.groupBy("name", "w", "o").agg(F.count(F.lit(1)).alias("n"), F.percentile_approx("rate", quantile, 100000).alias("t"))
    # All of a language serves every length; the narrowest of the others goes before it.
    lengths = F.when(F.col("w") == WHOLE, F.sequence(F.lit(0), F.lit(63))).otherwise(F.array("o"))
    usable = found.where((F.col("w") == WHOLE) | (F.col("n") >= MIN_CALIBRATION)).select("name", "w", "t", F.explode(lengths).alias("octave"))
    return cut(usable.groupBy("name", "octave").agg((F.min_by("t", "w") + slack).alias("threshold")))


def op3_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = classify(load(spark, sf_dir, "documents"), load(spark, sf_dir, "labels"))
    return got.select(F.col("id").alias("doc_id"), "lang", "n_tokens", F.round("score", 3).alias("score"), F.round("perplexity", 4).alias("perplexity"), F.round("rate", 4).alias("rate"), F.round("threshold", 4).alias("threshold"), "kept")
