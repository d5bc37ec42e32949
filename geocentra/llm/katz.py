"""Katz backoff language model: Good-Turing discounted bigrams with exactly normalised backoff weights.

Texts are turned once into numbered groups: a local vocabulary and token numbers. A
group asks count tables, which are partitioned by hash, for what it cannot know alone,
one record for each distinct word or bigram it holds, and is answered in the same
order. So a word or bigram that is everywhere costs one record a group.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from geocentra.llm import blocks as B
from geocentra.llm.exchange import ask, asked_of, requests, slices
from geocentra.llm.plan import cut, cut_by, load, parts_for, small_batches, text_bytes

PIECE_BYTES = 6 << 20
BUCKET_BYTES = 24 << 20
#: Good-Turing discounts counts up to this one; larger counts are trusted.
TRUSTED = 5

# Stand-ins for the hashes of the end of a text and of its beginning.
END, BEGIN = np.uint64(1), np.uint64(2)


def _tokenise(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Groups of texts: their words' hashes, and by text the words' places among these, in order of frequency."""
    task, k = TaskContext.get().partitionId(), 0
    for pieces in B.gathered(batches, "text", PIECE_BYTES):
        B.release()
        parts = []
        for small in B.chunks(pieces, "text", 1 << 20):
            raw, offs = B.text_block(small.column("text"))
            raw = B.LOWER[raw]
            starts, ends, by_text = B.words(raw, offs, B.NON_SPACE)
            parts.append((B.word_hashes(raw, starts, ends), np.diff(by_text)))
        h, size = (np.concatenate(x) for x in zip(*parts, strict=True))
        # An end after each text.
        tokens = np.full(len(h) + len(size), END, np.uint64)
        inside = np.ones(len(tokens), bool)
        inside[np.cumsum(size + 1) - 1] = False
        tokens[inside] = h
        vocabulary, code, times = np.unique(tokens, return_inverse=True, return_counts=True)
        order = np.argsort(-times, kind="stable")
        rank = np.empty(len(order), np.uint32)
        rank[order] = np.arange(len(order), dtype=np.uint32)
        code = rank[code].view(np.uint8).reshape(-1, 4)
        blob = B.pack(size.astype(np.int32), np.concatenate([x.column("held").to_numpy(zero_copy_only=False) for x in pieces]).astype(np.uint8), B.low_bytes(vocabulary[order]), *(np.ascontiguousarray(code[:, i]) for i in range(4)))
        ids = [i for x in pieces for i in x.column("id").to_pylist()]
        yield pa.RecordBatch.from_arrays([pa.array([(task << 24) + k], pa.int64()), pa.array([blob], pa.binary()), pa.array([ids], pa.list_(pa.int64()))], names=["g", "blob", "ids"])
        k += 1


def narrow(n: np.ndarray) -> np.ndarray:
    """Counts in 32 bits where all of them fit, else in 64."""
    return n.astype(np.int32 if not len(n) or n.max() <= np.iinfo(np.int32).max else np.int64)


class Group:
    """A group's tokens. `word` numbers them in the ascending vocabulary; `before` is the previous word, -1 at a beginning."""

    def __init__(self, blob: bytes):
        size, held, vocabulary, *planes = B.unpack(blob)
        self.size, self.held = size.astype(np.int64) + 1, held.astype(bool)
        h = B.mix(B.from_bytes(vocabulary))  # 56 bits, spread over 64 again
        order = np.argsort(h)
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        self.vocabulary = h[order]
        self.word = place[np.stack(planes, axis=1).view(np.uint32).ravel()]
        self.first = np.cumsum(self.size) - self.size
        self.before = np.empty_like(self.word)
        self.before[1:] = self.word[:-1]
        self.before[self.first] = -1
        self.train = np.repeat(~self.held, self.size)

    def bigrams(self) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Of the distinct bigrams in order of their hash: hash, previous word, word, training count; and each token's bigram."""
        v = len(self.vocabulary) + 1
        code = (self.before + 1) * v + self.word
        low = np.uint64((1 << max(1, int(len(code) - 1).bit_length())) - 1)
        if v * v < (1 << 63) // (int(low) + 1):
            key = code.astype(np.uint64) * (low + np.uint64(1)) + np.arange(len(code), dtype=np.uint64)
            key.sort()
            order = (key & low).astype(np.int64)
        else:
            order = np.argsort(code, kind="stable")
        new = np.ones(len(code), bool)
        new[1:] = code[order[1:]] != code[order[:-1]]
        number = np.cumsum(new) - 1
        at = order[new]
        before, word = self.before[at], self.word[at]
        known = np.concatenate(([BEGIN], self.vocabulary))
        h = B.mix(known[before + 1] * np.uint64(0x9E3779B97F4A7C15) + B.mix(self.vocabulary[word]))
        by_hash = np.argsort(h)
        place = np.empty(len(by_hash), np.int64)
        place[by_hash] = np.arange(len(by_hash))
        mine = np.empty(len(code), np.int64)
        mine[order] = place[number]
        return h[by_hash], before[by_hash], word[by_hash], np.bincount(mine[self.train], minlength=len(h)), mine


def _ask_counts(order: int, n_buckets: int):
    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for g, blob in zip(batch.column("g").to_pylist(), batch.column("blob").to_pylist(), strict=True):
                B.release()
                group = Group(blob)
                if order == 1:
                    h, n = group.vocabulary, np.bincount(group.word[group.train], minlength=len(group.vocabulary))
                else:
                    h, _, _, n, _ = group.bigrams()
                yield requests(ask(h, n_buckets, g, narrow(n)))

    return run


def _count(order: int):
    """One bucket of a count table: totals for those who asked, and how many have each count.

    Of bigrams only those that several groups hold are answered, by place: the total,
    and to one group that holds it in training, that it is the owner.
    Statistics are rows of g = -1: n is how many (bucket 1..TRUSTED+1: have that
    count; -1: tokens; -2: distinct).
    """

    def run(table: pa.Table) -> pa.Table:
        asked = [asked_of(b) for b in table.column("blob").to_pylist()]
        B.release()
        groups = table.column("g").to_numpy()
        bucket = table.column("bucket")[0].as_py()
        h = np.concatenate([a[0] for a in asked])
        n = np.concatenate([a[1][0] for a in asked]).astype(np.int64)
        who = np.repeat(np.arange(len(asked)), [len(a[0]) for a in asked])
        where = np.concatenate([np.arange(len(a[0])) for a in asked])
        order_ = np.argsort(h)
        new = np.ones(len(h), bool)
        new[1:] = h[order_[1:]] != h[order_[:-1]]
        number = np.empty(len(h), np.int64)
        number[order_] = np.cumsum(new) - 1
        total = np.add.reduceat(n[order_], np.flatnonzero(new))
        g, b, blob, count = [], [], [], []
        if order == 1:
            edges = np.concatenate(([0], np.cumsum([len(a[0]) for a in asked])))
            for i in range(len(asked)):
                g.append(int(groups[i]))
                b.append(bucket)
                blob.append(B.pack(narrow(total[number[edges[i] : edges[i + 1]]])))
                count.append(None)
        else:
            shared = np.flatnonzero(np.bincount(number)[number] > 1)
            # The owner: the first in training, by group.
            rank = np.lexsort((groups[who[shared]], n[shared] == 0, number[shared]))
            shared = shared[rank]
            owner = np.ones(len(shared), bool)
            owner[1:] = number[shared[1:]] != number[shared[:-1]]
            back = np.lexsort((where[shared], who[shared]))
            shared, owner = shared[back], owner[back]
            for i, s in slices(who[shared], len(asked)):
                at = where[shared[s]]
                g.append(int(groups[i]))
                b.append(bucket)
                blob.append(B.pack(B.gaps(at, np.array([len(at)])), narrow(total[number[shared[s]]]), owner[s].astype(np.uint8)))
                count.append(None)
        often = np.bincount(np.minimum(total[total > 0], TRUSTED + 2), minlength=TRUSTED + 3)
        stats = {r: int(often[r]) for r in range(1, TRUSTED + 2)} | {-1: int(total.sum()), -2: int((total > 0).sum())}
        g += [-1] * len(stats)
        b += list(stats)
        blob += [None] * len(stats)
        count += list(stats.values())
        return pa.table({"g": pa.array(g, pa.int64()), "bucket": pa.array(b, pa.int32()), "blob": pa.array(blob, pa.binary()), "n": pa.array(count, pa.int64())})

    return run


def discounts(n: dict[int, int]) -> np.ndarray:
    """Katz's Good-Turing discount factor for counts 0..TRUSTED+1 (the last stands for all larger ones).

    Where the counts of counts are too thin for a factor in (0, 1), as in tiny tables,
    it is (r - 1/2) / r.
    """
    out = np.ones(TRUSTED + 2)
    n1 = n.get(1, 0)
    cut_off = (TRUSTED + 1) * n.get(TRUSTED + 1, 0) / n1 if n1 else 1.0
    for r in range(1, TRUSTED + 1):
        d = np.nan
        if n.get(r, 0) and n.get(r + 1, 0) and cut_off < 1:
            d = ((r + 1) * n[r + 1] / (r * n[r]) - cut_off) / (1 - cut_off)
        out[r] = d if 0 < d < 1 else (r - 0.5) / r
    return out


class Model:
    """Numbers that hold for the whole corpus."""

    def __init__(self, words: dict[int, int], bigrams: dict[int, int], n_texts: int):
        self.tokens, self.distinct, self.n_texts = words.get(-1, 0), words.get(-2, 0), n_texts
        self.d1, self.d2 = discounts(words), discounts(bigrams)
        # What discounting the words leaves is the probability of any unknown word.
        taken = sum((1 - self.d1[r]) * r * words.get(r, 0) for r in range(1, TRUSTED + 1)) / max(1, self.tokens)
        least = 1 / (self.tokens + self.distinct + 1)
        self.unknown = max(taken, least)
        self.scale = (1 - self.unknown) / (1 - taken) if taken < 1 else 1.0

    def word_probability(self, count: np.ndarray) -> np.ndarray:
        d = self.d1[np.minimum(count, TRUSTED + 1)]
        return np.where(count > 0, self.scale * d * count / max(1, self.tokens), self.unknown)


class Answers:
    """A group's answers in the order of what it asked."""

    def __init__(self, table: pa.Table, n_buckets: int):
        self.by_kind: dict[int, dict[int, list[np.ndarray]]] = {}
        for kind, bucket, blob in zip(*(table.column(c).to_pylist() for c in ("kind", "bucket", "blob")), strict=True):
            self.by_kind.setdefault(kind, {})[bucket] = B.unpack(blob)
        self.n_buckets = n_buckets

    def aligned(self, kind: int, n: int, dtype) -> np.ndarray:
        got = self.by_kind.get(kind, {})
        out = [got[k][0] for k in sorted(got)]
        return np.concatenate(out).astype(dtype) if out else np.zeros(n, dtype)

    def placed(self, kind: int, h: np.ndarray, total: np.ndarray, owned: np.ndarray) -> None:
        edges = dict(slices(B.bucket_of(h, self.n_buckets), self.n_buckets))
        for k, (gap, count, owner) in self.by_kind.get(kind, {}).items():
            at = edges[k].start + np.cumsum(gap.astype(np.int64))
            total[at] = count
            owned[at] &= owner.astype(bool)


def _histories(group: Group, c: np.ndarray, model: Model) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hashes of the words that can stand before another (ascending; the beginning is last), their counts, and an order."""
    h = np.concatenate((group.vocabulary, [BEGIN]))
    count = np.concatenate((c, [model.n_texts]))
    count[:-1][group.vocabulary == B.mix(np.array([END]))] = 0
    h = B.mix(h)
    return h, count, np.argsort(h)


def _ask_weights(n_buckets: int, model: Model):
    """For each history: the mass its owned bigrams keep after discounting, and their words' probability."""

    def run(groups: pa.Table, answers: pa.Table) -> pa.Table:
        out = []
        B.release()
        if groups.num_rows:
            g = groups.column("g")[0].as_py()
            group, got = Group(groups.column("blob")[0].as_py()), Answers(answers, n_buckets)
            c = got.aligned(1, len(group.vocabulary), np.int64)
            h, before, word, n, _ = group.bigrams()
            total, owned = n.copy(), np.ones(len(h), bool)
            got.placed(2, h, total, owned)
            use = owned & (total > 0)
            total, slot, word = total[use], before[use], word[use]
            slot = np.where(slot < 0, len(group.vocabulary), slot)
            hist, count, order = _histories(group, c, model)
            kept = np.bincount(slot, weights=model.d2[np.minimum(total, TRUSTED + 1)] * total, minlength=len(hist))
            mass = np.bincount(slot, weights=model.word_probability(c[word]), minlength=len(hist))
            out = ask(hist[order], n_buckets, g, narrow(count[order]), kept[order], mass[order])
        return pa.Table.from_batches([requests(out)])

    return run


def _weigh(table: pa.Table) -> pa.Table:
    """Exactly normalised backoff weights, in the order asked.

    A history all of whose bigrams are trusted would keep no mass for others; it
    gives 1 of count + 1, and its weight is negative to say so.
    """
    asked = [asked_of(b) for b in table.column("blob").to_pylist()]
    h = np.concatenate([a[0] for a in asked])
    count, kept, mass = (np.concatenate([a[1][i] for a in asked]) for i in range(3))
    count = count.astype(np.int64)
    _, number = np.unique(h, return_inverse=True)
    kept, mass = np.bincount(number, weights=kept), np.bincount(number, weights=mass)
    left = 1 - kept[number] / np.maximum(count, 1)
    full = (left < 1e-9) & (count > 0)
    rest = np.maximum(1 - mass[number], 1e-300)
    weight = np.where(count > 0, np.where(full, -1 / (count + 1.0), left) / rest, 1.0)
    edges = np.concatenate(([0], np.cumsum([len(a[0]) for a in asked])))
    return pa.table(
        {
            "g": table.column("g").combine_chunks() if table.num_rows else pa.array([], pa.int64()),
            "bucket": table.column("bucket").combine_chunks() if table.num_rows else pa.array([], pa.int32()),
            "blob": pa.array([B.pack(weight[edges[i] : edges[i + 1]]) for i in range(len(asked))], pa.binary()),
        }
    )


def _score(n_buckets: int, model: Model):
    names = ["id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"]
    kinds = [pa.int64(), pa.bool_(), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.float64()]

    def run(groups: pa.Table, answers: pa.Table) -> pa.Table:
        B.release()
        if not groups.num_rows:
            return pa.table({n: pa.array([], k) for n, k in zip(names, kinds, strict=True)})
        group, got = Group(groups.column("blob")[0].as_py()), Answers(answers, n_buckets)
        c = got.aligned(1, len(group.vocabulary), np.int64)
        h, _, _, n, mine = group.bigrams()
        total, owned = n.copy(), np.ones(len(h), bool)
        got.placed(2, h, total, owned)
        hist, count, order = _histories(group, c, model)
        weight = np.empty(len(hist))
        weight[order] = got.aligned(3, len(hist), np.float64)
        slot = np.where(group.before < 0, len(group.vocabulary), group.before)
        seen, a, m = total[mine], weight[slot], count[slot]
        direct = model.d2[np.minimum(seen, TRUSTED + 1)] * seen / np.maximum(m, 1) * np.where(a < 0, m / (m + 1.0), 1.0)
        lower = model.word_probability(c)[group.word]
        p = np.where(seen > 0, direct, np.where(m > 0, np.abs(a), 1.0) * lower)
        base = np.log10((c[group.word] + 1) / (model.tokens + model.distinct + 1))
        got_columns = [
            groups.column("ids").combine_chunks().flatten(),
            group.held,
            group.size,
            np.add.reduceat((c[group.word] > 0).astype(np.int64), group.first),
            np.full(len(group.size), model.tokens),
            np.add.reduceat(base, group.first),
            np.add.reduceat(np.log10(p), group.first),
        ]
        return pa.table({n: pa.array(x, k) for n, k, x in zip(names, kinds, got_columns, strict=True)})

    return run


def katz_scores(docs: DataFrame, held_out: Column, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """log10 probabilities of all texts under a bigram model learnt from those not held out.

    Returns id, held_out, n_tokens, n_known (tokens known from training), train_tokens,
    base_score (add-one unigrams) and score. Tokens are the words of the text, A-Z
    folded, and one end; unknown words are one event, whose probability is what
    Good-Turing discounting leaves. The probabilities that follow any word sum to 1.

    Null and empty texts are an end alone. A null `held_out` counts as training. Null
    or repeated ids and repeated rows are scored, and counted, row by row. If nothing
    is left for training every word is unknown. An empty table gives no rows.
    """
    spark = docs.sparkSession
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(held_out, F.lit(False)).alias("held"), text.alias("text"))
    n_buckets = parts_for(spark, text_bytes(rows, "text"), BUCKET_BYTES)
    with small_batches(spark):
        groups = cut_by(rows.mapInArrow(_tokenise, "g long, blob binary, ids array<long>"), n_buckets, "g")
    n_texts = rows.where(~F.col("held")).count()
    answers, stats = [], []
    for order in (1, 2):
        asked = groups.select("g", "blob").mapInArrow(_ask_counts(order, n_buckets), "bucket int, g long, blob binary")
        told = cut(asked.groupBy("bucket").applyInArrow(_count(order), "g long, bucket int, blob binary, n long"))
        stats.append({r["bucket"]: r["n"] for r in told.where("g = -1").groupBy("bucket").agg(F.sum("n").alias("n")).collect()})
        answers.append(told.where("g <> -1").select("g", F.lit(order).alias("kind"), "bucket", "blob"))
    model = Model(stats[0], stats[1], n_texts)
    known = answers[0].unionByName(answers[1])
    weighed = groups.select("g", "blob").groupBy("g").cogroup(known.groupBy("g")).applyInArrow(_ask_weights(n_buckets, model), "bucket int, g long, blob binary")
    weights = weighed.groupBy("bucket").applyInArrow(_weigh, "g long, bucket int, blob binary").select("g", F.lit(3).alias("kind"), "bucket", "blob")
    return groups.groupBy("g").cogroup(known.unionByName(weights).groupBy("g")).applyInArrow(
        _score(n_buckets, model), "id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    )


def op4_katz_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    held_out = F.crc32(F.col("doc_id").cast("string")) % 7 == 2
    return katz_scores(load(spark, sf_dir, "documents"), held_out).withColumnRenamed("id", "doc_id")
