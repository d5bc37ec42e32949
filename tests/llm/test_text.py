import hashlib
import math
import re
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from geocentra.llm import chat, decontaminate, katz, kneser_ney, packing

WORD = re.compile(r"[^\x20\x09-\x0D]+")
ALNUM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def fold(s):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in s)


# --- decontamination -----------------------------------------------------------------------


def brute_leaks(rows, items, width):
    windows = defaultdict(set)
    for i, t in items:
        w = ALNUM.findall(fold(t or ""))
        if i is not None and w:
            for k in range(max(1, len(w) - width + 1)):
                windows[tuple(w[k : k + width])].add(i)
    out = []
    for i, t, *_ in rows:
        w = ALNUM.findall(fold(t or ""))
        hit, found = set(), set()
        for n in {len(x) for x in windows}:
            for k in range(len(w) - n + 1):
                if (x := tuple(w[k : k + n])) in windows:
                    hit.update(range(k, k + n))
                    found |= windows[x]
        out.append((i, len(w), len(hit), tuple(sorted(found))))
    return sorted(out, key=str)


@pytest.mark.parametrize("block", [8 << 20, 200])
def test_leaks(spark, odd, rows, block, monkeypatch):
    monkeypatch.setattr(decontaminate, "BLOCK_BYTES", block)
    texts = [r[1] for r in rows if r[1] and len(r[1].split()) > 30][:4]
    items = [(k, " ".join(t.split()[3:25]).upper()) for k, t in enumerate(texts)] + [(10, "two words"), (11, "one"), (12, ""), (13, None), (None, "a b c")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = decontaminate.decontaminate(odd, bench, clean_text=True, carry=["blob"]).collect()
    want = brute_leaks([(r["doc_id"], r["text"]) for r in odd.collect()], items, 10)
    assert sorted(((r["id"], r["n_words"], r["n_hit"], tuple(sorted(r["items"]))) for r in got), key=str) == want
    for r in got:
        assert len(ALNUM.findall(fold(r["clean_text"]))) == r["n_words"] - r["n_hit"]
        assert sum(s["end"] - s["start"] for s in r["spans"]) == r["n_hit"]


def test_leaks_of_nothing(spark, docs, empty):
    none = spark.createDataFrame([], "item_id long, text string")
    assert decontaminate.decontaminate(docs, none).agg(F.sum("n_hit")).first()[0] == 0
    assert decontaminate.decontaminate(empty, none).count() == 0


# --- language models -----------------------------------------------------------------------


def test_katz_equals_brute_force(odd, monkeypatch):
    monkeypatch.setattr(katz, "PIECE_BYTES", 3000)
    got = katz.katz_scores(odd, F.crc32(F.col("doc_id").cast("string")) % 7 == 2).collect()
    assert len(got) == odd.count()
    texts = [(r["doc_id"], WORD.findall(fold(r["text"] or "")) + ["</e>"], r["h"] or False) for r in odd.select("doc_id", "text", (F.crc32(F.col("doc_id").cast("string")) % 7 == 2).alias("h")).collect()]
    one, two, n_texts = Counter(), Counter(), 0
    for _, w, held in texts:
        if not held:
            one.update(w)
            two.update(zip(["<b>", *w], w, strict=False))
            n_texts += 1
    n, v = sum(one.values()), len(one)
    d2 = katz.discounts(Counter(two.values()))
    model = katz.Model(Counter(one.values()) | {-1: n, -2: v}, Counter(two.values()), n_texts)
    p1 = lambda w: float(model.word_probability(np.array([one.get(w, 0)]))[0])
    assert math.isclose(sum(map(p1, one)) + model.unknown, 1)
    before = {**one, "<b>": n_texts}
    before.pop("</e>")
    kept, mass = defaultdict(float), defaultdict(float)
    for (a, b), k in two.items():
        kept[a] += d2[min(k, 6)] * k
        mass[a] += p1(b)

    def p2(a, b):
        c, k = before.get(a, 0), two.get((a, b), 0)
        if not c:
            return p1(b)
        full = 1 - kept[a] / c < 1e-9
        if k:
            return d2[min(k, 6)] * k / c * (c / (c + 1) if full else 1)
        return (1 / (c + 1) if full else 1 - kept[a] / c) / (1 - mass[a]) * p1(b)

    for a in list(before)[:20]:  # probabilities after a word sum to 1
        assert math.isclose(sum(p2(a, b) for b in one) + p2(a, "no such word"), 1, rel_tol=1e-9)
    want = sorted((str(i), len(w), sum(x in one for x in w), round(sum(math.log10((one[x] + 1) / (n + v + 1)) for x in w), 6), round(sum(math.log10(p2(a, b)) for a, b in zip(["<b>", *w], w, strict=False)), 6)) for i, w, _ in texts)
    found = sorted((str(r["id"]), r["n_tokens"], r["n_known"], round(r["base_score"], 6), round(r["score"], 6)) for r in got)
    assert [x[:3] for x in found] == [w[:3] for w in want]
    assert all(abs(a - b) < 1e-5 for x, w in zip(found, want, strict=True) for a, b in zip(x[3:], w[3:], strict=True))


def test_katz_without_training(docs, empty):
    got = katz.katz_scores(docs, F.lit(True)).collect()
    assert all(r["n_known"] == 0 and r["train_tokens"] == 0 and math.isfinite(r["score"]) for r in got)
    assert katz.katz_scores(empty, F.lit(False)).count() == 0


def brute_kneser_ney(texts, order, asked):
    """Interpolated modified Kneser-Ney over bytes, from dictionaries."""
    grams = Counter()
    for t in texts:
        line = bytes(order - 1) + bytes(max(1, b) for b in t.encode()) + b"\0"
        grams.update(line[k : k + order] for k in range(len(line) - order + 1))
    levels = {order: grams}
    for k in range(order - 1, 0, -1):
        levels[k] = Counter(g[1:] for g in levels[k + 1])

    def p(g):
        if not g:
            return 1 / 256
        k = len(g)
        level = levels[k]
        d = kneser_ney.modified_discounts([sum(c == r for c in level.values()) for r in range(1, 5)])
        mine = {x: c for x, c in level.items() if x[:-1] == g[:-1]}
        if not mine:
            return p(g[1:])
        total = sum(mine.values())
        c = mine.get(g, 0)
        return (max(c - d[min(c, 3)], 0) if c else 0) / total + sum(d[min(x, 3)] for x in mine.values()) / total * p(g[1:])

    return [math.log10(p(g)) for g in asked]


def test_kneser_ney_shards_equal_brute_force():
    texts = ["the cat sat on the mat", "the dog sat", "a cat and a dog", "é the end"]
    raw = np.frombuffer("".join(texts).encode(), np.uint8)
    offs = np.concatenate(([0], np.cumsum([len(t.encode()) for t in texts])))
    gram, _ = kneser_ney.byte_grams(raw, offs)
    level, n = np.unique(gram, return_counts=True)
    asked = np.unique(np.concatenate((level, kneser_ney.byte_grams(np.frombuffer(b"the cow sat on a log", np.uint8), np.array([0, 20]))[0])))
    counts, lower, adjusted = {}, level, n
    for k in range(kneser_ney.ORDER, 2, -1):
        counts[k] = [int((adjusted == r).sum()) for r in range(1, 5)]
        lower, adjusted = np.unique(lower & ((1 << 8 * (k - 1)) - 1), return_counts=True)
    low = kneser_ney.LowOrders(counts, lower, adjusted)
    got = kneser_ney.shard_scores(level, n, low, asked)
    want = brute_kneser_ney(texts, kneser_ney.ORDER, [int(g).to_bytes(kneser_ney.ORDER, "big") for g in asked])
    assert np.allclose(got, want)
    # In two bytes' continuations probabilities sum to 1.
    assert np.allclose(low.two.sum(axis=1), 1)


def test_classifier_keeps_clean_and_rejects_junk(spark):
    import random

    rng = random.Random(5)
    syllables = ["an", "ber", "co", "del", "er", "fin", "ga"]
    clean = [" ".join("".join(rng.choice(syllables) for _ in range(rng.randint(1, 3))) for _ in range(80)) for _ in range(300)]
    junk = ["".join(rng.choice("#$%&XQZ012") for _ in range(400)) for _ in range(20)]
    rows = [(i, t, "xx") for i, t in enumerate(clean)] + [(1000 + i, t, "xx") for i, t in enumerate(junk)] + [(2000, None, "xx"), (2001, "", None), (None, clean[0], "xx"), (2002, clean[1], "no model")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, 1, 0) for i in range(200)] + [(1000, 0, 0)], "doc_id long, quality int, toxic int")
    got = {r["id"]: r for r in kneser_ney.classify(docs, labels).collect()}
    assert len(got) == len({r[0] for r in rows})
    assert all(got[i]["kept"] for i in range(300)) and not any(got[1000 + i]["kept"] for i in range(20))
    assert got[2002]["kept"] and got[2002]["threshold"] is None and got[2000]["kept"] and got[2001]["kept"] and got[None]["kept"]
    none = labels.limit(0)
    assert kneser_ney.classify(docs, none).where("kept").count() == len(rows)
    assert kneser_ney.classify(docs.limit(0), labels).count() == 0


# --- packing and chat ----------------------------------------------------------------------


def test_bins_take_the_tightest_fit():
    rng = np.random.default_rng(2)
    pieces = zip(-np.sort(-rng.integers(1, 60, 400)), rng.integers(-1, 9, 400), rng.integers(-1, 70, 400), strict=True)
    bins, inside = packing.Bins(100, 9, 70), []
    for size, source, cluster in ((int(a), int(b), int(c)) for a, b, c in pieces):
        left = [100 - sum(p[0] for p in b) for b in inside]
        fit = [left[k] for k, b in enumerate(inside) if left[k] >= size and not any(source == p[1] >= 0 or cluster == p[2] >= 0 for p in b)]
        at = bins.place(size, source, cluster)
        if fit:
            assert left[at] == min(fit)
        else:
            assert at == len(inside)
            inside.append([])
        inside[at].append((size, source, cluster))


def test_packing(odd, empty):
    got = packing.pack_best_fit(odd, capacity=64).collect()
    words = sorted((str(r["doc_id"]), len(WORD.findall(r["text"] or ""))) for r in odd.collect())
    total = defaultdict(int)
    for r in got:
        total[str(r["id"])] += r["n_tokens"]
    want = defaultdict(int)
    for i, n in words:
        want[i] += n
    assert dict(total) == dict(want)
    for key in ("source", "cluster"):
        pairs = Counter((r["bin"], r[key]) for r in got if r[key] is not None)
        assert max(pairs.values()) == 1
    for b in {r["bin"] for r in got}:
        inside = sorted((r["slot"], r["start"], r["n_tokens"]) for r in got if r["bin"] == b)
        assert [x[0] for x in inside] == list(range(len(inside))) and sum(x[2] for x in inside) <= 64
        assert all(inside[k][1] == sum(x[2] for x in inside[:k]) for k in range(len(inside)))
    assert packing.pack_best_fit(empty).count() == 0


@pytest.mark.parametrize("text", ["", "plain", "\\", "\\\\", "###", "####", "\\###", "</turn>", "a\\</turn>###\\", "### Assistant: </turn> ok", "é\\n\n"])
def test_escape_comes_back(text):
    escaped = chat.escape(text)
    assert chat.unescape(escaped) == text
    assert not re.search(r"(?<!\\)(###|</turn>)", escaped.replace("\\\\", "  "))


def test_chat(spark):
    rows = [(1, 1, "assistant", "hi ### there"), (1, 0, "user", "hello"), (2, 0, None, None), (2, None, "assistant", "first"), (None, 0, "user", "lost"), (3, 0, "assistant", "same"), (3, 0, "assistant", "same"), (4, 0, "user", "w " * 5000)]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    vocabulary = chat.Vocabulary.read()
    out = chat.format_chat(turns, vocabulary).collect()
    by = defaultdict(list)
    for r in out:
        by[r["conv_id"]].append(r)
    assert {k: len(v) for k, v in by.items()} == {1: 2, 2: 2, None: 1, 3: 2, 4: 1}
    for v in by.values():
        at = 0
        for r in v:
            assert r["start"] == at and r["ids"][0] == vocabulary.reserved and r["ids"][-1] == vocabulary.reserved + 2
            assert all(r["start"] <= x <= r["start"] + len(r["ids"]) for x in (r["loss_begin"], r["loss_end"]))
            at += len(r["ids"])
    shared = spark.sparkContext.broadcast(vocabulary)
    back = chat.format_chat(turns, vocabulary).mapInArrow(chat._read_back(shared), "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long").collect()
    got = {r["conv_id"]: r for r in back}
    assert got[1]["turns_sha256"] == hashlib.sha256(b"user\nhello\nassistant\nhi ### there\n").hexdigest()
    assert got[1]["loss_sha256"] == hashlib.sha256(b"hi ### there").hexdigest() and got[1]["loss_chars"] == 12
    assert got[3]["loss_sha256"] == hashlib.sha256(b"samesame").hexdigest() and got[4]["loss_chars"] == 0
    assert chat.format_chat(turns.limit(0), vocabulary).count() == 0
