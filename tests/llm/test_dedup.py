import hashlib
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from geocentra.llm import blocks as B
from geocentra.llm import minhash, suffix_dedup
from geocentra.llm.components import connected_components
from geocentra.llm.substring_dedup import substring_dedup

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def fold(s):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in s)


def brute_substrings(rows, width):
    seen, out = set(), {}
    for i, t, *_ in sorted(rows):
        words = WORD.findall(t or "")
        gone, mine = set(), []
        for k in range(len(words) - width + 1):
            w = tuple(words[k : k + width])
            if w in seen:
                gone.update(range(k, k + width))
            seen.add(w)
            mine.append(w)
        out[i] = (len(words), len(gone), " ".join(w for k, w in enumerate(words) if k not in gone))
    return out


@pytest.mark.parametrize("width", [5, 20])
def test_substrings(docs, rows, width):
    got = substring_dedup(docs, width=width, carry=["n_words", "id"]).collect()
    want = brute_substrings(rows, width)
    assert {r["id"]: (r["n_words"], r["n_removed"], r["kept_text"]) for r in got} == want
    for r in got:
        assert sum(s["end"] - s["start"] for s in r["spans"]) == r["n_removed"]
        assert r["carried"]["n_words"] == "n"


def test_substrings_in_place(docs, rows):
    text = {r[0]: r[1] for r in rows}
    for r in substring_dedup(docs, in_place=True).collect():
        if not r["n_removed"]:
            assert r["kept_text"] == (text[r["id"]] or "")
        else:
            assert len(WORD.findall(r["kept_text"])) == r["n_words"] - r["n_removed"]


def test_substrings_odd_rows(odd, empty):
    got = substring_dedup(odd, width=5).collect()
    assert len(got) == odd.count()
    assert all(r["n_removed"] == 0 for r in got if r["id"] is None)
    assert substring_dedup(empty).count() == 0


def brute_suffixes(rows, length):
    seen, out = set(), {}
    for i, t, *_ in sorted(rows):
        b = (t or "").encode()
        grams = [b[k : k + length] for k in range(len(b) - length + 1)]
        mask = bytearray(len(b))
        for k, g in enumerate(grams):
            if g in seen:
                mask[k : k + length] = b"\1" * length
        seen.update(grams)
        runs = sum(1 for k, m in enumerate(mask) if m and (k == 0 or not mask[k - 1]))
        out[i] = (len(b), sum(mask), runs, hashlib.sha256(bytes(c for c, m in zip(b, mask, strict=True) if not m)).hexdigest())
    return out


@pytest.mark.parametrize("length", [30, 50])
def test_suffixes(docs, rows, length, monkeypatch):
    monkeypatch.setattr(suffix_dedup, "GROUP_BYTES", 4000)
    monkeypatch.setattr(suffix_dedup, "SPLIT", 2)
    got = suffix_dedup.suffix_dedup(docs, length=length).withColumn("h", F.sha2("kept", 256)).collect()
    assert {r["id"]: (r["n_bytes"], r["n_removed"], len(r["spans"]), r["h"]) for r in got} == brute_suffixes(rows, length)


def test_suffixes_odd_rows(odd, empty):
    got = suffix_dedup.suffix_dedup(odd).collect()
    assert len(got) == odd.count()
    assert all(r["n_removed"] == 0 for r in got if r["id"] is None)
    assert suffix_dedup.suffix_dedup(empty).count() == 0
    with pytest.raises(ValueError, match="length"):
        suffix_dedup.suffix_dedup(odd, length=10)


def test_transform_finds_all_common_prefixes():
    rng = np.random.default_rng(1)
    for symbols in (2, 4, 20):
        segments = [rng.integers(1, symbols + 1, rng.integers(1, 60)).astype(np.uint16) for _ in range(30)]
        segments += segments[:5]
        text = np.concatenate([np.append(s, 0) for s in segments]).astype(np.uint16)
        order, new = suffix_dedup.repeats(text, 12)
        whole = [bytes(text[i : i + 12].astype(np.uint8)) if 0 not in text[i : i + 12] and i + 12 <= len(text) else None for i in order]
        run = np.cumsum(new)
        by_run = {}
        for r, w in zip(run.tolist(), whole, strict=True):
            if w is not None:
                by_run.setdefault(r, set()).add(w)
        assert all(len(v) == 1 for v in by_run.values())
        assert len(by_run) == len({w for w in whole if w is not None})


def brute_near(rows, width, percent):
    sets = {}
    for i, t, *_ in rows:
        w = WORD.findall(fold(t or ""))
        sets[i] = {tuple(w[k : k + width]) for k in range(len(w) - width + 1)} or ({tuple(w)} if w else set())
    parent = {i: i for i in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for x in ids:
        for y in ids:
            if x < y and sets[x] and 100 * len(sets[x] & sets[y]) >= percent * len(sets[x] | sets[y]) and sets[y]:
                a, b = sorted((root(x), root(y)))
                parent[b] = a
    return {i: (len(sets[i]), root(i)) for i in ids}


@pytest.mark.parametrize("width", [2, 5])
def test_near_duplicates(docs, rows, width, monkeypatch):
    monkeypatch.setattr(minhash, "BLOCK_ROWS", 3)
    got = minhash.near_duplicates(docs, width=width).collect()
    assert {r["id"]: (r["n_shingles"], r["component"]) for r in got} == brute_near(rows, width, 80)
    assert all(r["kept"] == (r["id"] == r["component"]) for r in got)


def test_near_duplicates_odd_rows(odd, empty):
    got = minhash.near_duplicates(odd).collect()
    assert sum(r["id"] is None for r in got) == 2
    named = [r["id"] for r in got if r["id"] is not None]
    assert len(named) == len(set(named))
    assert minhash.near_duplicates(empty).count() == 0


def test_tensored_keys_are_pairs_of_rows():
    banding = minhash.Banding(half=3, rows=2)
    a = np.arange(24, dtype=np.uint32).reshape(2, 12)
    a[1] = a[0]
    a[1, 0] = 99  # the first row of the first collection differs
    keys = minhash.table_keys(a, banding)
    assert keys.shape == (2, 9)
    assert (keys[0] == keys[1]).tolist() == [False] * 3 + [True] * 6


def test_components(spark):
    chain = [(i, i + 1) for i in range(0, 40)] + [(100, 101), (102, 101), (200, 200)]
    got = connected_components(spark.createDataFrame(chain, "a long, b long")).collect()
    assert {r["node"]: r["component"] for r in got} == {i: 0 for i in range(41)} | {100: 100, 101: 100, 102: 100}
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_blobs_come_back():
    arrays = [np.arange(5, dtype=np.int64), np.zeros(0, np.uint16), np.arange(14, dtype=np.uint8).reshape(2, 7), np.arange(1000, dtype=np.int32)]
    for a, b in zip(arrays, B.unpack(B.pack(*arrays)), strict=True):
        assert a.dtype == b.dtype and a.shape == b.shape and (a == b).all()


@pytest.mark.parametrize("local", [0, 150, 1 << 21])
def test_components_in_a_task_and_by_steps_agree(spark, monkeypatch, local):
    monkeypatch.setattr("geocentra.propagate.local.LOCAL_ARCS", local)
    monkeypatch.setattr("geocentra.propagate.local.OUT_ROWS", 70)
    rng = np.random.default_rng(5)
    order = rng.permutation(200)
    ends = [(int(order[i]), int(order[i + 1])) for i in range(99)] + [(500, i) for i in range(600, 640)] + [(7 + 1000 * int(a), 7 + 1000 * int(b)) for a, b in rng.integers(1, 90, (60, 2))]
    want = {x: x for e in ends for x in e}
    for _ in want:
        for a, b in ends:
            want[a] = want[b] = min(want[a], want[b])
    want = {x: c for x, c in want.items() if any(a != b for a, b in ends if x in (a, b))}
    assert {r["node"]: r["component"] for r in connected_components(spark.createDataFrame(ends, "a long, b long")).collect()} == want


def test_components_of_few_links_take_no_job_a_step(spark):
    chain = spark.range(3000).selectExpr("id * 7919 % 3001 AS a", "(id + 1) * 7919 % 3001 AS b")
    spark.sparkContext.setJobGroup("chain of links", "chain of links")
    try:
        found = connected_components(chain)
        assert found.count() == 3001 and found.where("component <> 0").isEmpty()
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("chain of links")) < 12
