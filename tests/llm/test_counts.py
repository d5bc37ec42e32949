"""Words and shingles of odd texts against their plain definitions."""

import re

import numpy as np
import pyarrow as pa

from geocentra.llm import blocks as B
from geocentra.llm import minhash as M
from geocentra.llm.packing import pack_best_fit

TEXTS = [None, "", " \t\n", "one", "a b", " A  b\x0b\x0c\r", "x" * 3000, "é ü ß  ", "a b a b a b a b a b", "\x00 \x1f a", "w " * 5000, "A b c d e f", "a B C d e g", "last"]
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def test_shingle_sets_are_distinct_ascending_and_of_the_right_size():
    texts = TEXTS + [" ".join(f"w{k * k % 89}" for k in range(n)) for n in range(120)]
    for width in (1, 2, 5):
        value, offs = M.shingle_sets(pa.array(texts), width)
        sets = []
        for text, lo, hi in zip(texts, offs[:-1], offs[1:], strict=True):
            words = [re.sub("[A-Z]", lambda m: m[0].lower(), w) for w in WORD.findall(text or "")]
            want = {tuple(words[i : i + width]) for i in range(max(1, len(words) - width + 1))} if words else set()
            assert hi - lo == len(want)
            assert (value[lo:hi][1:] > value[lo:hi][:-1]).all()
            sets.append((want, set(value[lo:hi].tolist())))
        for want, got in sets:
            for other, other_got in sets[::7]:
                assert len(want & other) == len(got & other_got)
    assert M.shingle_sets(pa.array([], pa.string()), 2)[1].tolist() == [0]


def test_minima_are_of_the_upper_halves():
    batch = pa.RecordBatch.from_arrays([pa.array(range(len(TEXTS)), pa.int64()), pa.array([0] * len(TEXTS), pa.int64()), pa.array(TEXTS)], names=["id", "version", "text"])
    banding = M.Banding()
    got = pa.Table.from_batches(M._sign(2, banding)([batch]))
    rng = np.random.default_rng(20240229)
    factor = (rng.integers(1, 1 << 62, banding.minima, dtype=np.uint64) << B.U64(1)) | B.U64(1)
    value, offs = M.shingle_sets(pa.array(TEXTS), 2)
    for k, blob in enumerate(got.column("minima").to_pylist()):
        mine = value[offs[k] : offs[k + 1]]
        assert np.frombuffer(blob, np.uint32).tolist() == [int(((mine * f) >> B.U64(32)).min()) if len(mine) else 0 for f in factor]


def test_packing_counts_words_without_a_list_of_them(spark):
    """Words were counted by a regular expression, which lists them all first."""
    docs = spark.createDataFrame([(i, t, None) for i, t in enumerate(TEXTS)] + [(None, "no id", None)], "doc_id long, text string, source string")
    got = pack_best_fit(docs, capacity=1 << 20)
    assert "regexp" not in got._jdf.queryExecution().toString()
    assert sorted((r.id if r.id is not None else -1, r.n_tokens) for r in got.collect()) == [(-1, 2)] + [(i, len(WORD.findall(t or ""))) for i, t in enumerate(TEXTS)]
