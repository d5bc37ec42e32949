"""Cases of the training-data operators that bounds used to leave out."""

import itertools
import math
import random
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from geocentra.llm import blocks as B
from geocentra.llm import katz, kneser_ney, minhash, packing, substring_dedup, suffix_dedup, topk, url_rules
from geocentra.llm.exchange import ask

SYLLABLES = ["an", "ber", "co", "del", "er", "fin", "ga"]


def prose(rng, n):
    return " ".join("".join(rng.choice(SYLLABLES) for _ in range(rng.randint(1, 3))) for _ in range(n))


def dirty(rng, text, k):
    out = list(text)
    for i in rng.sample(range(len(out)), k):
        out[i] = rng.choice("#$%&XQZ012")
    return "".join(out)


def test_classifier_limits_go_by_length(spark):
    """Short trusted texts, whose rates vary much, do not loosen the limit of long ones."""
    rng = random.Random(6)
    clean = [prose(rng, 80) for _ in range(200)] + [dirty(rng, prose(rng, 2), 2) for _ in range(200)]
    junk = [dirty(rng, prose(rng, 80), 12) for _ in range(20)]
    docs = spark.createDataFrame([(i, t, "xx") for i, t in enumerate(clean + junk)], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(i, 1, 0) for i in range(0, 400, 2)], "doc_id long, quality int, toxic int")
    got = {r["id"]: r["kept"] for r in kneser_ney.classify(docs, labels).collect()}
    assert not any(got[400 + i] for i in range(20))
    assert sum(got[i] for i in range(400)) >= 392


def test_near_copies_share_no_bin(spark):
    rng = random.Random(7)
    base = prose(rng, 120).split()
    rows = []
    for i in range(30):
        changed = list(base)
        changed[4 * i] = "zz"
        rows.append((i, " ".join(changed), f"s{i}"))
    rows += [(100 + i, prose(rng, 120), f"t{i}") for i in range(30)]
    # A repeated id with a text of its own, a row without an id, and texts without words.
    rows += [(5, " ".join(base), "u0"), (None, rows[0][1], "u1"), (200, "", "u2"), (201, None, "u3")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = packing.pack_best_fit(docs, capacity=600, group_rows=1 << 20, clusters=packing.near_cluster_names(docs).coalesce(1)).collect()
    assert len(got) == len(rows)
    near = Counter(r["bin"] for r in got if r["id"] is None or r["id"] < 100)
    assert len({r["cluster"] for r in got if r["source"] in {f"s{i}" for i in range(30)} | {"u1"} and r["id"] != 5}) == 1
    assert max(near[r["bin"]] for r in got if r["source"].startswith("s") and r["id"] != 5) <= 2
    assert max(Counter((r["bin"], r["cluster"]) for r in got if r["cluster"] is not None).values()) == 1


# --- counts and hashes ---------------------------------------------------------------------


def test_counts_beyond_32_bits():
    """Tables of counts add up and answer what no 32 bits hold."""
    h = np.sort(B.mix(np.arange(1, 6, dtype=np.uint64)))
    n = np.array([3_000_000_000, 1, 2, 0, 5])
    rows = [ask(h, 1, g, katz.narrow(n))[0] for g in (1, 2)]
    table = pa.table({"bucket": pa.array([0, 0], pa.int32()), "g": pa.array([1, 2], pa.int64()), "blob": pa.array([r[2] for r in rows], pa.binary())})
    got = katz._count(1)(table).to_pylist()
    assert [B.unpack(r["blob"])[0].tolist() for r in got if r["g"] >= 0] == [(2 * n).tolist()] * 2
    assert next(r["n"] for r in got if r["g"] < 0 and r["bucket"] == -1) == 2 * n.sum()
    assert katz.narrow(np.array([7])).dtype == np.int32


def test_colliding_hashes_remove_nothing_more(spark, monkeypatch):
    """A first hash of a few bits alone: the second tells windows apart."""
    rng = random.Random(8)
    passage = prose(rng, 30)
    rows = [(i, f"{prose(rng, 40)} {passage}" if i % 5 == 0 else prose(rng, 60)) for i in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").coalesce(1)
    want = {r["id"]: (r["n_removed"], r["kept_text"]) for r in substring_dedup.substring_dedup(docs).collect()}
    real = B.window_hashes
    # The tasks of Python get the patched function with the closure of _send_windows.
    tables = []
    for few in (False, True):
        monkeypatch.setattr(B, "window_hashes", (lambda items, width, second=False: real(items, width, second) if second else real(items, width) & np.uint64(0xFF)) if few else real)
        batch = pa.RecordBatch.from_arrays([pa.array([i for i, _ in rows], pa.int64()), pa.array([0] * len(rows), pa.int32()), pa.array([t for _, t in rows])], names=["id", "g", "text"])
        sent = pa.Table.from_batches(list(substring_dedup._send_windows(20, 1)([batch.slice(0, 20), batch.slice(20)])))
        doc, pos = substring_dedup.found_positions(substring_dedup._judge(sent).column("blob").to_pylist())
        tables.append({(int(d), int(p)) for d, p in zip(doc, pos, strict=True)})
    assert tables[0] == tables[1] and tables[0]
    assert sum(v[0] > 0 for v in want.values()) == len({d for d, _ in tables[0]})


def test_colliding_regions_are_compared_by_bytes(monkeypatch):
    raw = np.frombuffer(b"abcabdabcxyz", np.uint8)
    begin, size = np.array([0, 3, 6, 9]), np.array([3, 3, 3, 3])
    monkeypatch.setattr(B, "word_hashes", lambda raw, a, b: np.zeros(len(a), np.uint64))
    order, later = suffix_dedup._copies(raw, begin, size, np.zeros(4, np.uint64), np.array([1, 2, 3, 4]))
    assert order[later].tolist() == [2]
    assert B.same_spans(raw, np.array([0, 0, 5]), np.array([6, 3, 5]), np.array([3, 3, 0])).tolist() == [True, False, True]


# --- near copies ---------------------------------------------------------------------------


@pytest.mark.parametrize("block", [2, 512])
def test_groups_that_stars_leave_apart(spark, monkeypatch, block):
    """A chain of versions, each near to the next alone, and many texts that share half of their words."""
    monkeypatch.setattr(minhash, "BLOCK_ROWS", block)
    rng = random.Random(9)
    words = prose(rng, 400).split()
    rows = [(i, " ".join(words[4 * i : 4 * i + 100])) for i in range(40)]
    common = prose(rng, 60).split()
    rows += [(100 + i, " ".join(common + prose(rng, rng.choice([4, 10, 30])).split())) for i in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    sets = {i: {tuple(t.split()[k : k + 2]) for k in range(len(t.split()) - 1)} for i, t in rows}
    parent = {i: i for i in sets}
    root = lambda x: x if parent[x] == x else root(parent[x])
    for a, b in itertools.combinations(sorted(sets), 2):
        if 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
            x, y = sorted((root(a), root(b)))
            parent[y] = x
    got = {r["id"]: r["component"] for r in minhash.near_duplicates(docs, width=2).collect()}
    assert got == {i: root(i) for i in sets}


@pytest.mark.parametrize("width", [2, 5])
def test_recall_of_links(spark, width):
    """Of pairs just above the threshold none is missed: the share missed is some 1e-5 by design."""
    rng = random.Random(10 + width)
    rows = []
    for i in range(150):
        base = prose(rng, 200).split()
        other = list(base)
        for k in range(10 if width == 2 else 4):
            other[9 * k] = "zz%d" % rng.randrange(10**6)
        rows += [(2 * i, " ".join(base)), (2 * i + 1, " ".join(other))]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    sets = {i: {tuple(t.split()[k : k + width]) for k in range(len(t.split()) - width + 1)} for i, t in rows}
    linked = [i for i in range(150) if 100 * len(sets[2 * i] & sets[2 * i + 1]) >= 80 * len(sets[2 * i] | sets[2 * i + 1])]
    got = {r["id"]: r["component"] for r in minhash.near_duplicates(docs, width=width).collect()}
    assert linked and all(got[2 * i + 1] == 2 * i for i in linked)


# --- classifier, rules, packing, search ------------------------------------------------------


def brute_rates(train, asked, order):
    """-log10 a byte of each text under a Kneser-Ney model of the training texts, from dictionaries."""
    levels = {order: Counter()}
    lines = lambda t: bytes(order - 1) + bytes(max(1, b) for b in t.encode()) + bytes(1)
    for t in train:
        x = lines(t)
        levels[order].update(x[k : k + order] for k in range(len(x) - order + 1))
    for k in range(order - 1, 0, -1):
        levels[k] = Counter(g[1:] for g in levels[k + 1])
    cuts = {k: kneser_ney.modified_discounts([sum(c == r for c in v.values()) for r in range(1, 5)]) for k, v in levels.items()}
    after = {k: defaultdict(list) for k in levels}
    for k, v in levels.items():
        for g, c in v.items():
            after[k][g[:-1]].append(c)

    def p(g):
        if not g:
            return 1 / 256
        k = len(g)
        mine = after[k].get(g[:-1])
        if not mine:
            return p(g[1:])
        c, d = levels[k].get(g, 0), cuts[k]
        return max(c - d[min(c, 3)], 0) / sum(mine) + sum(d[min(x, 3)] for x in mine) / sum(mine) * p(g[1:])

    out = []
    for t in asked:
        x = lines(t)
        got = [math.log10(p(x[k : k + order])) for k in range(len(x) - order + 1)]
        out.append(-sum(got) / len(got))
    return out


def test_classifier_equals_brute_force(spark):
    """Sample, model, thresholds and decisions from end to end; repeated ids and rows, clashing columns, a long text."""
    rng = random.Random(11)
    rows = [(i, prose(rng, rng.choice([5, 20, 40])), rng.choice(["xx", "yy"])) for i in range(120)]
    rows += [(200 + i, "".join(rng.choice("#$%&XQZ012") for _ in range(150)), "xx") for i in range(10)] + [(3, "quite another text", "xx"), rows[4], (300, prose(rng, 3000), "yy"), (301, "", "xx"), (302, "no model", "zz"), (None, rows[0][1], "xx")]
    docs = spark.createDataFrame([(*r, 1.5, "k") for r in rows], "doc_id long, text string, lang string, score double, kept string")
    labels = spark.createDataFrame([(i, int(i % 6 > 0), int(i % 11 == 0)) for i in range(120)], "doc_id long, quality int, toxic int")
    halves = {r["id"]: r["h"] for r in spark.range(400).select("id", F.pmod(F.xxhash64("id", F.lit(11)), F.lit(2)).alias("h")).collect()}
    trusted = {i for i in range(120) if i % 6 > 0 and i % 11}
    rates = {}
    for lang in ("xx", "yy"):
        texts = [t for _, t, one in rows if one == lang]
        train = [t for i, t, one in rows if one == lang and i in trusted and halves[i] == 0]
        rates |= {(lang, t): x for t, x in zip(texts, brute_rates(train, texts, kneser_ney.ORDER), strict=True)}
    octave = lambda t: int(math.log2(len(t.encode()) + 1))
    quantile = lambda v: sorted(v)[max(0, math.ceil(0.999 * len(v)) - 1)]

    def limit(lang, o):
        mine = [(octave(t), rates[lang, t]) for i, t, one in rows if one == lang and i in trusted and halves[i] == 1]
        for w in kneser_ney.WIDTHS:
            near = [x for k, x in mine if abs(k - o) <= w]
            if len(near) >= kneser_ney.MIN_CALIBRATION:
                return quantile(near) + 0.02
        return quantile([x for _, x in mine]) + 0.02

    want = sorted((str(i), t == "" or one == "zz" or rates[one, t] <= limit(one, octave(t)) + 1e-9) for i, t, one in rows)
    got = kneser_ney.classify(docs, labels).collect()
    assert sorted((str(r["id"]), r["kept"]) for r in got) == want
    assert not all(k for _, k in want)
    found = {(r["id"], r["version"]): r["rate"] for r in got}
    versions = {(r["doc_id"], r["v"]): (r["lang"], r["text"]) for r in docs.select("doc_id", F.xxhash64("text").alias("v"), "lang", "text").collect()}
    for key, rate in found.items():
        if versions[key] in rates and versions[key][1]:
            assert rate == pytest.approx(rates[versions[key]], abs=2e-5)


def test_mined_verdicts_equal_brute_force(spark):
    """Every combination of up to three tokens, counted outright."""
    rng = random.Random(12)
    pool = ["spam", "win", "shop", "news", "blog", "free", "wiki"]
    urls = []
    for _ in range(300):
        t = rng.sample(pool, rng.randint(1, 4))
        bad = ("spam" in t and "win" in t) or ("free" in t and rng.random() < 0.8) or rng.random() < 0.02
        urls.append((f"http://{t[0]}.org/" + "/".join(t[1:]), bad))
    long = "http://blog.org/" + "x" * 20000 + "/spam/win"
    labelled = spark.createDataFrame(urls + [(None, True), ("", False)], "url string, bad boolean")
    pages = spark.createDataFrame([(i, u, "z") for i, (u, _) in enumerate(urls)] + [(0, urls[0][0], "z"), (900, long, "z"), (901, None, "z"), (902, None, "z")], "page_id long, url string, token string")
    tokens = lambda u: {x for x in u.replace("://", "/").replace(".", "/").split("/") if x}
    baskets = [(tokens(u), b) for u, b in urls] + [(set(), True), (set(), False)]
    n, rules = len(baskets), []
    for size in (1, 2, 3):
        for combo in itertools.combinations(sorted({x for t, _ in baskets for x in t}), size):
            holds = [b for t, b in baskets if set(combo) <= t]
            if sum(holds) >= 0.01 * n and sum(holds) / max(1, len(holds)) >= 0.6:
                rules.append(set(combo))
    mined = {r["url"] for r in url_rules.matched_urls(pages, url_rules.mine_rules(labelled, 0.01, 0.6)).collect()}
    assert mined == {u for u in [x for x, _ in urls] + [long] if any(r <= tokens(u) for r in rules)}
    assert rules and len(mined) < len({u for u, _ in urls})
    judged = url_rules.judge_urls(pages, url_rules.RULES, labelled, 0.01, 0.6).collect()
    assert len(judged) == pages.count() and {r["verdict"] for r in judged if r["url"] is None} == {"allow"}


def test_packing_equals_brute_force(spark):
    """One group, piece by piece: the tightest bin that has neither source nor cluster, else a new one."""
    rng = random.Random(13)
    rows = [(i, prose(rng, rng.choice([1, 5, 20, 50, 130])), rng.choice(["a", "b", "c", "d", None])) for i in range(80)] + [(100, "", "a"), (101, None, "a")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    clusters = spark.createDataFrame([(i, None, i % 9) for i in range(40)], "id long, version long, component long").drop("version").join(docs.select(F.col("doc_id").alias("id"), F.xxhash64("text").alias("version")), "id").select("id", "version", "component")
    got = packing.pack_best_fit(docs, capacity=60, group_rows=1 << 20, clusters=clusters.coalesce(1))
    assert got.select(F.shiftright("bin", 32)).distinct().count() >= 1
    order = {r["doc_id"]: r["o"] for r in docs.select("doc_id", F.xxhash64("doc_id", "text").alias("o")).collect()}
    groups = defaultdict(list)
    for r in got.collect():
        groups[r["bin"] >> 32].append(r)
    for found in groups.values():
        times = Counter(c for c in {(r["id"], r["cluster"]) for r in found})
        often = Counter(c for (_, c) in times)
        bins = []
        for r in sorted(found, key=lambda r: (-r["n_tokens"], order[r["id"]], r["piece"])):
            c = r["cluster"] if r["cluster"] is not None and often[r["cluster"]] > 1 else None
            fit = [b for b in bins if b["left"] >= max(r["n_tokens"], 1) and not (r["source"] is not None and r["source"] in b["sources"]) and not (c is not None and c in b["clusters"])] if r["n_tokens"] else None
            b = bins_at(bins, r["bin"] & 0xFFFFFFFF)
            if fit is not None:
                assert b["left"] == min(x["left"] for x in fit) if fit else b["left"] == 60
            b["left"] -= r["n_tokens"]
            b["sources"].add(r["source"]), b["clusters"].add(c)


def bins_at(bins, k):
    while len(bins) <= k:
        bins.append({"left": 60, "sources": set(), "clusters": set()})
    return bins[k]


def test_repeated_ids_with_other_vectors(spark):
    rows = [(1, [1.0, 0.0]), (1, [0.0, 1.0]), (2, [1.0, 1.0]), (3, [0.5, 0.5]), (10, [1.0, 0.0]), (10, [2.0, 0.0])]
    got = topk.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), F.col("vec_id") == 10, k=9).orderBy("rank").collect()
    # Of a repeated id the least vector counts: (0, 256) of 1 and (256, 0) of 10.
    assert [(r["rank"], r["vec_id"], r["score"]) for r in got] == [(1, 2, 65536), (2, 3, 32768), (3, 1, 0)]


# --- the pipeline ----------------------------------------------------------------------------


@pytest.fixture(scope="module")
def tables(spark, tmp_path_factory):
    """Benchmark and labels for a few documents, in a folder as the given ones are."""
    folder = str(tmp_path_factory.mktemp("tables"))
    rng = random.Random(14)
    spark.createDataFrame([(1, prose(rng, 14)), (2, None)], "item_id long, text string").write.parquet(f"{folder}/benchmark.parquet")
    spark.createDataFrame([(i, 1, 0) for i in range(20)], "doc_id long, quality int, toxic int").write.parquet(f"{folder}/labels.parquet")
    return folder


def odd_documents(spark, tables):
    rng = random.Random(15)
    item = spark.read.parquet(f"{tables}/benchmark.parquet").where("item_id = 1").first()["text"]
    base = prose(rng, 60)
    rows = [(i, prose(rng, 40), "xx", "s", 1) for i in range(20)]
    rows += [(30, base, "xx", "s", 1), (31, base, "xx", "t", 1), (32, base + " end", None, None, None), (33, f"{prose(rng, 20)} {item} {prose(rng, 20)}", "xx", "s", 1)]
    rows += [(40, None, "xx", "s", None), (41, "", "xx", "s", 0), (None, base, "xx", "s", 1), (None, None, None, None, None), rows[0], (1, "another text of the first id", "xx", "s", 1), (50, prose(rng, 4000), "xx", "s", 1)]
    return spark.createDataFrame([(*r, 7, "g") for r in rows], "doc_id long, text string, lang string, source string, n_chars long, id int, g string").repartition(3), len(rows), base


def test_stages_take_odd_rows(spark, tables):
    import corpus_pipeline as P

    docs, n, base = odd_documents(spark, tables)
    got = {}
    for name, stage in P.STAGES[:-1]:
        out = stage(spark, docs, tables)
        assert out.columns == P.COLUMNS, name
        got[name] = out.collect()
        assert stage(spark, docs.limit(0), tables).count() == 0, name
    ids = lambda name: Counter(r["doc_id"] for r in got[name])
    # Rows are judged one by one: repeated rows, null and empty texts, other languages stay.
    quality = ids("quality classifier")
    assert quality[0] == 2 and quality[1] == 2 and quality[40] == quality[41] == 1 and quality[None] == 2
    # Copies go, whatever their language and source; a repeated row goes; another text of an id, null ids, and empty texts stay.
    near = ids("near-dedup")
    assert near[30] == 1 and near[31] == near[32] == 0 and near[0] == 1 and near[40] == near[41] == 1 and near[None] == 2
    assert near[1] == 2
    assert ids("substring dedup") == ids("decontamination") == Counter(r["doc_id"] for r in docs.collect())
    text = {r["doc_id"]: r["text"] for r in got["substring dedup"] if r["doc_id"] is not None}
    assert text[30] == base and text[31] == "" and len(text[50].split()) == 4000 and not text[40]
    clean = {r["doc_id"]: r["text"] for r in got["decontamination"] if r["doc_id"] is not None}
    assert len(clean[33].split()) == 40 and clean[30] == base
    packed = P.STAGES[-1][1](spark, docs, tables).collect()
    assert Counter(r["doc_id"] for r in packed if r["piece"] == 0) == Counter(r["doc_id"] for r in docs.collect())
    assert max(Counter((r["bin"], r["source"]) for r in packed if r["source"] is not None).values()) == 1
    assert P.STAGES[-1][1](spark, docs.limit(0), tables).count() == 0


def test_a_failing_stage_leaves_no_rows(spark, tables, tmp_path, monkeypatch):
    import os

    import corpus_pipeline as P

    monkeypatch.setattr(P, "own_folder", lambda spark: str(tmp_path))
    docs, _, _ = odd_documents(spark, tables)
    monkeypatch.setattr(P, "load", lambda spark, d, t: docs if t == "documents" else spark.read.parquet(f"{d}/{t}.parquet"))

    def broken(spark, docs, d):
        raise ValueError("broken")

    monkeypatch.setattr(P, "STAGES", [P.STAGES[0], ("broken", broken)])
    with pytest.raises(ValueError, match="broken"):
        P.run(spark, tables)
    assert not os.listdir(tmp_path)
