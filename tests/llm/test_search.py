import math

import pytest
from pyspark.sql import functions as F

from geocentra.llm import registry, topk, url_rules

SF = "/root/testdata/sf0.001"


def test_threshold_search(spark, monkeypatch):
    monkeypatch.setattr(topk, "SHARD_ROWS", 10)
    monkeypatch.setattr(topk, "QUERY_BLOCK", 4)
    monkeypatch.setattr(topk, "STEP", 3)
    import random

    rng = random.Random(1)
    rows = [(i, [rng.gauss(0, 1) for _ in range(6)], 1) for i in range(60)] + [(60, [0.0] * 6, 1), (61, [0.0] * 6, 1), (62, None, 1), (63, [1.0, None, 0.0, 0.0, 0.0, 0.0], 1), (64, [float("nan")] * 6, 1), (65, [float("inf")] + [0.0] * 5, 1), (None, [1.0] * 6, 1), (66, [1.0, 2.0], 1), (67, [2.0, 2.0], 1)]
    rows += [(5, rows[5][1], 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, score int")
    got = topk.top_k(df, F.col("vec_id") % 10 == 0, k=4).collect()
    clean = {i: [math.floor(256 * float(x)) for x in r] for i, r in ((r["vec_id"], r["embedding"]) for r in df.collect()) if i is not None and r is not None and all(x is not None and math.isfinite(x) for x in r)}
    for q in [i for i in clean if i % 10 == 0]:
        want = sorted((-sum(a * b for a, b in zip(clean[q], v, strict=True)), i) for i, v in clean.items() if i != q and len(v) == len(clean[q]))[:4]
        assert [(r["vec_id"], r["score"]) for r in sorted((r for r in got if r["query_id"] == q), key=lambda r: r["rank"])] == [(i, -s) for s, i in want]
    assert topk.top_k(df.limit(0), F.col("vec_id") % 10 == 0).count() == 0


def test_urls(spark):
    urls = ["http://a.example.com/en/x?q#f", "HTTPS://WWW.Example.COM/en/1", "http://b.net/es/", "http://net/fr", "b.net/es/", None, "http://x.org", "http://spam.example.org/win", "http://spam.example.org/win", "", "a://b://c/d"]
    pages = spark.createDataFrame([(i, u, "x") for i, u in enumerate(urls)] + [(None, "http://b.net/es/2", "x")], "page_id long, url string, rule string")
    labelled = spark.createDataFrame([(f"http://spam.example.org/{i}", True) for i in range(30)] + [(f"http://fine.example.org/{i}", False) for i in range(60)] + [(None, True)], "url string, bad boolean")
    got = {r["page_id"]: r for r in url_rules.judge_urls(pages, url_rules.RULES, labelled).collect()}
    assert len(got) == 12
    assert (got[0]["host"], got[0]["path"], got[0]["rule"], got[0]["verdict"]) == ("a.example.com", "/en/x", "example.com/en/", "block")
    assert (got[1]["host"], got[1]["rule"], got[1]["verdict"]) == ("www.example.com", "www.example.com/en/", "allow")
    assert got[2]["rule"] == "net/es/" and got[3]["rule"] is None and got[3]["path"] == "/fr"
    assert (got[4]["host"], got[4]["path"]) == ("", "") and (got[5]["host"], got[5]["verdict"]) == ("", "allow")
    assert got[6]["path"] == "" and got[7]["verdict"] == "block" and got[8]["verdict"] == "block" and got[6]["verdict"] == "allow"
    assert (got[10]["host"], got[10]["path"]) == ("b:", "//c/d") and got[None]["rule"] == "net/es/"
    none = labelled.limit(0)
    assert url_rules.judge_urls(pages, url_rules.RULES, none).where("verdict = 'block'").count() == 3
    assert url_rules.judge_urls(pages.limit(0), url_rules.RULES, labelled).count() == 0


@pytest.mark.parametrize("name", sorted(registry.oracle_sql()))
def test_queries_equal_sql(spark, name):
    import duckdb

    con = duckdb.connect()
    for t in ("documents", "benchmark", "embeddings", "pages", "labels", "conversations"):
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    got = registry.queries()[name](spark, SF)
    names = sorted(got.columns)
    want = con.execute(registry.oracle_sql()[name]).df()
    assert sorted(want.columns) == names
    assert sorted(map(str, (tuple(r[n] for n in names) for r in got.collect()))) == sorted(map(str, (tuple(r) for r in want[names].astype(object).itertuples(index=False, name=None))))


def test_pipeline(spark):
    import corpus_pipeline as P

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    before = docs.count()
    for name, stage in P.STAGES[:-1]:
        then = stage(spark, docs, SF)
        assert then.columns == P.COLUMNS, name
        docs = spark.createDataFrame(then.collect(), then.schema)
        assert 0 < docs.count() <= before, name
        before = docs.count()
    packed = P.STAGES[-1][1](spark, docs, SF)
    assert {r["doc_id"] for r in packed.collect()} == {r["doc_id"] for r in docs.collect()}
    whole = P.run(spark, SF)
    assert whole.agg(F.sum("n_tokens")).first()[0] == packed.agg(F.sum("n_tokens")).first()[0]
