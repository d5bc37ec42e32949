"""Exact distances by classes of equal nodes against those of all nodes."""

import pytest
from pyspark.sql import functions as F

from geocentra.graph import views
from geocentra.propagate import classes as C
from geocentra.propagate.exact import exact_pairs
from geocentra.registry import graphs as R


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def html(*links):
    return "".join(f'<a href="{x}">' for x in links)


@pytest.fixture()
def pages(spark, tmp_path):
    """Copies, a page id with two texts, pages alone, without links, or null."""
    some = [("a", "b"), ("b", "a"), ("c", "b", "a"), ("d", "c"), ("e",), ("f", "f"), ("f",), ("x", "e"), ()]
    made = [(i, "u", html(*some[i % 7])) for i in range(40)] + [(50, "u", html(*some[7])), (51, "u", html(*some[8])), (52, "u", None), (None, "u", html("a"))]
    made += [(60, "u", html("a", "d")), (60, "u", html("g", "h")), (61, "u", html("y", "z")), (62, "u", html("h", "e"))]
    spark.createDataFrame(made, "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    return str(tmp_path)


@pytest.mark.parametrize("direction", ["in", "out"])
@pytest.mark.parametrize("tables", [False, True])
def test_classes_and_nodes_agree(spark, monkeypatch, pages, direction, tables):
    monkeypatch.setattr(C, "CHUNK", 3)
    if tables:
        monkeypatch.setattr(C.L, "LOCAL_ARCS", 0)
    want = exact_pairs(views.graph(spark, pages, "g8"), direction=direction)
    got = C.exact_pairs_of_classes(C.classes_of(views.page_keys(spark, pages)), direction)
    pairs = rows(got.pairs())
    assert pairs == rows(want.pairs()) and len(pairs) == len(set(pairs)) > 900
    assert rows(got.counts()) == rows(want.counts())


def test_copies_of_pages_make_no_arcs(spark, tmp_path):
    """300,000 copies would be 9 * 10^10 arcs."""
    rows_of = spark.range(300000).select(F.col("id").alias("page_id"), F.lit("u").alias("url"), F.when(F.col("id") % 2 == 0, html("a", "b")).otherwise(html("b", "a")).alias("html"))
    rows_of.write.parquet(f"{tmp_path}/pages.parquet")
    found = R.QUERIES["exact_centralities_g8"](spark, str(tmp_path))
    assert [tuple(r) for r in found.groupBy("coreach", "sum_dist", "harmonic").count().collect()] == [(300000.0, 299999.0, 299999.0, 300000)]


def test_pairs_of_copies_take_few_bytes_in_files(spark, tmp_path, monkeypatch):
    """9,000,000 pairs: short repetitions of sources take a fifth of a byte a pair at most, and no task unfolds many times TASK_PAIRS."""
    monkeypatch.setattr(C, "TASK_PAIRS", 200000)
    spark.range(3000).select(F.col("id").alias("page_id"), F.lit("u").alias("url"), F.lit(html("a")).alias("html")).write.parquet(f"{tmp_path}/pages.parquet")
    run = C.exact_pairs_of_classes(C.classes_of(views.page_keys(spark, str(tmp_path))))
    assert run.n_pairs() == 9000000
    assert run.pairs().rdd.getNumPartitions() == 45
    R.QUERIES["exact_pairs_g8"](spark, str(tmp_path)).write.parquet(f"{tmp_path}/out")
    got = spark.read.parquet(f"{tmp_path}/out")
    assert got.count() == 9000000 and got.select("node", "source").distinct().count() == 9000000
    assert sum(x.stat().st_size for x in (tmp_path / "out").glob("*.parquet")) < 9000000 / 5
