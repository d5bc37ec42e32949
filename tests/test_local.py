"""Rounds in memory against rounds in tables."""

import pytest
from pyspark.sql import functions as F

from geocentra.centrality import measures as M
from geocentra.graph import generators as G
from geocentra.graph import views
from geocentra.graph.model import Graph
from geocentra.propagate import local as L
from geocentra.propagate import packed as P
from geocentra.propagate.balls import ball_sketches, pattern_balls
from geocentra.propagate.exact import exact_pairs
from geocentra.propagate.packed import packed_balls, packed_patterns


def rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.fixture(scope="module")
def graph(spark):
    g = G.kronecker(spark, [[0.57, 0.19], [0.19, 0.05]], 5, 60, seed=4)
    ends = g.arcs.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
    return Graph.from_arcs(g.arcs, ends.unionByName(spark.sql("SELECT -5L AS id")))


@pytest.mark.parametrize("small, direction", [(True, "in")])
def test_tasks_and_tables_agree(spark, monkeypatch, graph, small, direction):
    if small:
        monkeypatch.setattr(L, "TASK_BYTES", 4000)
        monkeypatch.setattr(L, "OUT_ROWS", 50)
    runs = lambda: (ball_sketches(graph, 16, 2, direction), pattern_balls(graph, 8, direction=direction), exact_pairs(graph, direction=direction))
    balls, patterns, exact = runs()
    sources = graph.vertices.where("id % 3 = 0")
    some = rows(exact_pairs(graph, sources, direction).pairs())
    got = [rows(balls.rounds.changes), rows(balls.rounds.final()), rows(balls.profile()), rows(patterns.rounds.changes), rows(patterns.rounds.final()), rows(exact.pairs()), rows(exact.counts())]
    assert balls.rounds.last > 1 and not balls.truncated
    monkeypatch.setattr(L, "LOCAL_ARCS", 0)
    balls, patterns, exact = runs()
    assert some == rows(exact_pairs(graph, sources, direction).pairs())
    names = ["node", "run", "item", "value", "old", "t"]
    want = [rows(balls.rounds.changes.select(names)), rows(balls.rounds.final()), rows(balls.profile()), rows(patterns.rounds.changes.select(names)), rows(patterns.rounds.final()), rows(exact.pairs()), rows(exact.counts())]
    assert got == want


def test_a_long_path_takes_no_job_a_round(spark):
    n = 3000
    graph = G.path(spark, n)
    spark.sparkContext.setJobGroup("long path", "long path")
    try:
        counts = {r["node"]: r for r in M.ingredients(exact_pairs(graph).counts()).collect()}
        registers = ball_sketches(graph, 16).registers().count()
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert counts[n - 1]["sum_dist"] == n * (n - 1) / 2 and counts[0]["coreach"] == 1
    assert registers > n
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("long path")) < 40


def test_no_arcs(spark):
    graph = Graph(spark.range(3).select("id", F.lit(1).alias("weight")), spark.range(0).select(F.col("id").alias("src"), F.col("id").alias("dst")))
    assert rows(exact_pairs(graph).pairs()) == [(0, 0, 0), (1, 1, 0), (2, 2, 0)]
    assert rows(exact_pairs(graph).counts()) == [(k, 0, 0, 1.0) for k in range(3)]
    assert ball_sketches(graph, 16).profile().count() == 3


def _left(run, sums):
    return [run.changed, run.last, rows(run.final()), *([rows(run.sums()), rows(run.neighbourhood_function())] if sums else [rows(run.profile())])]


@pytest.mark.parametrize("bits, gains, direction", [(False, None, "out"), (False, {"log": lambda t: 1 / (t + 1)}, "in"), (True, None, "in")])
def test_packed_runs_of_tasks_and_of_tables_agree(spark, monkeypatch, graph, bits, gains, direction):
    made = lambda: packed_patterns(graph, 8, 2, direction, gains=gains) if bits else packed_balls(graph, 16, 3, direction, gains=gains)
    monkeypatch.setattr(P.W, "ROW_BYTES", 300)
    monkeypatch.setattr(L, "TASK_BYTES", 200)
    got = made()
    assert got.last > 1 and got.sent_bytes[1] > 0
    got = _left(got, gains is not None)
    monkeypatch.setattr(P, "LOCAL_BYTES", 0)
    want = _left(made(), gains is not None)
    assert got[:3] == want[:3]
    for a, b in zip(got[3:], want[3:], strict=True):
        assert [x for r in a for x in r] == pytest.approx([x for r in b for x in r], abs=1e-9)


def test_packed_rounds_of_a_long_path_are_no_jobs(spark):
    graph = G.path(spark, 3000)
    spark.sparkContext.setJobGroup("packed path", "packed path")
    run = packed_balls(graph, 16, gains={})
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("packed path")) < 25
    assert run.last > 100 and run.sums().count() == 3000


def test_lines_of_documents_are_dealt_once_and_found_once(spark, tmp_path):
    line = "a line of forty characters or more than that"
    texts = [(1, f"{line}\n{line}\nshort"), (70000, line), (5, f"{line}\n{line} 2"), (9, f"{line} 2"), (140000, line), (None, line), (11, None)]
    spark.createDataFrame(texts, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    arcs = views.VIEWS["g10"](spark, str(tmp_path))
    assert rows(arcs) == [(1, 5), (5, 9), (5, 70000), (70000, 140000)]
    graph = views.graph(spark, str(tmp_path), "g10")
    assert rows(graph.vertices) == [(x, 1) for x in (1, 5, 9, 70000, 140000)]
    for df in (graph.vertices, graph.arcs):
        assert "documents.parquet" not in df._jdf.queryExecution().toString()
