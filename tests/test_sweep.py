"""Distances found by passing nodes in order against those of visits and of pairs."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from geocentra.accuracy import errors as A
from geocentra.centrality import measures as M
from geocentra.graph import generators as G
from geocentra.graph.model import Graph
from geocentra.propagate import local as L
from geocentra.propagate import sweep as S
from geocentra.propagate.exact import exact_pairs
from geocentra.registry import tools  # noqa: F401
from geocentra.registry.graphs import QUERIES

NAMES = ["sum_dist", "harmonic", "coreach"]


def rows(df):
    return sorted(tuple(r) for r in df.collect())


def _arcs(kind):
    """Three components and a node or two; ids against the arcs, or in no order, or with a cycle."""
    draw = np.random.default_rng(7)
    a = draw.integers(0, 120, 400)
    arcs = {(int(x), int(x + y)) for x, y in zip(a, draw.integers(1, 9, 400), strict=True)} | {(i, i + 1) for i in range(200, 260)} | {(300, 301), (300, 302), (302, 303)}
    if kind == "shuffled":
        ids = (draw.permutation(400) * 1000003).tolist()
        return [(ids[a], ids[b]) for a, b in arcs]
    return [*((b, a) if kind == "against" else (a, b) for a, b in arcs), *([(260, 200)] if kind == "cycle" else [])]


def _pairs(arcs):
    """node, source, dist by brute force."""
    onward, found = {}, [(-5, -5, 0)]
    for a, b in arcs:
        onward.setdefault(a, []).append(b)
    for source in {x for arc in arcs for x in arc}:
        dist, live = {source: 0}, [source]
        for x in live:
            for y in onward.get(x, ()):
                if y not in dist:
                    dist[y] = dist[x] + 1
                    live.append(y)
        found += [(x, source, t) for x, t in dist.items()]
    return sorted(found)


@pytest.mark.parametrize("kind, deep", [("along", 3), ("against", 3), ("shuffled", 3), ("cycle", 3), ("along", 1 << 30)])
def test_pairs_sums_and_outermost_pairs(spark, monkeypatch, kind, deep):
    monkeypatch.setattr(S, "DEEP", deep)
    monkeypatch.setattr(S, "MOST", 7)
    monkeypatch.setattr(S, "LEAST", 1)
    monkeypatch.setattr(S, "BLOCK", 5)
    arcs = spark.createDataFrame(_arcs(kind), "src long, dst long")
    ends = arcs.select(F.explode(F.array("src", "dst")).alias("id")).distinct()
    run = exact_pairs(Graph.from_arcs(arcs, ends.unionByName(spark.sql("SELECT -5L AS id"))))
    pairs = rows(run.pairs())
    assert pairs == _pairs(_arcs(kind))
    few = sorted({a for a, _ in _arcs(kind)})[::9]
    some = exact_pairs(Graph.from_arcs(arcs), spark.createDataFrame([(x,) for x in few], "id long"))
    assert rows(some.pairs()) == [r for r in pairs if r[1] in few]
    want = rows(M.ingredients(M.exact_counts(run.pairs())).select("node", *NAMES))
    got = rows(M.ingredients(run).select("node", *NAMES))
    assert [r[0] for r in got] == [r[0] for r in want] and got[0] == (-5, 0.0, 0.0, 1.0)
    assert [x for r in got for x in r] == pytest.approx([x for r in want for x in r], abs=1e-9)
    for step in (1000000, 1):
        some = rows(run.outermost(step))
        assert set(some) <= set(pairs) and len(some) <= 2 * len(want)
        best, least = {}, {}
        for node, source, dist in pairs:
            best[node] = max(best.get(node, -(1 << 60)), dist * step - source)
            least[node] = min(least.get(node, 1 << 60), dist)
        assert best == {n: max(t * step - x for m, x, t in some if m == n) for n in best}
        assert least == {n: min(t for m, _, t in some if m == n) for n in least}


def test_orders_of_too_many_rows_take_visits(spark, monkeypatch):
    path = G.path(spark, 300)
    monkeypatch.setattr(S.Order, "passed", lambda *_: 1 / 0)
    with pytest.raises(Exception, match="ZeroDivisionError"):
        exact_pairs(path).sums().collect()
    monkeypatch.setattr(S, "LEAST", S.MOST + 1)
    assert {r["node"]: r["sum_dist"] for r in exact_pairs(path).sums().collect()} == {k: k * (k + 1) / 2 for k in range(300)}


@pytest.fixture()
def chain(spark, tmp_path):
    """A line of 6,000 documents: 18 million pairs, as many distances, and rounds of a link each."""
    line = "a line of forty characters or more than that"
    spark.range(6000).select(F.col("id").alias("doc_id"), F.lit(line).alias("text")).write.parquet(f"{tmp_path}/documents.parquet")
    return str(tmp_path)


def test_bias_report_finds_distances_once_and_makes_no_row_of_them(spark, monkeypatch, chain):
    visits, used = L.dealt, []
    monkeypatch.setattr(L, "dealt", lambda *a, **k: used.append(a[4]) or visits(*a, **k))
    got = {r["measure"]: r for r in QUERIES["bias_report_g10"](spark, chain).collect()}
    assert used == [L.SUMS]
    # Node k has the distances 1 to k: closeness is 2 / (k (k + 1)), and lin 2 (k + 1) / k.
    assert got["harmonic"]["low_share"] == 0 and got["closeness"]["low_share"] == got["lin"]["low_share"] == 1
    assert got["closeness"]["correlation"] < 0 < got["harmonic"]["correlation"]


def test_bias_report_reads_what_was_found(spark, chain):
    measures = M.centralities(exact_pairs(G.path(spark, 20)))
    plan = A.bias_report(measures, ["lin"])._jdf.queryExecution().toString()
    assert "FlatMapGroupsInArrow" not in plan


def test_farthest_source_of_a_long_line(spark, chain):
    plan = QUERIES["farthest_source"](spark, chain)
    assert plan.select("node", "farthest", "sane", "nearest").where("farthest <> 0 or not sane or nearest <> 0").count() == 0
    assert plan.count() == 6000
