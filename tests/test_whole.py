"""Queries that leave no node, line or pair out, against brute force."""

from geocentra.registry import tools
from geocentra.registry.graphs import QUERIES

SF = "/root/testdata/sf0.01"


def test_dominated_over_all_nodes(spark):
    measures = tools._measures(spark, SF).collect()
    rows = [(r["node"], round(r["closeness"], 9), r["coreach"]) for r in measures]
    want = {n: k for n, c, r in rows if (k := sum(c2 > c and r2 > r for _, c2, r2 in rows))}
    assert {r["node"]: r["better"] for r in QUERIES["dominated_nodes"](spark, SF).collect()} == want
    assert any(n >= 20000 for n in want)


def test_snapshots_follow_all_events_of_a_day(spark):
    days = {}
    for r in spark.read.parquet(f"{SF}/events.parquet").selectExpr("datediff(ts, DATE '1970-01-01') AS day", "user_id", "event_type").orderBy("ts", "event_id").collect():
        days.setdefault(r["day"], []).append((r["user_id"], r["event_type"]))
    want = {(day, u) for day, users in days.items() for a, b in zip(users, users[1:], strict=False) if a[0] != b[0] for u in (a[0], b[0])}
    assert {(r["day"], r["node"]) for r in QUERIES["snapshot_centrality"](spark, SF).collect()} == want
    assert len({kind for users in days.values() for _, kind in users}) > 1
