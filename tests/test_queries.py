"""Registered queries against their SQL on the smallest tables."""

import duckdb
import pytest

from geocentra.registry import tools  # noqa: F401
from geocentra.registry.graphs import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"
TABLES = ["region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations"]
SLOW = {"delta_equals_full_g2", "accuracy_g12", "concentration_g12"}
SOME = sorted(n for n in ORACLES if n not in SLOW)[::3] + ["sketch_centralities_g2", "exact_centralities_g10", "stream_sessions"]


def plain(rows):
    return sorted(tuple("null" if v is None or v != v else f"{v:.6g}" if isinstance(v, float) else str(v) for v in r) for r in rows)


@pytest.fixture(scope="module")
def con():
    c = duckdb.connect()
    c.execute("set timezone = 'UTC'")
    for t in TABLES:
        c.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return c


@pytest.mark.parametrize("name", sorted(set(SOME)))
def test_query(spark, con, name):
    got = QUERIES[name](spark, SF)
    want = con.execute(ORACLES[name]).df()
    names = sorted(got.columns)
    assert sorted(want.columns) == names
    assert plain(tuple(r[n] for n in names) for r in got.collect()) == plain(tuple(None if v is None or v != v else v for v in r) for r in want[names].astype(object).itertuples(index=False, name=None))


def test_entry_guards_only_the_subpackage():
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert len(QUERIES) > 130
