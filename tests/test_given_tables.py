"""Queries that made their data up read a given table, with the results of their SQL."""

import duckdb
import pytest

from geocentra.registry import tools  # noqa: F401
from geocentra.registry.graphs import ORACLES, QUERIES

SF = "/root/testdata/sf0.001"
READ = {"discount_table": "lineitem", "footprint_table": "lineitem", "kronecker_source": "events", "path_source": "orders", "register_sizing": "lineitem", "theory_table": "lineitem"}


@pytest.mark.parametrize("name", sorted(READ))
def test_reads_a_given_table(spark, name):
    got = QUERIES[name](spark, SF)
    assert any(f.endswith(f"{READ[name]}.parquet") for f in got.inputFiles())
    con = duckdb.connect()
    con.execute(f"create view {READ[name]} as select * from '{SF}/{READ[name]}.parquet'")
    names = sorted(got.columns)
    want = con.execute(f"SELECT {', '.join(names)} FROM ({ORACLES[name]})").fetchall()
    plain = lambda rows: sorted(tuple(f"{v:.9g}" if isinstance(v, float) else str(v) for v in r) for r in rows)
    assert want and plain(got.select(*names).collect()) == plain(want)
