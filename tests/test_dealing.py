"""Rows come to a block's function by kind, whether or not the session keeps the tables' dealing."""

from collections.abc import Iterator

import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from geocentra.propagate import blocks as K
from geocentra.propagate.packed import _Tables

KINDS = "block int, place int, kind int"


def reader():
    def kinds(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows = [r for b in batches for r in b.to_pylist()]
        yield pa.RecordBatch.from_pylist([{"block": r["block"], "place": i, "kind": r["kind"]} for i, r in enumerate(rows)], pa.schema([("block", pa.int32()), ("place", pa.int32()), ("kind", pa.int32())]))

    return kinds


@pytest.mark.parametrize("key, value", [("spark.sql.unionOutputPartitioning", "true"), ("spark.sql.unionOutputPartitioning", "false"), ("spark.sql.sources.bucketing.enabled", "false")])
def test_rows_come_by_kind(spark, key, value):
    tables = _Tables(spark, f"dealing-{key.count('.')}-{value}-{key[-7:]}".replace(".", "-"))
    tables.blocks = 3
    tables.settings({"spark.sql.shuffle.partitions": "3", key: value})
    for name, kind in (("late", K.LATE), ("early", 0), ("between", 7)):
        tables.keep(tables.dealt(tables.work.range(40).select((F.col("id") % 5).cast("int").alias("block"), F.lit(kind).alias("kind"))), name)
    got = tables.by_block([tables.read(n) for n in ("late", "early", "between")], reader(), KINDS).collect()
    assert len(got) == 120
    for block in range(5):
        mine = [r["kind"] for r in sorted((r for r in got if r["block"] == block), key=lambda r: r["place"])]
        assert mine == sorted(mine) and len(mine) == 24


def test_a_late_counter_is_an_error():
    rows = [{"block": 1, "kind": K.LATE}, {"block": 1, "kind": 0}]
    with pytest.raises(RuntimeError, match="comes after"):
        list(K.in_order(rows))
