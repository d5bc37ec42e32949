"""Balls by Spark's own sketches."""

import pytest
from pyspark.sql import functions as F

from geocentra.errors import ParameterError
from geocentra.graph import generators as G
from geocentra.sketch.native import native_balls


def test_few_jobs_and_no_result_by_chance(spark):
    graph = G.path(spark, 40)
    spark.sparkContext.setJobGroup("native path", "native path")
    try:
        found = {n: sorted(map(tuple, native_balls(graph).collect())) for n in (3, 4) if spark.conf.set("spark.sql.shuffle.partitions", str(n)) is None}
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
        spark.conf.set("spark.sql.shuffle.partitions", "4")
    assert found[3] == found[4]
    # Up to seven nodes are a list, whose size is exact.
    assert {(n, t): size for n, t, size in found[4] if t < 7} == {(n, t): t + 1 for n in range(40) for t in range(min(n + 1, 7))}
    assert max(t for _, t, _ in found[4]) > 30
    # Two runs of about 40 rounds each.
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("native path")) < 160


def test_a_limit_that_cuts_is_an_error(spark):
    graph = G.path(spark, 6)
    assert native_balls(graph, max_iter=5).agg(F.max("t")).first()[0] == 5
    with pytest.raises(ParameterError):
        native_balls(graph, max_iter=4)
