"""Headline timings: one JSON line. BENCH_SF_DIR and BENCH_CPUS set the tables and the cores; BENCH_ARCS the large graph."""

from __future__ import annotations

import json
import math
import os
import sys
import tempfile
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import SparkSession  # noqa: E402

from geocentra.accuracy.theory import throughput  # noqa: E402
from geocentra.centrality import measures as M  # noqa: E402
from geocentra.graph import views  # noqa: E402
from geocentra.graph.generators import kronecker  # noqa: E402
from geocentra.graph.model import Graph  # noqa: E402
from geocentra.plans.checkpoint import cut  # noqa: E402
from geocentra.propagate.balls import ball_sketches  # noqa: E402
from geocentra.propagate.exact import exact_pairs  # noqa: E402
from geocentra.propagate.packed import packed_balls, packed_patterns  # noqa: E402

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = int(os.environ.get("BENCH_CPUS", "8"))
ARCS = int(os.environ.get("BENCH_ARCS", "44000000"))
#: Nearly all pairs of nodes are within two arcs of each other.
DENSE = [[0.9, 0.7, 0.5], [0.7, 0.5, 0.5], [0.5, 0.5, 0.6]]

TIMES: dict[str, float] = {}
DETAILS: dict[str, dict] = {}


def started(cpus: int) -> SparkSession:
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.driver.memory", "12g")
        .config("spark.sql.shuffle.partitions", str(2 * cpus))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.sql.warehouse.dir", tempfile.mkdtemp(prefix="bench-warehouse-"))
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="bench-"))
    return spark


def kept(graph: Graph) -> Graph:
    return Graph(cut(graph.vertices), cut(graph.arcs))


def measured(name: str, graph: Graph, make, cpus: int = CPUS) -> None:
    """Time to all measures of every node, and per round."""
    arcs = graph.arcs.count()
    began = time.time()
    run = make(graph)
    measures = M.centralities_of_sums(run.sums()) if hasattr(run, "sums") else M.centralities(M.sketch_counts(run))
    measures.write.format("noop").mode("overwrite").save()
    TIMES[name] = round(time.time() - began, 2)
    rounds = run.rounds.seconds[1:]
    mean = sum(rounds) / max(1, len(rounds))
    DETAILS[name] = {"arcs": arcs, "rounds": len(rounds), "sec_before_rounds": round(run.rounds.seconds[0], 2), "sec_per_round": round(mean, 3), "slowest_round": round(max(rounds, default=0), 3), "ns_per_arc_core": round(throughput(mean, max(1, arcs), cpus))}
    if hasattr(run, "sent_bytes"):
        DETAILS[name]["bytes_sent_first_round"] = run.sent_bytes[1] if len(run.sent_bytes) > 1 else 0


def sums(p: int):
    return lambda g: packed_balls(g, p=p, gains={})


def per_round(name: str) -> float:
    return DETAILS[name]["sec_per_round"]


def main() -> None:
    spark = started(CPUS)
    measured("warm_up", views.graph(spark, SF, "g5"), sums(64))
    TIMES.pop("warm_up"), DETAILS.pop("warm_up")
    parts = kept(views.graph(spark, SF, "g1"))
    for p in (16, 64, 256):
        measured(f"balls_parts_p{p}", parts, sums(p))
    measured("balls_parts_rows_p16", parts, lambda g: ball_sketches(g, p=16))
    measured("balls_customer_supplier_p64", kept(views.graph(spark, SF, "g3").symmetrise()), sums(64))
    sparse = kept(views.graph(spark, SF, "g2"))
    measured("balls_sparse_parts_p64", sparse, sums(64))
    # A long tail of rounds in which little changes.
    tail = kept(sparse.symmetrise())
    for p in (16, 64, 256):
        measured(f"balls_tail_p{p}", tail, sums(p))
    # The dense graphs of three sizes: counters by delta rounds, bit patterns and counters by whole rounds.
    for k, arcs in ((5, 30_000), (7, 1_000_000), (9, ARCS)):
        dense = kept(kronecker(spark, DENSE, k, arcs, seed=3))
        measured(f"balls_dense{k}_p64", dense, sums(64))
        measured(f"patterns_dense{k}_32", dense, lambda g: packed_patterns(g, 32, gains={}))
    measured("full_dense7_p64", kept(kronecker(spark, DENSE, 7, 1_000_000, seed=3)), lambda g: packed_balls(g, p=64, propagation="full", gains={}))
    hand = kept(views.graph(spark, SF, "g4"))
    measured("balls_handoff_p64", hand, sums(64))
    began = time.time()
    M.centralities(M.exact_counts(exact_pairs(hand).pairs())).write.format("noop").mode("overwrite").save()
    TIMES["exact_handoff"] = round(time.time() - began, 2)
    spark.stop()
    for cpus in sorted({1, 2, 4} - {CPUS}):
        small = started(cpus)
        measured(f"cores{cpus}_parts_p256", kept(views.graph(small, SF, "g1")), sums(256), cpus)
        small.stop()
    ratios = {
        "p16_to_p256_parts": per_round("balls_parts_p256") / per_round("balls_parts_p16"),
        "p16_to_p256_tail": per_round("balls_tail_p256") / per_round("balls_tail_p16"),
        **{f"patterns_to_balls_dense{k}": per_round(f"patterns_dense{k}_32") / per_round(f"balls_dense{k}_p64") for k in (5, 7, 9)},
        "exact_to_balls_handoff": TIMES["exact_handoff"] / TIMES["balls_handoff_p64"],
    }
    # Time of a round as a power of the number of registers.
    points = [(math.log(p), math.log(per_round(f"balls_parts_p{p}"))) for p in (16, 64, 256)]
    mean = [sum(x) / 3 for x in zip(*points, strict=True)]
    ratios["power_of_p"] = sum((a - mean[0]) * (b - mean[1]) for a, b in points) / sum((a - mean[0]) ** 2 for a, _ in points)
    print(json.dumps({"metric": "total time of the headline centrality runs", "value": round(sum(TIMES.values()), 2), "unit": "sec", "queries": TIMES, "sf": SF, "cpus": CPUS, "ratios": {k: round(v, 3) for k, v in ratios.items()}, "details": DETAILS}))


if __name__ == "__main__":
    main()
