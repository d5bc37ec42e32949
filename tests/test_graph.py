import math

import pytest
from pyspark.sql import functions as F

from geocentra.accuracy import errors as A
from geocentra.accuracy import theory
from geocentra.centrality import measures as M
from geocentra.errors import GraphError, ParameterError, WeightError
from geocentra.graph import generators as G
from geocentra.graph import views
from geocentra.graph.components import giant_share, strong_components, weak_components
from geocentra.graph.model import Graph, degrees, graph_stats, scale_weights
from geocentra.propagate.balls import ball_sketches, pattern_balls
from geocentra.propagate.exact import ads_estimate, all_distances_sketch, exact_pairs
from geocentra.propagate import packed as P
from geocentra.propagate.packed import packed_balls, packed_patterns
from geocentra.sketch.packed import pack_registers, unpack_registers
from geocentra.sketch.registers import alpha, hll_count, log2_registers, md5_bits, register_bits, register_of

SF = "/root/testdata/sf0.01"


def arcs(spark, *pairs):
    return spark.createDataFrame([tuple(p) for p in pairs], "src long, dst long")


@pytest.fixture(scope="module")
def tail(spark):
    """A cycle a b c with a tail to d, a further source e, and an isolated f; a..f are 0..5."""
    nodes = spark.createDataFrame([(0, 2), (1, 1), (2, 3), (3, 1), (4, 4), (5, 1)], "id long, weight int")
    return Graph.from_arcs(arcs(spark, (0, 1), (1, 2), (2, 0), (2, 3), (4, 3)), nodes)


def exact(graph, weighted=False, **discounts):
    counts = M.exact_counts(exact_pairs(graph).pairs(), graph.vertices if weighted else None)
    return {r["node"]: r for r in M.centralities(counts, discounts or None).collect()}


def test_known_answers(tail):
    got = exact(tail, quadratic=M.quadratic, constant=M.constant)
    for node in (0, 1, 2):
        r = got[node]
        assert (r["coreach"], r["sum_dist"], r["lin"], r["harmonic"], r["quadratic"], r["constant"]) == (3, 3, 3, 1.5, 1.25, 2)
        assert r["closeness"] == pytest.approx(1 / 3)
    d = got[3]
    assert (d["coreach"], d["sum_dist"], d["constant"]) == (5, 7, 4)
    assert [d["closeness"], d["lin"], d["harmonic"], d["quadratic"]] == pytest.approx([1 / 7, 25 / 7, 17 / 6, 85 / 36])
    for node in (4, 5):
        r = got[node]
        assert (r["coreach"], r["sum_dist"], r["closeness"], r["lin"], r["harmonic"]) == (1, 0, 0, 1, 0)
    counts = M.exact_counts(exact_pairs(tail).pairs())
    assert all(r["closeness_strict"] == 0 for r in M.strict_closeness_exact(counts, 6).collect())


def test_weights(tail, spark):
    d = exact(tail, weighted=True)[3]
    assert (d["coreach"], d["sum_dist"]) == (11, 15)
    assert [d["lin"], d["harmonic"]] == pytest.approx([121 / 15, 49 / 6])
    bad = Graph(spark.createDataFrame([(0, 0)], "id long, weight int"), tail.arcs)
    with pytest.raises(WeightError):
        ball_sketches(bad, weighted=True)
    assert [r["weight"] for r in scale_weights(spark.createDataFrame([(0.1,), (1.0,)], "x double"), "x", 10).orderBy("x").collect()] == [1, 10]


def test_direction(tail):
    out = {r["node"]: r["coreach"] for r in M.centralities(M.exact_counts(exact_pairs(tail, direction="out").pairs())).collect()}
    back = {r["node"]: r["coreach"] for r in M.centralities(M.exact_counts(exact_pairs(tail.transpose()).pairs())).collect()}
    assert out == back and out[4] == 2 and out[3] == 1


@pytest.mark.parametrize("n", [2, 5])
def test_generators(spark, n):
    h = sum(1 / k for k in range(1, n))
    for r in exact(G.cycle(spark, n)).values():
        assert r["sum_dist"] == n * (n - 1) / 2 and r["harmonic"] == pytest.approx(h)
    for r in exact(G.complete(spark, n)).values():
        assert r["harmonic"] == n - 1 and r["closeness"] == pytest.approx(1 / (n - 1))
    assert exact(G.star(spark, n, inward=True))[0]["lin"] == pytest.approx(n * n / (n - 1))
    assert exact(G.star(spark, n))[1]["harmonic"] == 1
    assert exact(G.path(spark, n))[n - 1]["sum_dist"] == n * (n - 1) / 2
    assert G.grid(spark, 3, n).arcs.count() == 3 * (n - 1) + 2 * n


def test_kronecker_does_not_depend_on_partitions(spark):
    g = G.kronecker(spark, [[0.6, 0.2], [0.15, 0.05]], 6, 300, seed=2)
    a = sorted(map(tuple, g.arcs.collect()))
    assert a and all(0 <= s < 64 and 0 <= d < 64 and s != d for s, d in a)
    spark.conf.set("spark.sql.shuffle.partitions", "7")
    assert sorted(map(tuple, G.kronecker(spark, [[0.6, 0.2], [0.15, 0.05]], 6, 300, seed=2).arcs.collect())) == a
    spark.conf.set("spark.sql.shuffle.partitions", "4")
    with pytest.raises(ParameterError):
        G.kronecker(spark, [[1.0]], 2, 10)


def test_degenerate_graphs(spark):
    empty = Graph.from_arcs(arcs(spark).limit(0) if False else spark.createDataFrame([], "src long, dst long"))
    assert ball_sketches(empty).profile().count() == 0 and exact_pairs(empty).pairs().count() == 0
    loops = Graph.from_arcs(arcs(spark, (1, 1), (1, 2), (1, 2)), spark.createDataFrame([(1,), (2,), (3,)], "id long"))
    assert loops.arcs.count() == 1
    got = {r["node"]: r["size"] for r in ball_sketches(loops).profile().where("t = 0").collect()}
    assert got == pytest.approx({k: 64 * math.log(64 / 63) for k in (1, 2, 3)})
    with pytest.raises(GraphError, match="vertices"):
        Graph.from_arcs(arcs(spark, (1, 9)), spark.createDataFrame([(1,)], "id long"))
    assert Graph.from_arcs(arcs(spark, (1, 9)), spark.createDataFrame([(1,)], "id long"), dangling="drop").arcs.count() == 0
    with pytest.raises(GraphError, match="src"):
        Graph.from_arcs(spark.createDataFrame([("a", 1)], "src string, dst long"))


def test_wrong_parameters(tail):
    for p in (8, 63, 100):
        with pytest.raises(ParameterError):
            log2_registers(p)
    for kw in ({"direction": "up"}, {"propagation": "half"}, {"runs": 0}, {"hash": "crc"}):
        with pytest.raises(ParameterError):
            ball_sketches(tail, **kw)
    for kw in ({"propagation": "half"}, {"p": 63}, {"direction": "up"}):
        with pytest.raises(ParameterError):
            packed_balls(tail, **kw)


def test_portable_hash(spark):
    got = [r["h"] for r in spark.range(3).select(md5_bits(F.concat_ws(":", F.lit(7), F.col("id").cast("string"))).alias("h")).collect()]
    assert got == [995994322303770437, 494670966109493051, 436388637374705511]


def test_fast_hash_registers(spark):
    reg, rho = register_of(F.col("id").cast("string"), 64, "xx64")
    r = spark.range(20000).select(reg.alias("reg"), rho.alias("rho")).agg(F.min("reg"), F.max("reg"), F.min("rho"), F.avg("rho")).first()
    assert (r[0], r[1], r[2]) == (0, 63, 1) and 1.9 < r[3] < 2.1


def test_delta_full_packed_agree(spark):
    graph = views.graph(spark, "/root/testdata/sf0.001", "g2")
    delta, full = ball_sketches(graph), ball_sketches(graph, propagation="full")
    rows = sorted(map(tuple, delta.registers().select("node", "reg", "rho").collect()))
    assert rows == sorted(map(tuple, full.registers().select("node", "reg", "rho").collect()))
    packed = packed_balls(graph)
    assert rows == sorted(map(tuple, packed.registers().select("node", "reg", "rho").collect()))
    assert sorted(map(tuple, packed.profile().collect())) == sorted(map(tuple, delta.profile().collect()))
    assert packed_balls(graph, p=16, max_iter=1).truncated
    whole = packed_balls(graph, propagation="full", gains={})
    by_node = lambda df: {(r["node"], r["run"]): pytest.approx(tuple(r[n] for n in ("coreach", "sum_dist", "harmonic"))) for r in df.collect()}
    assert {k: tuple(v.expected) for k, v in by_node(whole.sums()).items()} == by_node(M.ingredients(M.sketch_counts(delta)))
    again = unpack_registers(pack_registers(delta.registers().drop("run"), 64), 64)
    assert rows == sorted(map(tuple, again.collect()))
    runs = ball_sketches(graph, runs=2).registers().where("run = 0").select("node", "reg", "rho")
    assert rows == sorted(map(tuple, runs.collect()))


def test_only_stabilisation_is_right(spark):
    """A dense core feeds a long path: cut short, the path's far end sees nothing of the core."""
    core = G.complete(spark, 40).arcs
    line = arcs(spark, *[(39 + k, 40 + k) for k in range(12)])
    graph = Graph.from_arcs(core.unionByName(line))
    cut, whole = ball_sketches(graph, max_iter=4), ball_sketches(graph)
    assert cut.truncated and not whole.truncated
    last = lambda run: run.profile().where("node = 51").agg(F.max("size")).first()[0]
    assert last(cut) < 10 < last(whole)
    assert whole.rounds.last == 13


def test_golden_totals(spark):
    exact_run = exact_pairs(views.graph(spark, SF, "g9")).pairs()
    r = M.centralities(M.exact_counts(exact_run)).agg(F.sum("sum_dist"), F.sum("harmonic"), F.sum("coreach"), F.sum("lin")).first()
    assert tuple(r) == pytest.approx((3431, 757.714218, 1886, 1384.828571))
    run = ball_sketches(views.graph(spark, SF, "g9"))
    assert run.profile().count() == 1854 and run.rounds.last == 7
    assert tuple(run.registers().agg(F.count("*"), F.sum("rho")).first()) == (1818, 3538)
    sums = M.centralities(M.sketch_counts(run)).agg(F.sum("coreach"), F.sum("harmonic"), F.sum("sum_dist")).first()
    assert tuple(sums) == pytest.approx((1884.7196, 756.4784, 3404.9545), rel=1e-6)


def test_closed_forms_of_turns(spark):
    rows = M.centralities(M.exact_counts(exact_pairs(views.graph(spark, "/root/testdata/sf0.001", "g9")).pairs())).collect()
    for r in rows:
        k = r["node"] % 1000
        assert r["coreach"] == k + 1 and r["sum_dist"] == k * (k + 1) / 2
        assert r["lin"] == pytest.approx(2 * (k + 1) / k if k else 1)


def test_accuracy_of_many_runs(spark):
    graph = G.cycle(spark, 60).symmetrise()
    run = ball_sketches(graph, p=64, runs=12)
    counts = M.sketch_counts(run)
    mean = M.average_runs(M.centralities(counts), ["harmonic", "coreach"]).agg(F.avg("harmonic_mean"), F.avg("coreach_mean")).first()
    truth = exact(graph)[0]
    limit = 3 * theory.theoretical_rsd(64, 12)
    assert abs(mean[0] / truth["harmonic"] - 1) < limit and abs(mean[1] / truth["coreach"] - 1) < limit
    # One strongly connected component: within a run all nodes share one counter.
    spread = M.centralities(counts).groupBy("run").agg((F.max("coreach") - F.min("coreach")).alias("d"))
    assert all(abs(r["d"]) < 1e-9 for r in spread.collect())
    strict = M.strict_closeness_sketch(run).where("closeness_strict = 0").count()
    assert strict == 0


def test_discounts(tail, spark):
    counts = M.exact_counts(exact_pairs(tail).pairs())
    by_rule = {r["node"]: r["gain"] for r in M.discounted(counts, M.quadratic).collect()}
    table = spark.createDataFrame([(1, 1.0), (2, 0.25), (3, 1 / 9)], "t int, f double")
    assert {r["node"]: r["gain"] for r in M.discounted_by_table(counts, table).collect()} == pytest.approx(by_rule)
    with pytest.raises(ParameterError, match="rises"):
        M.discounted_by_table(counts, spark.createDataFrame([(1, 1.0), (2, 2.0)], "t int, f double"))
    constant = {r["node"]: r["gain"] for r in M.discounted(counts, M.constant).collect()}
    assert constant == {r["node"]: r["coreach"] - 1 for r in M.centralities(counts).collect()}


def test_bit_patterns(spark):
    graph = G.path(spark, 6)
    sizes = {r["node"]: r["size"] for r in pattern_balls(graph, patterns=64).profile().groupBy("node").agg(F.max_by("size", "t").alias("size")).collect()}
    assert sizes[5] > sizes[0] and 2.5 < sizes[5] < 12
    full = pattern_balls(graph, patterns=8).rounds.final()
    delta = pattern_balls(graph, patterns=8, propagation="delta").rounds.final()
    assert full.exceptAll(delta).count() == 0
    assert pattern_balls(graph, patterns=16, averaging="stochastic").profile().count() > 0


def test_all_distances_sketches_are_exact_when_large(tail):
    got = {r["node"]: r["value"] for r in ads_estimate(all_distances_sketch(tail, k=50)).collect()}
    assert got == pytest.approx({n: r["harmonic"] for n, r in exact(tail).items()})


def test_components(tail, spark):
    assert {r["node"]: r["component"] for r in weak_components(tail).collect()} == {0: 0, 1: 0, 2: 0, 3: 0, 4: 0, 5: 5}
    strong = strong_components(tail)
    assert {r["node"]: r["component"] for r in strong.collect()} == {0: 0, 1: 0, 2: 0, 3: 3, 4: 4, 5: 5}
    assert giant_share(strong).first()["share"] == 0.5
    assert [r["n_in"] for r in degrees(tail).orderBy("node").collect()] == [1, 1, 1, 2, 0, 0]
    assert graph_stats(tail).first()["arcs"] == 5


def test_theory_and_footprint():
    assert theory.theoretical_rsd(64) == pytest.approx(0.1318, abs=1e-4)
    assert theory.theoretical_rsd(4096) == pytest.approx(0.0162, abs=1e-4)
    for p, gib in ((16, 73), (64, 234), (256, 875)):
        assert theory.footprint(4_780_950_903, p) / 2**30 == pytest.approx(gib, rel=0.02)
    assert register_bits(2**64) == 6 and alpha(128) == pytest.approx(0.7213 / (1 + 1.079 / 128))
    assert theory.throughput(2, 1_000_000, 4) == 8000


def test_counting_distinct(spark):
    df = spark.range(5000).select((F.col("id") % 2).alias("k"), (F.col("id") % 1000).alias("item"))
    for r in hll_count(df, "item", ["k"], p=1024).collect():
        assert abs(r["size"] / 500 - 1) < 0.15


def test_derived(tail):
    counts = M.exact_counts(exact_pairs(tail).pairs())
    assert [r["pairs"] for r in M.neighbourhood_function(counts).orderBy("t").collect()] == [6, 11, 15, 16]
    assert sum(r["share"] for r in M.distance_distribution(counts).collect()) == pytest.approx(1)
    s = M.distance_summary(counts, 6).first()
    assert s["average_distance"] == pytest.approx(16 / 10) and s["harmonic_diameter"] == pytest.approx(30 / (4.5 + 17 / 6))
    assert {r["node"]: r["eccentricity"] for r in M.eccentricity(counts).collect()}[3] == 3
    radius = {r["node"]: r["radius"] for r in M.effective_radius(counts).collect()}
    assert radius[4] == 0 and radius[3] == pytest.approx(2.5)
    top = M.ranking(M.centralities(counts), "harmonic", 1).collect()
    assert (top[0]["node"], top[0]["place"]) == (3, 1)


def test_plans(spark):
    plan = views.sparse_part_succession(spark, SF)._jdf.queryExecution().toString()
    assert "EqualTo(l_returnflag,R)" in plan and "l_comment" not in plan
    chain = views.turn_chain(spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "SinglePartition" not in chain


@pytest.mark.parametrize("bits", [False, True])
def test_packed_blocks_hubs_and_tails(spark, monkeypatch, bits):
    """Many small blocks, spread senders, and rounds that look up which blocks they reach give what rows give."""
    graph = views.graph(spark, "/root/testdata/sf0.001", "g1")
    hub = graph.arcs.unionByName(spark.range(300).select(F.lit(7).cast("long").alias("src"), (F.col("id") + 1000).alias("dst"))).unionByName(spark.range(40).select((F.col("id") + 1299).alias("src"), (F.col("id") + 1300).alias("dst")))
    graph = Graph.from_arcs(hub)
    rows = (pattern_balls(graph, 8) if bits else ball_sketches(graph, p=16, runs=2)).rounds.final()
    for name, value in {"HUB_ARCS": 20, "SMALL_ARCS": 50, "TAIL_BLOCKS": 2, "TAIL_SHARE": 0.5}.items():
        monkeypatch.setattr(P, name, value)
    monkeypatch.setattr(P.K, "CHUNK_ARCS", 100)
    run = packed_patterns(graph, 8) if bits else packed_balls(graph, p=16, runs=2)
    want = {(r["node"], r["run"], r["item"], r["value"]) for r in rows.collect()}
    assert {(r["node"], r["run"], r["item"], r["value"]) for r in run.final().collect()} == want
    assert run.sent_bytes[1] > 0 and run.last > 20


def test_spread_senders_of_the_row_layout(spark, monkeypatch):
    from geocentra.propagate import fixpoint

    graph = G.star(spark, 60)
    want = sorted(map(tuple, exact_pairs(graph).pairs().collect()))
    monkeypatch.setattr(fixpoint, "HUB_ARCS", 10)
    assert sorted(map(tuple, exact_pairs(graph).pairs().collect())) == want


def test_a_hub_of_a_million_arcs_is_spread(spark):
    arcs_of = spark.range(1_300_000).select(F.lit(-1).cast("long").alias("src"), F.col("id").alias("dst"))
    run = packed_balls(Graph(arcs_of.select(F.col("dst").alias("id"), F.lit(1).alias("weight")).unionByName(spark.sql("SELECT -1L AS id, 1 AS weight")), arcs_of), p=16, hash="xx64", gains={})
    assert run.last == 1 and run.changed[1] > 1_200_000


def test_strong_components_of_a_giant(spark):
    """Two cycles, an arc between them, and tails."""
    g = Graph.from_arcs(arcs(spark, (1, 2), (2, 3), (3, 1), (3, 4), (4, 5), (5, 4), (5, 9), (8, 1)))
    assert {r["node"]: r["component"] for r in strong_components(g).collect()} == {1: 1, 2: 1, 3: 1, 4: 4, 5: 4, 8: 8, 9: 9}


def test_ranks_without_a_global_window(spark):
    rows = spark.createDataFrame([(i, float(i % 7), float(i * 31 % 11)) for i in range(100)], "node long, a double, b double")
    got = M.ranking(rows, "a").collect()
    want = sorted(((r["a"], r["node"]) for r in rows.collect()), key=lambda x: (-x[0], x[1]))
    assert [(r["value"], r["node"]) for r in sorted(got, key=lambda r: r["place"])] == want
    assert sorted(r["place"] for r in got) == list(range(1, 101))
    a, b = ([r[c] for r in rows.collect()] for c in "ab")
    sign = lambda x: (x > 0) - (x < 0)
    tau = sum(sign(a[i] - a[j]) * sign(b[i] - b[j]) for i in range(100) for j in range(i)) / (100 * 99 / 2)
    assert A.kendall(rows, "a", "b").first()["tau"] == pytest.approx(tau)
    rank = lambda v, x: sum(y < x for y in v) + (sum(y == x for y in v) + 1) / 2
    import numpy as np

    assert A.spearman(rows, "a", "b").first()["spearman"] == pytest.approx(np.corrcoef([rank(a, x) for x in a], [rank(b, x) for x in b])[0, 1])


def test_steps_make_the_same_succession(spark):
    from geocentra.operators.ordered import succession, succession_in_steps

    rows = spark.createDataFrame([(i % 3, i * 37 % 101, i) for i in range(100)], "g int, at int, node int")
    want = sorted(map(tuple, succession(rows, [F.col("g")], ["at"], "node").collect()))
    assert sorted(map(tuple, succession_in_steps(rows, F.col("g"), F.floor(F.col("at") / 10), ["at"], "node").collect())) == want


def test_turns_have_ids_of_their_own(spark):
    turns = [0, 999, 1000, 1001, views.MAX_TURNS - 1]
    rows = spark.createDataFrame([(c, t) for c in (0, 1, 2) for t in turns], "c long, t long").select("t", views.turn_node(F.col("c"), F.col("t")).alias("n")).select("t", "n", views.turn_of(F.col("n")).alias("back")).collect()
    assert len({r["n"] for r in rows}) == len(rows) and all(r["t"] == r["back"] for r in rows)
    with pytest.raises(Exception, match="beyond"):
        spark.range(1).select(views.turn_node(F.lit(1).cast("long"), F.lit(views.MAX_TURNS).cast("long")).alias("n")).collect()


def test_nearest_vectors_in_blocks(spark, monkeypatch):
    want = sorted(map(tuple, views.vector_knn(spark, "/root/testdata/sf0.001").collect()))
    monkeypatch.setattr(views, "KNN_BLOCK", 60)
    assert sorted(map(tuple, views.vector_knn(spark, "/root/testdata/sf0.001").collect())) == want


def test_late_rows_are_dropped(spark, tmp_path):
    """A file whose events are older than the watermark adds nothing; a file within it does."""
    from geocentra.streaming import ingest

    events = spark.read.parquet("/root/testdata/sf0.001/events.parquet").select("event_id", "ts", "user_id", "event_type", "value", "props")
    days = [events.where(F.to_date("ts") == d).coalesce(1) for d in ("2024-01-10", "2024-01-12")]
    days.append(days[0])
    out = str(tmp_path / "out")
    for k, day in enumerate(days):
        day.write.mode("append").parquet(str(tmp_path / "in"))
        stream = spark.readStream.schema(ingest.EVENTS).parquet(str(tmp_path / "in"))
        counted = ingest.counts_by_window(stream, "1 day", late="1 hour")
        counted.writeStream.option("checkpointLocation", str(tmp_path / "state")).outputMode("append").format("parquet").option("path", out).trigger(availableNow=True).start().awaitTermination()
    got = spark.read.parquet(out).agg(F.sum("n")).first()[0]
    assert got == days[0].count()
