"""Queries of graphs, methods, measures and baselines."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geocentra.accuracy import errors as A
from geocentra.accuracy import theory
from geocentra.centrality import measures as M
from geocentra.graph import views
from geocentra.graph.components import giant_share, strong_components, weak_components
from geocentra.graph.generators import kronecker
from geocentra.graph.model import Graph, graph_stats, indegree, scale_weights
from geocentra.plans.checkpoint import cut
from geocentra.propagate.balls import ball_sketches, pattern_balls, rank_seeds
from geocentra.propagate.classes import classes_of, exact_pairs_of_classes
from geocentra.propagate.exact import ExactRun, ads_estimate, all_distances_sketch, exact_pairs, sampled_bfs
from geocentra.propagate.fixpoint import MAXIMUM, fixpoint
from geocentra.propagate.packed import packed_balls, packed_patterns
from geocentra.registry import sql as S
from geocentra.sketch.native import native_balls
from geocentra.sketch.registers import bits_of, hll_count, md5_bits, register_of, union_registers

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}
NAMES = ["coreach", "sum_dist", "closeness", "lin", "harmonic"]
EXACT_VIEWS = ["g2", "g5", "g8", "g9", "g10", "g11"]
WEIGHT_SQL = "SELECT p_partkey AS id, p_size AS weight FROM part"


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def keep(f: Query) -> Query:
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = sql
        return f

    return keep


def rounded(df: DataFrame, names: list[str], digits: int = 6) -> DataFrame:
    return df.withColumns({n: F.round(n, digits) for n in names})


def part_weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    return views.table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), F.col("p_size").alias("weight"))


def exact_of(spark: SparkSession, sf_dir: str, g: str):
    """Exact pairs and counts of a view: by classes of equal nodes where its nodes have keys."""
    return exact_pairs_of_classes(classes_of(views.KEYS[g](spark, sf_dir))) if g in views.KEYS else exact_pairs(views.graph(spark, sf_dir, g))


def counts_of(spark: SparkSession, sf_dir: str, g: str, direction: str = "in", symmetric: bool = False, weighted: bool = False, as_run: bool = False) -> DataFrame | ExactRun:
    """Exact counts by distance, as rows; or as the run that has them, for measures that only add them up."""
    graph = views.graph(spark, sf_dir, g)
    run = exact_pairs(graph.symmetrise() if symmetric else graph, direction=direction)
    if as_run:
        return run
    return M.exact_counts(run.pairs(), graph.with_weights(part_weights(spark, sf_dir)).vertices) if weighted else run.counts()


def sketch_of(spark: SparkSession, sf_dir: str, g: str, **kw):
    return ball_sketches(views.graph(spark, sf_dir, g), **kw)


# --- views ---------------------------------------------------------------------------------

for _g in views.VIEWS:
    query(f"arcs_{_g}", f"SELECT src, dst FROM ({S.ARCS[_g]})")(lambda spark, d, g=_g: views.VIEWS[g](spark, d))

STATS_VIEWS = ["g1", "g2", "g3", "g4", "g5", "g6", "g7", "g8", "g9", "g10", "g11"]


@query(
    "graph_stats_all",
    " UNION ALL ".join(
        f"SELECT '{g}' AS view, nodes, arcs, round(arcs / nodes, 6) AS avg_degree, max_in, max_out FROM (SELECT (SELECT count(*) FROM (SELECT src FROM a UNION SELECT dst FROM a)) AS nodes, (SELECT count(*) FROM a) AS arcs, (SELECT max(k) FROM (SELECT count(*) AS k FROM a GROUP BY dst)) AS max_in, (SELECT max(k) FROM (SELECT count(*) AS k FROM a GROUP BY src)) AS max_out FROM (SELECT 1)) ".replace(" a)", f" ({S.ARCS[g]}) a)").replace(" a GROUP", f" ({S.ARCS[g]}) a GROUP").replace("FROM a UNION", f"FROM ({S.ARCS[g]}) a UNION")
        for g in STATS_VIEWS
    ),
)
def graph_stats_all(spark, d):
    out = None
    for g in STATS_VIEWS:
        row = graph_stats(views.graph(spark, d, g)).select(F.lit(g).alias("view"), "nodes", "arcs", F.round("avg_degree", 6).alias("avg_degree"), "max_in", "max_out")
        out = row if out is None else out.unionByName(row)
    return out


@query("weak_components_g10", f"{S.pairs('g10', symmetric=True)} SELECT node, min(source) AS component FROM reach GROUP BY node")
def weak_components_g10(spark, d):
    return weak_components(views.graph(spark, d, "g10"))


@query("strong_components_g8", f"{S.pairs('g8')} SELECT a.node, min(a.source) AS component FROM reach a JOIN reach b ON a.node = b.source AND a.source = b.node GROUP BY a.node")
def strong_components_g8(spark, d):
    return strong_components(views.graph(spark, d, "g8"))


_DRAWN = "SELECT i, level, ('0x' || substr(md5('1:' || i || ':' || level), 1, 15))::BIGINT % 1073741824 AS u FROM (SELECT event_id AS i FROM events), (SELECT unnest(range(1, 11)) AS level)"
_CELLS = f"SELECT i, level, (u >= 612032840)::INTEGER + (u >= 816043786)::INTEGER + (u >= 1020054733)::INTEGER AS c FROM ({_DRAWN})"


@query("giant_share_g8", f"{S.pairs('g8')}, parts AS (SELECT a.node, min(a.source) AS component FROM reach a JOIN reach b ON a.node = b.source AND a.source = b.node GROUP BY a.node), sizes AS (SELECT count(*) AS k FROM parts GROUP BY component) SELECT round(max(k) / sum(k), 6) AS share FROM sizes")
def giant_share_g8(spark, d):
    return rounded(giant_share(strong_components(views.graph(spark, d, "g8"))), ["share"])


query("scaled_weights", "SELECT p_partkey AS id, greatest(1, ceil(p_retailprice * 50 / (SELECT max(p_retailprice) FROM part)))::INTEGER AS weight FROM part")(
    lambda spark, d: scale_weights(views.table(spark, d, "part").select(F.col("p_partkey").alias("id"), "p_retailprice"), "p_retailprice", 50).select("id", "weight")
)
query("register_sizing", "SELECT l_returnflag, count(DISTINCT l_partkey) AS n, ceil(log2(log2(greatest(4, count(DISTINCT l_partkey)))))::INTEGER AS bits FROM lineitem GROUP BY l_returnflag")(
    lambda spark, d: views.table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("n")).withColumn("bits", bits_of(F.col("n")))
)


@query("kronecker_source", f"SELECT DISTINCT src, dst FROM (SELECT i, sum((c // 2) * (1 << (10 - level)))::BIGINT AS src, sum((c % 2) * (1 << (10 - level)))::BIGINT AS dst FROM ({_CELLS}) GROUP BY i) WHERE src <> dst")
def kronecker_source(spark, d):
    """An arc a row of events, drawn from its id."""
    numbers = views.table(spark, d, "events").select(F.col("event_id").alias("id"))
    return kronecker(spark, [[0.57, 0.19], [0.19, 0.05]], 10, seed=1, portable=True, numbers=numbers).arcs


# --- exact methods -------------------------------------------------------------------------

for _g in EXACT_VIEWS:
    query(f"exact_pairs_{_g}", f"{S.pairs(_g)} SELECT node, source, dist FROM reach")(lambda spark, d, g=_g: exact_of(spark, d, g).pairs())
    query(f"exact_centralities_{_g}", f"{S.exact_counts(_g)}, {S.MEASURES} SELECT node, {S.rounded(NAMES)} FROM measures")(
        lambda spark, d, g=_g: rounded(M.centralities(exact_of(spark, d, g).counts()).drop("run"), NAMES)
    )

for _name, _column in (("closeness_patched", "closeness"), ("lin", "lin"), ("harmonic", "harmonic"), ("coreach", "coreach")):
    query(f"{_name}_g2", f"{S.exact_counts('g2')}, {S.MEASURES} SELECT node, round({_column}, 6) AS {_column} FROM measures")(
        lambda spark, d, c=_column: rounded(M.centralities(counts_of(spark, d, "g2")).select("node", c), [c])
    )
query("harmonic_out_g2", f"{S.exact_counts('g2', 'out')}, {S.MEASURES} SELECT node, round(harmonic, 6) AS harmonic FROM measures")(
    lambda spark, d: rounded(M.centralities(counts_of(spark, d, "g2", "out")).select("node", "harmonic"), ["harmonic"])
)
query("undirected_harmonic_g10", f"{S.exact_counts('g10', symmetric=True)}, {S.MEASURES} SELECT node, round(harmonic, 6) AS harmonic, constant FROM measures")(
    lambda spark, d: rounded(M.centralities(counts_of(spark, d, "g10", symmetric=True), {"constant": M.constant}).select("node", "harmonic", "constant"), ["harmonic"])
)


for _g in ("g2", "g5", "g9", "g10"):

    @query(f"closeness_strict_{_g}", f"{S.exact_counts(_g)}, {S.MEASURES} SELECT node, round(CASE WHEN coreach >= (SELECT count(*) FROM nodes) AND sum_dist > 0 THEN 1 / sum_dist ELSE 0 END, 9) AS closeness_strict FROM measures")
    def closeness_strict(spark, d, g=_g):
        graph = views.graph(spark, d, g)
        counts = exact_pairs(graph).counts()
        return rounded(M.strict_closeness_exact(counts, graph.vertices.count()).drop("run"), ["closeness_strict"], 9)


query("indegree_g1", f"WITH {S.graph('g1')} SELECT id AS node, (SELECT count(*) FROM arcs WHERE dst = id) AS indegree FROM nodes")(lambda spark, d: indegree(views.graph(spark, d, "g1")))

for _f in ("logarithmic", "quadratic", "constant", "exponential"):
    query(f"discount_{_f}_g2", f"{S.exact_counts('g2')}, {S.MEASURES} SELECT node, round({_f}, 6) AS gain FROM measures")(
        lambda spark, d, f=_f: rounded(M.discounted(counts_of(spark, d, "g2"), M.DISCOUNTS[f]).drop("run"), ["gain"])
    )


@query("discount_table_g2", f"{S.exact_counts('g2')} SELECT node, round(coalesce(sum(n * CASE t WHEN 1 THEN 1.0 WHEN 2 THEN 0.5 WHEN 3 THEN 0.1 ELSE 0 END) FILTER (WHERE t > 0), 0), 6) AS gain FROM counts GROUP BY node")
def discount_table_g2(spark, d):
    table = spark.createDataFrame([(1, 1.0), (2, 0.5), (3, 0.1)], "t int, f double")
    return rounded(M.discounted_by_table(counts_of(spark, d, "g2"), table).drop("run"), ["gain"])


query("weighted_exact_g2", f"{S.exact_counts('g2', weights=WEIGHT_SQL)}, {S.MEASURES} SELECT node, {S.rounded(NAMES)} FROM measures")(
    lambda spark, d: rounded(M.centralities(counts_of(spark, d, "g2", weighted=True)).drop("run"), NAMES)
)
query("discounted_gain_exact_g2", f"{S.exact_counts('g2', weights=WEIGHT_SQL)}, {S.MEASURES} SELECT node, round(logarithmic, 6) AS gain FROM measures")(
    lambda spark, d: rounded(M.discounted(counts_of(spark, d, "g2", weighted=True), M.logarithmic).drop("run"), ["gain"])
)
query("neighbourhood_fn_g2", f"{S.exact_counts('g2')} SELECT t, sum(sum(n)) OVER (ORDER BY t) AS pairs FROM counts GROUP BY t")(lambda spark, d: M.neighbourhood_function(counts_of(spark, d, "g2")).drop("run"))
query("distance_distribution_g10", f"{S.exact_counts('g10')} SELECT t, round(sum(n) / (SELECT sum(n) FROM counts WHERE t > 0), 9) AS share FROM counts WHERE t > 0 GROUP BY t")(
    lambda spark, d: rounded(M.distance_distribution(counts_of(spark, d, "g10")).drop("run"), ["share"], 9)
)
query("average_distance_g5", f"{S.exact_counts('g5')} SELECT round(sum(n * t) / sum(n), 9) AS average_distance FROM counts WHERE t > 0")(
    lambda spark, d: rounded(M.distance_summary(counts_of(spark, d, "g5"), 1).select("average_distance"), ["average_distance"], 9)
)


@query("harmonic_diameter_g2", f"{S.exact_counts('g2')} SELECT round(k * (k - 1) / h, 6) AS harmonic_diameter, round(h / (k * (k - 1)), 9) AS mean_reciprocal FROM (SELECT sum(n / t) AS h, (SELECT count(*) FROM nodes) AS k FROM counts WHERE t > 0)")
def harmonic_diameter_g2(spark, d):
    graph = views.graph(spark, d, "g2")
    got = M.distance_summary(exact_pairs(graph).counts(), graph.vertices.count())
    return got.select(F.round("harmonic_diameter", 6).alias("harmonic_diameter"), F.round("mean_reciprocal", 9).alias("mean_reciprocal"))


RADIUS_SQL = "sized AS (SELECT node, t, sum(n) OVER (PARTITION BY node ORDER BY t) AS size, sum(n) OVER (PARTITION BY node) AS total FROM counts), near AS (SELECT *, lag(size) OVER (PARTITION BY node ORDER BY t) AS before FROM sized), hit AS (SELECT *, row_number() OVER (PARTITION BY node ORDER BY t) AS r FROM near WHERE size >= 0.9 * total)"
query("effective_radius_g10", f"{S.exact_counts('g10')}, {RADIUS_SQL} SELECT node, round(CASE WHEN t = 0 THEN 0 ELSE t - 1 + (0.9 * total - before) / (size - before) END, 6) AS radius FROM hit WHERE r = 1")(
    lambda spark, d: rounded(M.effective_radius(counts_of(spark, d, "g10")).drop("run"), ["radius"])
)
query("eccentricity_g10", f"{S.pairs('g10')} SELECT node, max(dist) AS eccentricity FROM reach GROUP BY node")(lambda spark, d: M.eccentricity(counts_of(spark, d, "g10")).drop("run"))


@query(
    "katz_g2",
    f"WITH RECURSIVE {S.graph('g2')}, walk(node, step, paths) AS (SELECT id, 0, 1.0::DOUBLE FROM nodes UNION ALL SELECT dst, step + 1, 0.1 * paths FROM walk JOIN arcs ON src = node WHERE step < 5) SELECT id AS node, round(coalesce((SELECT sum(paths) FROM walk w WHERE w.node = n.id AND step > 0), 0), 6) AS katz FROM nodes n",
)
def katz_g2(spark, d):
    return rounded(M.katz(views.graph(spark, d, "g2"), 0.1, 5), ["katz"])


@query(
    "sampled_bfs_g2",
    f"{S.pairs('g2')}, pivots AS (SELECT id FROM nodes ORDER BY ('0x' || substr(md5('0:' || id), 1, 15))::BIGINT, id LIMIT 50), scale AS (SELECT count(*) / 50.0 AS f FROM nodes) SELECT n.id AS node, round(coalesce(f * sum(dist), 0), 6) AS sum_dist, round(coalesce(f * sum(CASE WHEN dist > 0 THEN 1.0 / dist ELSE 0 END), 0), 6) AS harmonic, round(f * count(dist), 6) AS coreach FROM scale, nodes n LEFT JOIN (SELECT * FROM reach WHERE source IN (SELECT id FROM pivots)) r ON r.node = n.id GROUP BY n.id, f",
)
def sampled_bfs_g2(spark, d):
    return rounded(sampled_bfs(views.graph(spark, d, "g2"), 50), ["sum_dist", "harmonic", "coreach"])


# --- sketches ------------------------------------------------------------------------------

EVENT_REGISTERS = "SELECT event_type, ts::DATE AS day, ('0x' || substr(md5('0:' || user_id), 1, 15))::BIGINT AS h FROM events"
_RHO = f"CASE WHEN h & {(1 << 54) - 1} = 0 THEN 55 ELSE 55 - length(bin(h & {(1 << 54) - 1})) END"


def _event_registers(spark, d) -> DataFrame:
    reg, rho = register_of(F.concat_ws(":", F.lit(0), F.col("user_id").cast("string")), 64)
    return views.table(spark, d, "events").select("event_type", F.to_date("ts").alias("day"), reg.alias("reg"), rho.alias("rho"))


query("hll_registers_events", f"SELECT event_type, (h >> 54)::INTEGER AS reg, max({_RHO})::INTEGER AS rho FROM ({EVENT_REGISTERS}) GROUP BY ALL")(lambda spark, d: union_registers(_event_registers(spark, d), ["event_type"]))
query("hll_union_by_day", f"SELECT strftime(day, '%Y-%m-%d') AS day, (h >> 54)::INTEGER AS reg, max({_RHO})::INTEGER AS rho FROM ({EVENT_REGISTERS}) GROUP BY ALL")(
    lambda spark, d: union_registers(union_registers(_event_registers(spark, d), ["event_type", "day"]), ["day"]).withColumn("day", F.date_format("day", "yyyy-MM-dd"))
)
query(
    "hll_count_users_by_type",
    f"WITH r AS (SELECT event_type, h >> 54 AS reg, max({_RHO}) AS rho FROM ({EVENT_REGISTERS}) GROUP BY ALL), s AS (SELECT event_type, 64 - sum(1 - pow(2.0, -rho)) AS s, 64 - count(*) AS z FROM r GROUP BY event_type) SELECT event_type, round(CASE WHEN 0.709 * 4096 / s <= 160 AND z > 0 THEN 64 * ln(64.0 / z) ELSE 0.709 * 4096 / s END, 6) AS size FROM s",
)(lambda spark, d: rounded(hll_count(views.table(spark, d, "events"), "user_id", ["event_type"]), ["size"]))

query("md5_register_check", "SELECT p_partkey AS id, ('0x' || substr(md5('7:' || p_partkey), 1, 15))::BIGINT AS h FROM part")(
    lambda spark, d: views.table(spark, d, "part").select(F.col("p_partkey").alias("id"), md5_bits(F.concat_ws(":", F.lit(7), F.col("p_partkey").cast("string"))).alias("h"))
)

for _g in ("g2", "g9", "g10"):
    query(f"ball_registers_{_g}", f"{S.sketch_counts(_g)} SELECT node, reg::INTEGER AS reg, max(rho)::INTEGER AS rho FROM registers GROUP BY ALL")(lambda spark, d, g=_g: sketch_of(spark, d, g).registers().drop("run"))
for _g in ("g2", "g5", "g9", "g10"):
    query(f"ball_profile_{_g}", f"{S.sketch_counts(_g)} SELECT node, t, round(size, 6) AS size FROM profile")(lambda spark, d, g=_g: rounded(sketch_of(spark, d, g).profile().drop("run"), ["size"]))
    query(f"sketch_centralities_{_g}", f"{S.sketch_counts(_g)}, {S.MEASURES} SELECT node, {S.rounded(NAMES)} FROM measures")(
        lambda spark, d, g=_g: rounded(M.centralities(M.sketch_counts(sketch_of(spark, d, g))).drop("run"), NAMES)
    )
query("distance_counts_g2", f"{S.sketch_counts('g2')} SELECT node, t, round(n, 6) AS n FROM counts")(lambda spark, d: rounded(M.sketch_counts(sketch_of(spark, d, "g2")).drop("run"), ["n"]))
query("sketch_out_g2", f"{S.sketch_counts('g2', direction='out')}, {S.MEASURES} SELECT node, {S.rounded(NAMES)} FROM measures")(
    lambda spark, d: rounded(M.centralities(M.sketch_counts(sketch_of(spark, d, "g2", direction="out"))).drop("run"), NAMES)
)


@query("sketch_runs_mean_g2", f"{S.sketch_counts('g2', runs=4)}, {S.MEASURES} SELECT node, round(avg(harmonic), 6) AS harmonic_mean, round(stddev_samp(harmonic), 6) AS harmonic_sd, round(avg(coreach), 6) AS coreach_mean, round(stddev_samp(coreach), 6) AS coreach_sd, round(1.96 * stddev_samp(harmonic) / 2, 6) AS harmonic_half_width FROM measures GROUP BY node")
def sketch_runs_mean_g2(spark, d):
    got = M.average_runs(M.centralities(M.sketch_counts(sketch_of(spark, d, "g2", runs=4))), ["harmonic", "coreach"])
    names = ["harmonic_mean", "harmonic_sd", "coreach_mean", "coreach_sd", "harmonic_half_width"]
    return rounded(got.select("node", *names), names)


def _weighted(spark, d) -> Graph:
    return views.graph(spark, d, "g2").with_weights(part_weights(spark, d))


query("sketch_weighted_g2", f"{S.sketch_counts('g2', weights=WEIGHT_SQL)}, {S.MEASURES} SELECT node, {S.rounded(NAMES)} FROM measures")(
    lambda spark, d: rounded(M.centralities(M.sketch_counts(ball_sketches(_weighted(spark, d), weighted=True))).drop("run"), NAMES)
)
query("sketch_discounted_gain_g2", f"{S.sketch_counts('g2', weights=WEIGHT_SQL)}, {S.MEASURES} SELECT node, round(logarithmic, 6) AS logarithmic, round(quadratic, 6) AS quadratic FROM measures")(
    lambda spark, d: rounded(M.centralities(M.sketch_counts(ball_sketches(_weighted(spark, d), weighted=True)), {k: M.DISCOUNTS[k] for k in ("logarithmic", "quadratic")}).select("node", "logarithmic", "quadratic"), ["logarithmic", "quadratic"])
)
query("neighbourhood_fn_sketch_g2", f"{S.sketch_counts('g2')} SELECT t, round(sum(sum(n)) OVER (ORDER BY t), 4) AS pairs FROM counts GROUP BY t")(
    lambda spark, d: rounded(M.neighbourhood_function(M.sketch_counts(sketch_of(spark, d, "g2"))).drop("run"), ["pairs"], 4)
)
query("strict_closeness_sketch_g5", f"{S.sketch_counts('g5')}, {S.MEASURES}, last_of AS (SELECT node, reg, max(rho) AS rho FROM registers GROUP BY ALL), whole AS (SELECT reg, max(rho) AS top FROM last_of GROUP BY reg), have AS (SELECT node, count(*) AS k FROM last_of JOIN whole USING (reg) WHERE rho = top GROUP BY node) SELECT m.node, round(CASE WHEN h.k = (SELECT count(*) FROM whole) AND sum_dist > 0 THEN 1 / sum_dist ELSE 0 END, 9) AS closeness_strict FROM measures m LEFT JOIN have h USING (node)")(
    lambda spark, d: rounded(M.strict_closeness_sketch(sketch_of(spark, d, "g5")).drop("run"), ["closeness_strict"], 9)
)


@query("delta_equals_full_g2", "SELECT 0::BIGINT AS differing")
def delta_equals_full_g2(spark, d):
    a, b = sketch_of(spark, d, "g2"), sketch_of(spark, d, "g2", propagation="full")
    one, two = a.profile().select("node", "t", "size"), b.profile().select("node", "t", "size")
    return one.exceptAll(two).unionByName(two.exceptAll(one)).agg(F.count(F.lit(1)).alias("differing"))


@query(
    "fm_registers_g2",
    f"{S.pairs('g2')}, items AS (SELECT id, k, ('0x' || substr(md5('0:' || id || ':k' || k), 1, 15))::BIGINT AS h FROM nodes, (SELECT unnest(range(8)) AS k)), bits AS (SELECT id, k, 1::BIGINT << (CASE WHEN h = 0 THEN 60 ELSE 60 - length(bin(h)) END) AS b FROM items) SELECT node, k::BIGINT AS item, bit_or(b) AS value FROM reach JOIN bits ON id = source GROUP BY ALL",
)
def fm_registers_g2(spark, d):
    return pattern_balls(views.graph(spark, d, "g2"), patterns=8).rounds.final().select("node", "item", "value")


def _pattern_profile(g: str, patterns: int) -> str:
    """... and counts of bit-pattern counters: the mean place of the lowest zero bit at every distance."""
    return f"""{S.pairs(g)}, items AS (SELECT id, k, ('0x' || substr(md5('0:' || id || ':k' || k), 1, 15))::BIGINT AS h FROM nodes, (SELECT unnest(range({patterns})) AS k)),
bits AS (SELECT id, k, 1::BIGINT << (CASE WHEN h = 0 THEN 60 ELSE 60 - length(bin(h)) END) AS b FROM items),
met AS (SELECT r.node, r.dist AS t, k, bit_or(b) AS b FROM reach r JOIN bits ON bits.id = r.source GROUP BY ALL),
held AS (SELECT node, t, bit_or(b) OVER (PARTITION BY node, k ORDER BY t) AS x FROM met),
profile AS (SELECT node, 0 AS run, t, pow(2.0, sum(bit_count(x & ~(x + 1))) / {patterns}.0) / 0.77351 AS size FROM held GROUP BY node, t),
counts AS (SELECT node, run, t, size - coalesce(lag(size) OVER (PARTITION BY node ORDER BY t), 0) AS n FROM profile)"""


@query("fm_closeness_g9", f"{_pattern_profile('g9', 32)}, {S.MEASURES}, {RADIUS_SQL} SELECT m.node, {S.rounded(['coreach', 'closeness', 'harmonic'])}, round(CASE WHEN t = 0 THEN 0 ELSE t - 1 + (0.9 * total - before) / (size - before) END, 6) AS radius FROM measures m JOIN hit ON hit.node = m.node AND r = 1")
def fm_closeness_g9(spark, d):
    """The bit-pattern baseline's closeness and 90% radius."""
    counts = M.sketch_counts(pattern_balls(views.graph(spark, d, "g9"), patterns=32))
    names = ["coreach", "closeness", "harmonic", "radius"]
    return rounded(M.centralities(counts).join(M.effective_radius(counts), ["node", "run"]).select("node", *names), names)


@query("packed_patterns_g9", f"{_pattern_profile('g9', 32)}, {S.MEASURES} SELECT node, {S.rounded(['coreach', 'harmonic'])} FROM measures")
def packed_patterns_g9(spark, d):
    """The same counters in the packed layout, by whole rounds that keep sums."""
    return rounded(packed_patterns(views.graph(spark, d, "g9"), 32, gains={}).sums().select("node", "coreach", "harmonic"), ["coreach", "harmonic"])


_REGISTERS = "SELECT node, reg::INTEGER AS reg, max(rho)::INTEGER AS rho FROM registers GROUP BY ALL"
query("packed_g2", f"{S.sketch_counts('g2')} {_REGISTERS}")(lambda spark, d: packed_balls(views.graph(spark, d, "g2")).registers().drop("run"))
for _g in ("g2", "g5"):
    query(f"packed_profile_{_g}", f"{S.sketch_counts(_g)} SELECT node, t, round(size, 6) AS size FROM profile")(lambda spark, d, g=_g: rounded(packed_balls(views.graph(spark, d, g)).profile().drop("run"), ["size"]))
query("packed_centralities_g5", f"{S.sketch_counts('g5')}, {S.MEASURES} SELECT node, {S.rounded(NAMES)} FROM measures")(
    lambda spark, d: rounded(M.centralities(M.sketch_counts(packed_balls(views.graph(spark, d, "g5")))).drop("run"), NAMES)
)
for _g in ("g9", "g10"):
    query(f"accumulated_{_g}", f"{S.sketch_counts(_g)}, {S.MEASURES} SELECT node, {S.rounded(NAMES)} FROM measures")(
        lambda spark, d, g=_g: rounded(M.centralities_of_sums(packed_balls(views.graph(spark, d, g), gains={}).sums()).drop("run"), NAMES)
    )
query("accumulated_weighted_g2", f"{S.sketch_counts('g2', weights=WEIGHT_SQL)}, {S.MEASURES} SELECT node, round(logarithmic, 6) AS logarithmic, round(quadratic, 6) AS quadratic, round(harmonic, 6) AS harmonic FROM measures")(
    lambda spark, d: rounded(packed_balls(_weighted(spark, d), weighted=True, gains={"logarithmic": lambda t: 1 / math.log2(t + 1), "quadratic": lambda t: 1 / t**2}).sums().select("node", "logarithmic", "quadratic", "harmonic"), ["logarithmic", "quadratic", "harmonic"])
)
query("accumulated_out_runs_g2", f"{S.sketch_counts('g2', runs=3, direction='out')}, {S.MEASURES} SELECT node, run::INTEGER AS run, {S.rounded(NAMES)} FROM measures")(
    lambda spark, d: rounded(M.centralities_of_sums(packed_balls(views.graph(spark, d, "g2"), runs=3, direction="out", gains={}).sums()), NAMES)
)
query("aggregate_only_nf_g2", f"{S.sketch_counts('g2')} SELECT t, round(sum(sum(n)) OVER (ORDER BY t), 4) AS pairs FROM counts GROUP BY t")(
    lambda spark, d: rounded(packed_balls(views.graph(spark, d, "g2"), gains={}).neighbourhood_function().drop("run"), ["pairs"], 4)
)
query("round_changes_g2", f"{S.sketch_counts('g2')} SELECT t::INTEGER AS t, count(*) AS changed FROM profile GROUP BY t")(lambda spark, d: packed_balls(views.graph(spark, d, "g2")).stats().select("t", "changed"))
query("sketch_eccentricity_g10", f"{S.sketch_counts('g10')} SELECT node, max(t) AS eccentricity FROM profile GROUP BY node")(
    lambda spark, d: M.eccentricity(packed_balls(views.graph(spark, d, "g10")).profile()).drop("run")
)
query("diameter_bound_g2", f"{S.sketch_counts('g2')} SELECT max(t) AS diameter FROM profile")(lambda spark, d: M.diameter_bound(packed_balls(views.graph(spark, d, "g2")).profile()).drop("run"))
query("symmetric_tail_g2", f"{S.sketch_counts('g2', p=16, symmetric=True)}, {S.MEASURES} SELECT node, {S.rounded(NAMES)} FROM measures")(
    lambda spark, d: rounded(M.centralities_of_sums(packed_balls(views.graph(spark, d, "g2").symmetrise(), p=16, gains={}).sums()).drop("run"), NAMES)
)
query("average_distance_g3", f"{S.sketch_counts('g3', symmetric=True)} SELECT round(sum(n * t) / sum(n), 6) AS average_distance FROM counts WHERE t > 0")(
    lambda spark, d: rounded(M.distance_summary(M.sketch_counts(packed_balls(views.graph(spark, d, "g3").symmetrise())), 1).select("average_distance"), ["average_distance"])
)
query("native_sketch_g2")(lambda spark, d: native_balls(views.graph(spark, d, "g2"), lg_k=6))


@query(
    "ads_g9",
    f"{S.pairs('g9')}, h AS (SELECT node, source, dist, ('0x' || substr(md5('0:' || source), 1, 15))::BIGINT AS h FROM reach) SELECT node, source, dist FROM (SELECT *, (SELECT count(*) FROM h b WHERE b.node = a.node AND (b.dist < a.dist OR b.dist = a.dist) AND (b.h < a.h OR (b.h = a.h AND b.source < a.source))) AS better FROM h a) WHERE better < 3",
)
def ads_g9(spark, d):
    return all_distances_sketch(views.graph(spark, d, "g9"), k=3).select("node", "source", "dist")


_EARLIER = "(b.dist < a.dist OR (b.dist = a.dist AND (b.h < a.h OR (b.h = a.h AND b.source < a.source))))"
query(
    "ads_harmonic_g2",
    f"{S.pairs('g2')}, h AS (SELECT node, source, dist, ('0x' || substr(md5('0:' || source), 1, 15))::BIGINT AS h FROM reach), before AS (SELECT a.node, a.source, a.dist, a.h, list_sort(list(b.h)) AS l FROM h a LEFT JOIN h b ON a.node = b.node AND {_EARLIER} GROUP BY ALL), entries AS (SELECT *, CASE WHEN l[16] IS NULL THEN 1.0 ELSE l[16] / {1 << 60}::DOUBLE END AS tau FROM before WHERE l[16] IS NULL OR h < l[16]) SELECT node, round(coalesce(sum(1.0 / dist / tau) FILTER (WHERE dist > 0), 0), 6) AS value FROM entries GROUP BY node",
)(lambda spark, d: rounded(ads_estimate(all_distances_sketch(views.graph(spark, d, "g2"), k=16)), ["value"]))

# --- accuracy and cost ---------------------------------------------------------------------

_ERRORS = f"""{S.sketch_counts('g2', runs=4)}, {S.MEASURES}, truth_counts AS (SELECT node, dist AS t, count(*)::DOUBLE AS n FROM reach GROUP BY ALL),
truth AS (SELECT node, sum(n * t) AS sum_dist, coalesce(sum(n / t) FILTER (WHERE t > 0), 0) AS harmonic, sum(n) AS coreach FROM truth_counts GROUP BY node),
long_truth AS (SELECT node, 'harmonic' AS measure, harmonic AS exact FROM truth UNION ALL SELECT node, 'coreach', coreach FROM truth),
long_runs AS (SELECT node, run, 'harmonic' AS measure, harmonic AS v FROM measures UNION ALL SELECT node, run, 'coreach', coreach FROM measures),
averaged AS (SELECT k AS runs, node, measure, avg(v) AS approx FROM long_runs, (SELECT unnest([1, 2, 4]) AS k) WHERE run < k GROUP BY ALL),
errors AS (SELECT runs, node, measure, approx, exact, (approx - exact) / exact AS error FROM averaged JOIN long_truth USING (node, measure) WHERE exact > 0)"""


def _error_rows(spark, d, ks=(1, 2, 4)) -> DataFrame:
    graph = views.graph(spark, d, "g2")
    names = ["harmonic", "coreach"]
    exact = M.ingredients(exact_pairs(graph).counts()).select("node", *names)
    runs = M.ingredients(M.sketch_counts(ball_sketches(graph, runs=max(ks)))).select("node", "run", *names)
    return A.convergence(runs, exact, names, list(ks))


query("relative_errors_g2", f"{_ERRORS} SELECT node, measure, round(abs(error), 6) AS rel_error FROM errors WHERE runs = 1")(
    lambda spark, d: _error_rows(spark, d).where("runs = 1").select("node", "measure", F.round(F.abs("error"), 6).alias("rel_error"))
)
query("convergence_g2", f"{_ERRORS} SELECT runs, measure, round(sqrt(avg(error * error)), 6) AS rms FROM errors GROUP BY ALL")(
    lambda spark, d: A.rms(_error_rows(spark, d)).select("runs", "measure", F.round("rms", 6).alias("rms"))
)
query(
    "error_boxes_g2",
    f"{_ERRORS} SELECT runs, measure, round(quantile_cont(error, 0.25), 6) AS q1, round(quantile_cont(error, 0.5), 6) AS median, round(quantile_cont(error, 0.75), 6) AS q3, round(avg(error), 6) AS mean, round(avg(error) - stddev_samp(error), 6) AS low, round(avg(error) + stddev_samp(error), 6) AS high FROM errors GROUP BY ALL",
)(lambda spark, d: rounded(A.error_boxes(_error_rows(spark, d), ["runs", "measure"]), ["q1", "median", "q3", "mean", "low", "high"]))

query("footprint_table", "SELECT p, round(n * (p * 6 / 8.0 + 4.5) / 1073741824.0, 9) AS gib FROM (SELECT count(DISTINCT l_partkey) AS n FROM lineitem), (SELECT unnest([16, 64, 256]) AS p)")(
    lambda spark, d: theory.footprint_table(views.table(spark, d, "lineitem").agg(F.countDistinct("l_partkey").alias("n")), [16, 64, 256], 9)
)
query("theory_table", "SELECT p, k, round(CASE p WHEN 16 THEN 1.106 WHEN 32 THEN 1.070 WHEN 64 THEN 1.054 WHEN 128 THEN 1.046 ELSE 1.039 END / sqrt(p) / sqrt(k), 6) AS rsd FROM (SELECT unnest([16, 32, 64, 128, 256, 4096]) AS p), (SELECT DISTINCT l_linenumber AS k FROM lineitem)")(
    lambda spark, d: theory.theory_table(views.table(spark, d, "lineitem").select(F.col("l_linenumber").alias("k")), [16, 32, 64, 128, 256, 4096])
)
query(
    "rank_agreement_g2",
    f"{S.exact_counts('g2')}, {S.MEASURES}, ranks AS (SELECT node, rank() OVER (ORDER BY harmonic) + (count(*) OVER (PARTITION BY harmonic) - 1) / 2.0 AS a, rank() OVER (ORDER BY lin) + (count(*) OVER (PARTITION BY lin) - 1) / 2.0 AS b FROM (SELECT node, round(harmonic, 9) AS harmonic, round(lin, 9) AS lin FROM measures)) SELECT round(corr(a, b), 6) AS spearman FROM ranks",
)(lambda spark, d: rounded(A.spearman(rounded(M.centralities(counts_of(spark, d, "g2")), ["harmonic", "lin"], 9), "harmonic", "lin"), ["spearman"]))
query("overlap_g2", f"{S.exact_counts('g2')}, {S.MEASURES}, a AS (SELECT node FROM measures ORDER BY round(harmonic, 9) DESC, node LIMIT 50), b AS (SELECT node FROM measures ORDER BY round(lin, 9) DESC, node LIMIT 50) SELECT count(*) / 50.0 AS overlap FROM a JOIN b USING (node)")(
    lambda spark, d: A.overlap(rounded(M.centralities(counts_of(spark, d, "g2")), ["harmonic", "lin"], 9), "harmonic", "lin", 50)
)
query(
    "kendall_g9",
    f"{S.exact_counts('g9')}, {S.MEASURES}, m AS (SELECT round(harmonic, 9) AS h, round(closeness, 9) AS c, count(*) AS n FROM measures GROUP BY ALL) SELECT round(sum(a.n * b.n * sign(a.h - b.h) * sign(a.c - b.c)) / (SELECT sum(n) * (sum(n) - 1) FROM m), 6) AS tau FROM m a, m b",
)(lambda spark, d: rounded(A.kendall(rounded(M.centralities(counts_of(spark, d, "g9")), ["harmonic", "closeness"], 9), "harmonic", "closeness"), ["tau"]))
query(
    "bias_report_g10",
    f"{S.exact_counts('g10')}, {S.MEASURES}, m AS (SELECT node, coreach, round(closeness, 9) AS closeness, round(lin, 9) AS lin, round(harmonic, 9) AS harmonic FROM measures), med AS (SELECT median(coreach) AS c FROM m) "
    + " UNION ALL ".join(
        f"SELECT '{x}' AS measure, (SELECT round(corr({x}, coreach), 6) FROM m) AS correlation, (SELECT count(*) FILTER (WHERE coreach < (SELECT c FROM med)) / 10.0 FROM (SELECT * FROM m ORDER BY {x} DESC, node LIMIT 10)) AS low_share" for x in ("closeness", "lin", "harmonic")
    ),
)(lambda spark, d: rounded(A.bias_report(rounded(M.centralities(counts_of(spark, d, "g10", as_run=True)), ["closeness", "lin", "harmonic"], 9), ["closeness", "lin", "harmonic"], 10), ["correlation"]))


def _run_errors(g: str, p: int, runs: int, more: str = "") -> str:
    """... and errors(node, run, measure, error) of single runs."""
    long = lambda t, run: " UNION ALL ".join(f"SELECT node, {run} '{m}' AS measure, {m} AS v FROM {t}" for m in ("harmonic", "coreach", "sum_dist"))
    return f"""{S.sketch_counts(g, p=p, runs=runs)}, {S.MEASURES}, truth_counts AS (SELECT node, dist AS t, count(*)::DOUBLE AS n FROM reach GROUP BY ALL),
truth AS (SELECT node, sum(n * t) AS sum_dist, coalesce(sum(n / t) FILTER (WHERE t > 0), 0) AS harmonic, sum(n) AS coreach FROM truth_counts GROUP BY node){more},
errors AS (SELECT a.node, a.run, a.measure, (a.v - e.v) / e.v AS error FROM ({long("measures", "run,")}) a JOIN ({long("truth", "")}) e USING (node, measure) WHERE e.v > 0)"""


def _errors_of_runs(graph: Graph, p: int, runs: int) -> DataFrame:
    names = ["harmonic", "coreach", "sum_dist"]
    exact = M.ingredients(exact_pairs(graph).counts()).select("node", *names)
    return A.run_errors(packed_balls(graph, p=p, runs=runs, gains={}).sums().select("node", "run", *names), exact, names)


_BOXES = "round(quantile_cont(error, 0.25), 6) AS q1, round(quantile_cont(error, 0.5), 6) AS median, round(quantile_cont(error, 0.75), 6) AS q3, round(avg(error), 6) AS mean, round(avg(error) - stddev_samp(error), 6) AS low, round(avg(error) + stddev_samp(error), 6) AS high"
_BOX = ["q1", "median", "q3", "mean", "low", "high"]


@query("concentration_g5", f"{_run_errors('g5', 64, 4)} SELECT run::INTEGER AS run, measure, {_BOXES} FROM errors GROUP BY run, measure")
def concentration_g5(spark, d):
    """Spread of errors over nodes within runs."""
    return rounded(A.error_boxes(_errors_of_runs(views.graph(spark, d, "g5"), 64, 4), ["run", "measure"]), _BOX)


_GIANT = ", mutual AS (SELECT a.node, min(a.source) AS c FROM reach a JOIN reach b ON a.node = b.source AND a.source = b.node GROUP BY a.node), giant AS (SELECT node FROM mutual WHERE c = (SELECT c FROM mutual GROUP BY c ORDER BY count(*) DESC, c LIMIT 1))"


@query("concentration_g12", f"{_run_errors('g12', 256, 4, _GIANT)} SELECT run::INTEGER AS run, measure, e.node IN (SELECT node FROM giant) AS inside, {_BOXES} FROM errors e GROUP BY ALL")
def concentration_g12(spark, d):
    """The same by membership of the giant strong component, whose nodes share one final counter: there the spread of coreachable counts is nil."""
    graph = views.graph(spark, d, "g12")
    graph = Graph(cut(graph.vertices), cut(graph.arcs))
    parts = cut(strong_components(graph))
    giant = parts.groupBy("component").count().orderBy(F.desc("count"), "component").limit(1)
    errors = A.by_membership(_errors_of_runs(graph, 256, 4), parts.join(giant, "component").select("node"))
    return rounded(A.error_boxes(errors, ["run", "measure", "inside"]), _BOX)


_KS = [1, 5, 10, 20]
_ACCURACY = ["closeness", "lin", "harmonic", "coreach"]


def _accuracy_sql(g: str, p: int, runs: int) -> str:
    long = lambda t, run: " UNION ALL ".join(f"SELECT node, {run} '{m}' AS measure, {m} AS v FROM {t}" for m in _ACCURACY)
    truth = "truth AS (SELECT node, n AS coreach, h AS harmonic, CASE WHEN s > 0 THEN 1 / s ELSE 0 END AS closeness, CASE WHEN s > 0 THEN n * n / s ELSE 1 END AS lin FROM (SELECT node, count(*)::DOUBLE AS n, sum(dist)::DOUBLE AS s, coalesce(sum(1.0 / dist) FILTER (WHERE dist > 0), 0) AS h FROM reach GROUP BY node))"
    return f"{S.sketch_counts(g, p=p, runs=runs)}, {S.MEASURES}, {truth}, averaged AS (SELECT k AS runs, node, measure, avg(v) AS v FROM ({long('measures', 'run,')}), (SELECT unnest({_KS}) AS k) WHERE run < k GROUP BY ALL) SELECT runs::INTEGER AS runs, measure, round(sqrt(avg(pow((a.v - e.v) / e.v, 2))), 6) AS rms FROM averaged a JOIN ({long('truth', '')}) e USING (node, measure) WHERE e.v > 0 GROUP BY ALL"


@query("accuracy_g12", _accuracy_sql("g12", 256, 20))
def accuracy_g12(spark, d):
    """Errors of the means of 1 to 20 runs, by measure, on a graph with a giant component."""
    return accuracy_of_means(views.graph(spark, d, "g12"), 256, _KS)


def accuracy_of_means(graph: Graph, p: int, ks: list[int]) -> DataFrame:
    """runs, measure, rms: relative errors of the means of the first k runs, for each k."""
    graph = Graph(cut(graph.vertices), cut(graph.arcs))
    exact = M.centralities(exact_pairs(graph).counts()).select("node", *_ACCURACY)
    runs = M.centralities_of_sums(packed_balls(graph, p=p, runs=max(ks), gains={}).sums()).select("node", "run", *_ACCURACY)
    return rounded(A.rms(A.convergence(runs, exact, _ACCURACY, ks)), ["rms"])


@query(
    "visits_against_sketch_g2",
    f"{S.sketch_counts('g2')}, {S.MEASURES}, pivots AS (SELECT id FROM nodes ORDER BY ('0x' || substr(md5('0:' || id), 1, 15))::BIGINT, id LIMIT 50), truth AS (SELECT node, coalesce(sum(1.0 / dist) FILTER (WHERE dist > 0), 0) AS h FROM reach GROUP BY node), visits AS (SELECT n.id AS node, coalesce((SELECT count(*) FROM nodes) / 50.0 * sum(CASE WHEN dist > 0 THEN 1.0 / dist ELSE 0 END), 0) AS h FROM nodes n LEFT JOIN (SELECT * FROM reach WHERE source IN (SELECT id FROM pivots)) r ON r.node = n.id GROUP BY n.id), both_of AS (SELECT 'visits' AS method, node, h FROM visits UNION ALL SELECT 'sketch', node, harmonic FROM measures) SELECT method, round(sqrt(avg(pow((b.h - t.h) / t.h, 2))), 6) AS rmse FROM both_of b JOIN truth t USING (node) WHERE t.h > 0 GROUP BY method",
)
def visits_against_sketch_g2(spark, d):
    """Errors of harmonic centrality from 50 sampled visits and from counters of 64 registers: on a disconnected graph visits fail."""
    graph = views.graph(spark, d, "g2")
    exact = M.ingredients(exact_pairs(graph).counts()).select("node", "harmonic")
    ways = {"visits": sampled_bfs(graph, 50), "sketch": packed_balls(graph, gains={}).sums()}
    out = None
    for name, got in ways.items():
        part = A.relative_errors(got.select("node", "harmonic"), exact, ["harmonic"]).withColumn("method", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return rounded(A.rmse(out, ["method"]), ["rmse"])


@query("rounds_g2")
def rounds_g2(spark, d):
    """Cost of each round: changed nodes and registers, and seconds."""
    graph = views.graph(spark, d, "g2")
    return fixpoint(rank_seeds(graph, 64), graph, MAXIMUM).stats()

