"""Queries of the tools around the graph methods: sources, joins, windows, functions, streams."""

from __future__ import annotations

import uuid

from pyspark.sql import Window
from pyspark.sql import functions as F

from geocentra.centrality import measures as M
from geocentra.functions import sketching
from geocentra.graph import views
from geocentra.graph.generators import path_of
from geocentra.graph.model import Graph, dangling_arcs, degrees, node_id
from geocentra.operators.joins import dominated
from geocentra.plans.checkpoint import own_folder
from geocentra.propagate.exact import exact_pairs
from geocentra.registry import sql as S
from geocentra.registry.graphs import NAMES, ORACLES, counts_of, query, rounded, sketch_of
from geocentra.propagate.packed import packed_balls
from geocentra.sketch.packed import estimate_packed, pack_registers, union_packed
from geocentra.sources import edges
from geocentra.streaming import ingest

T = views.table
#: A side of more bytes is not broadcast.
BROADCAST_BYTES = 64 << 20
_MEASURES_G9 = f"{S.exact_counts('g9')}, {S.MEASURES}"
_MEASURES_G2 = f"{S.exact_counts('g2')}, {S.MEASURES}"


def _measures(spark, d, g="g9"):
    return M.centralities(counts_of(spark, d, g)).drop("run")


def _folder(spark, name: str) -> str:
    return f"{own_folder(spark)}/{name}-{uuid.uuid4().hex}"


# --- sources and sinks ---------------------------------------------------------------------

query("scan_arcs_pruned", "SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey FROM lineitem WHERE l_quantity <= 5")(
    lambda s, d: T(s, d, "lineitem").where("l_quantity <= 5").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")
)


@query("sink_arcs_roundtrip", f"SELECT src, dst FROM ({S.ARCS['g1']})")
def sink_arcs_roundtrip(s, d):
    at = _folder(s, "arcs")
    edges.write_partitioned(views.VIEWS["g1"](s, d), at)
    return s.read.parquet(at).select("src", "dst")


for _format in ("csv", "json", "text", "orc"):

    @query(f"edge_list_{_format}", f"SELECT src, dst FROM ({S.ARCS['g11']})")
    def edge_list(s, d, format=_format):
        at = _folder(s, "edges")
        edges.write_edges(views.VIEWS["g11"](s, d), at, format)
        return edges.read_edges(s, at, format)[0]


@query("arcs_bucketed", f"SELECT src, dst FROM ({S.ARCS['g5']})")
def arcs_bucketed(s, d):
    return edges.write_bucketed(views.graph(s, d, "g5"), f"arcs_{uuid.uuid4().hex}").select("src", "dst")


query("adjacency_rows", f"SELECT src AS node, list_sort(list(dst))::VARCHAR AS successors, count(*)::INTEGER AS degree FROM ({S.ARCS['g5']}) GROUP BY src")(
    lambda s, d: edges.adjacency(views.VIEWS["g5"](s, d)).withColumn("successors", F.concat(F.lit("["), F.array_join("successors", ", "), F.lit("]")))
)
query("path_source", "SELECT src, dst FROM (SELECT o_orderkey AS src, lead(o_orderkey) OVER (ORDER BY o_orderkey) AS dst FROM orders) WHERE dst IS NOT NULL AND src <> dst")(lambda s, d: path_of(T(s, d, "orders"), "o_orderkey"))
query("filter_arcs_by_part", f"SELECT src, dst FROM ({S.ARCS['g1']}) JOIN part ON src = p_partkey WHERE p_size BETWEEN 10 AND 20 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#21') AND p_name LIKE '%a%'")(
    lambda s, d: views.VIEWS["g1"](s, d).join(T(s, d, "part").where("p_size BETWEEN 10 AND 20 AND p_brand IN ('Brand#11', 'Brand#12', 'Brand#21') AND p_name LIKE '%a%'").select("p_partkey"), F.col("src") == F.col("p_partkey")).select("src", "dst")
)
query("filter_events_window", "SELECT event_id, user_id FROM events WHERE ts >= TIMESTAMP '2024-01-05' AND ts < TIMESTAMP '2024-01-07' AND event_type IS NOT DISTINCT FROM 'click'")(
    lambda s, d: T(s, d, "events").where((F.col("ts") >= F.lit("2024-01-05").cast("timestamp")) & (F.col("ts") < F.lit("2024-01-07").cast("timestamp")) & F.col("event_type").eqNullSafe("click")).select("event_id", "user_id")
)
query("node_keys", f"SELECT {S.kind('customer', 'c_custkey')} AS id, CASE WHEN c_acctbal < 0 THEN 'debt' WHEN c_acctbal < 5000 THEN 'low' ELSE 'high' END AS band FROM customer")(
    lambda s, d: T(s, d, "customer").select(node_id("customer", "c_custkey").alias("id"), F.when(F.col("c_acctbal") < 0, "debt").when(F.col("c_acctbal") < 5000, "low").otherwise("high").alias("band"))
)
query("arcs_clean", "SELECT DISTINCT l_partkey AS src, l_suppkey AS dst FROM lineitem WHERE l_partkey <> l_suppkey")(
    lambda s, d: Graph.from_arcs(T(s, d, "lineitem").select(F.col("l_partkey").alias("src"), F.col("l_suppkey").alias("dst"))).arcs
)
query("dangling_arcs", f"SELECT src, dst FROM ({S.ARCS['g1']}) WHERE src NOT IN (SELECT p_partkey FROM part WHERE p_size > 5) OR dst NOT IN (SELECT p_partkey FROM part WHERE p_size > 5)")(
    lambda s, d: dangling_arcs(views.VIEWS["g1"](s, d), T(s, d, "part").where("p_size > 5").select(F.col("p_partkey").alias("id")))
)

# --- joins and set operations --------------------------------------------------------------

for _hint in ("merge", "shuffle_hash", "broadcast"):

    @query(f"join_customer_supplier_{_hint}", "SELECT o_custkey, l_suppkey, count(*) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_returnflag = 'R' GROUP BY ALL")
    def join_customer_supplier(s, d, hint=_hint):
        orders = T(s, d, "orders").select("o_orderkey", "o_custkey")
        lines = T(s, d, "lineitem").where("l_returnflag = 'R'").select("l_orderkey", "l_suppkey")
        if hint == "broadcast" and orders.count() * 16 > BROADCAST_BYTES:
            hint = "shuffle_hash"
        return lines.join(orders.hint(hint), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_custkey", "l_suppkey").agg(F.count(F.lit(1)).alias("n"))


_G11_IN = f"{S.exact_counts('g11', 'out')}, {S.MEASURES}"
query("centrality_by_segment", f"{_G11_IN} SELECT c_mktsegment, count(*) AS n, round(avg(harmonic), 6) AS harmonic FROM measures JOIN customer ON node = {S.kind('customer', 'c_custkey')} GROUP BY ALL")(
    lambda s, d: rounded(
        M.centralities(counts_of(s, d, "g11", "out")).join(T(s, d, "customer").select(node_id("customer", "c_custkey").alias("node"), "c_mktsegment"), "node").groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n"), F.avg("harmonic").alias("harmonic")), ["harmonic"]
    )
)
query("measures_with_isolated", f"{_MEASURES_G2} SELECT p_partkey AS node, round(coalesce(closeness, 0), 6) AS closeness, round(coalesce(lin, 1), 6) AS lin, round(coalesce(harmonic, 0), 6) AS harmonic FROM part LEFT JOIN measures ON node = p_partkey")(
    lambda s, d: rounded(
        T(s, d, "part").select(F.col("p_partkey").alias("node")).join(_measures(s, d, "g2"), "node", "left").select("node", F.coalesce("closeness", F.lit(0.0)).alias("closeness"), F.coalesce("lin", F.lit(1.0)).alias("lin"), F.coalesce("harmonic", F.lit(0.0)).alias("harmonic")),
        ["closeness", "lin", "harmonic"],
    )
)
query(
    "approx_vs_exact",
    f"{S.sketch_counts('g9')}, {S.MEASURES}, e AS (SELECT node, sum(1.0 / dist) AS harmonic FROM reach WHERE dist > 0 GROUP BY node) SELECT coalesce(m.node, e.node) AS node, round(m.harmonic, 6) AS approx, round(e.harmonic, 6) AS exact FROM measures m FULL JOIN e ON m.node = e.node",
)(
    lambda s, d: M.centralities(M.sketch_counts(sketch_of(s, d, "g9"))).select("node", F.round("harmonic", 6).alias("approx"))
    .join(exact_pairs(views.graph(s, d, "g9")).pairs().where("dist > 0").groupBy("node").agg(F.round(F.sum(1 / F.col("dist")), 6).alias("exact")), "node", "full")
)
query("arcs_into_top_k", f"{_MEASURES_G9}, best AS (SELECT node FROM measures ORDER BY round(harmonic, 9) DESC, node LIMIT 20) SELECT src, dst FROM arcs WHERE dst IN (SELECT node FROM best)")(
    lambda s, d: views.VIEWS["g9"](s, d).join(rounded(_measures(s, d), ["harmonic"], 9).orderBy(F.desc("harmonic"), "node").limit(20).select(F.col("node").alias("dst")), "dst", "left_semi").select("src", "dst")
)
for _end, _name in (("dst", "source_nodes"), ("src", "sink_nodes")):
    query(_name, f"WITH {S.graph('g2')} SELECT id AS node FROM nodes WHERE id NOT IN (SELECT {_end} FROM arcs)")(
        lambda s, d, end=_end: (lambda g: g.vertices.select(F.col("id").alias("node")).join(g.arcs.select(F.col(end).alias("node")), "node", "left_anti"))(views.graph(s, d, "g2"))
    )
query("two_hop_pairs", f"WITH a AS ({S.ARCS['g2']}) SELECT src, dst FROM a UNION SELECT x.src, y.dst FROM a x JOIN a y ON x.dst = y.src WHERE x.src <> y.dst")(
    lambda s, d: (lambda a: a.unionByName(a.alias("x").join(a.select(F.col("src").alias("mid"), F.col("dst").alias("far")), F.col("dst") == F.col("mid")).select("src", F.col("far").alias("dst")).where("src <> dst")).distinct())(views.VIEWS["g2"](s, d))
)


@query("dominated_nodes", f"{_MEASURES_G9}, m AS (SELECT node, round(closeness, 9) AS c, coreach AS k FROM measures) SELECT a.node, count(*) AS better FROM m a JOIN m b ON b.c > a.c AND b.k > a.k GROUP BY a.node")
def dominated_nodes(s, d):
    return dominated(_measures(s, d).select("node", F.round("closeness", 9).alias("c"), F.col("coreach").alias("k")), "c", "k")


@query("event_pairs_within_hour", "SELECT a.user_id, count(*) AS n FROM events a JOIN events b ON a.user_id <> b.user_id AND a.event_type = 'error' AND b.event_type = 'signup' AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 1 HOUR GROUP BY a.user_id")
def event_pairs_within_hour(s, d):
    """A range join by hour buckets: an event meets its own hour and the next."""
    hour = F.floor(F.unix_timestamp("ts") / 3600)
    a = T(s, d, "events").where("event_type = 'error'").select("user_id", "ts", F.explode(F.array(hour, hour + 1)).alias("hour"))
    b = T(s, d, "events").where("event_type = 'signup'").select(F.col("user_id").alias("other"), F.col("ts").alias("ts2"), hour.alias("hour"))
    near = a.join(b, "hour").where("user_id <> other AND ts2 BETWEEN ts AND ts + INTERVAL 1 HOUR")
    return near.groupBy("user_id").agg(F.count(F.lit(1)).alias("n"))


@query("asof_previous_order", "SELECT c_custkey, max(o_orderkey) AS o_orderkey FROM (SELECT c_custkey, o_orderkey, rank() OVER (PARTITION BY c_custkey ORDER BY o_orderdate DESC) AS r FROM customer JOIN orders ON c_custkey = o_custkey WHERE o_orderdate <= TIMESTAMP '1996-06-30') WHERE r = 1 GROUP BY c_custkey")
def asof_previous_order(s, d):
    """Each customer's last order up to a date, by a window over the union of probes and orders."""
    probes = T(s, d, "customer").select("c_custkey", F.lit("1996-06-30").cast("timestamp").alias("at"), F.lit(None).cast("long").alias("key"), F.lit(1).alias("probe"))
    orders = T(s, d, "orders").select(F.col("o_custkey").alias("c_custkey"), F.col("o_orderdate").alias("at"), F.col("o_orderkey").alias("key"), F.lit(0).alias("probe"))
    w = Window.partitionBy("c_custkey").orderBy("at", "probe", F.col("key").asc_nulls_last()).rowsBetween(Window.unboundedPreceding, Window.currentRow)
    found = probes.unionByName(orders).withColumn("o_orderkey", F.last("key", True).over(w))
    return found.where("probe = 1 AND o_orderkey IS NOT NULL").select("c_custkey", "o_orderkey")


query("all_pairs_small", f"{S.pairs('g11')} SELECT a.n_nationkey AS a, b.r_regionkey AS b, round(CASE WHEN r.dist > 0 THEN 1.0 / r.dist ELSE 0 END, 6) AS gain FROM nation a CROSS JOIN region b LEFT JOIN reach r ON r.source = {S.kind('nation', 'a.n_nationkey')} AND r.node = {S.kind('region', 'b.r_regionkey')}")(
    lambda s, d: T(s, d, "nation").select(F.col("n_nationkey").alias("a"), node_id("nation", "n_nationkey").alias("source")).crossJoin(T(s, d, "region").select(F.col("r_regionkey").alias("b"), node_id("region", "r_regionkey").alias("node")))
    .join(exact_pairs(views.graph(s, d, "g11")).pairs(), ["node", "source"], "left").select("a", "b", F.round(F.when(F.col("dist") > 0, 1.0 / F.col("dist")).otherwise(0.0), 6).alias("gain"))
)
query("sym_arcs", f"WITH a AS ({S.ARCS['g1']}) SELECT src, dst FROM a UNION SELECT dst, src FROM a")(lambda s, d: views.graph(s, d, "g1").symmetrise().arcs)
query("mutual_arcs", f"WITH a AS ({S.ARCS['g1']}) SELECT src, dst FROM a INTERSECT SELECT dst, src FROM a")(lambda s, d: (lambda g: g.arcs.intersect(g.transpose().arcs))(views.graph(s, d, "g1")))
query("one_way_arcs", f"WITH a AS ({S.ARCS['g1']}) SELECT src, dst FROM a EXCEPT SELECT dst, src FROM a")(lambda s, d: (lambda g: g.arcs.exceptAll(g.transpose().arcs))(views.graph(s, d, "g1")))

# --- aggregation and windows ---------------------------------------------------------------

query("degree_in_out", f"WITH {S.graph('g2')} SELECT id AS node, (SELECT count(*) FROM arcs WHERE dst = id) AS n_in, (SELECT count(*) FROM arcs WHERE src = id) AS n_out FROM nodes")(lambda s, d: degrees(views.graph(s, d, "g2")))
query("distinct_sources", f"SELECT count(DISTINCT src) AS sources, count(DISTINCT dst) AS targets FROM ({S.ARCS['g1']})")(lambda s, d: views.VIEWS["g1"](s, d).agg(F.countDistinct("src").alias("sources"), F.countDistinct("dst").alias("targets")))
query("approx_distinct_sources")(lambda s, d: views.VIEWS["g1"](s, d).agg(F.approx_count_distinct("src", 0.02).alias("sources"), F.hll_sketch_estimate(F.hll_sketch_agg("dst")).alias("targets")))

_BRANDS = f"{_MEASURES_G2}, b AS (SELECT p_brand, p_type, harmonic FROM measures JOIN part ON node = p_partkey)"
for _kind, _sql in (("cube", "CUBE (p_brand, p_type)"), ("rollup", "ROLLUP (p_brand, p_type)"), ("grouping_sets", "GROUPING SETS ((p_brand), (p_type), ())")):

    @query(f"centrality_{_kind}", f"{_BRANDS} SELECT p_brand, p_type, count(*) AS n, round(avg(harmonic), 6) AS harmonic FROM b GROUP BY {_sql}")
    def centrality_groups(s, d, kind=_kind):
        rows = _measures(s, d, "g2").join(T(s, d, "part").select(F.col("p_partkey").alias("node"), "p_brand", "p_type"), "node")
        if kind == "grouping_sets":
            sets = rows.groupingSets([["p_brand"], ["p_type"], []], "p_brand", "p_type")
        else:
            sets = rows.cube("p_brand", "p_type") if kind == "cube" else rows.rollup("p_brand", "p_type")
        return rounded(sets.agg(F.count(F.lit(1)).alias("n"), F.avg("harmonic").alias("harmonic")), ["harmonic"])


query("measure_pivot", f"{_MEASURES_G9} SELECT CASE WHEN node >= 0 THEN node % 1000 ELSE -node % 1048576 END AS turn, round(max(closeness), 6) AS closeness, round(max(harmonic), 6) AS harmonic, round(max(lin), 6) AS lin FROM measures GROUP BY ALL")(
    lambda s, d: rounded(
        _measures(s, d).select(views.turn_of(F.col("node")).alias("turn"), F.explode(F.array(*[F.struct(F.lit(n).alias("m"), F.col(n).alias("v")) for n in ("closeness", "harmonic", "lin")])).alias("x")).select("turn", "x.*").groupBy("turn").pivot("m", ["closeness", "harmonic", "lin"]).agg(F.max("v")),
        ["closeness", "harmonic", "lin"],
    )
)
query("measure_correlations", f"{_MEASURES_G2} SELECT round(corr(harmonic, lin), 6) AS harmonic_lin, round(corr(harmonic, coreach), 6) AS harmonic_coreach, round(stddev_samp(harmonic), 6) AS sd FROM measures")(
    lambda s, d: rounded(_measures(s, d, "g2").agg(F.corr("harmonic", "lin").alias("harmonic_lin"), F.corr("harmonic", "coreach").alias("harmonic_coreach"), F.stddev_samp("harmonic").alias("sd")), ["harmonic_lin", "harmonic_coreach", "sd"])
)
query("measure_quantiles", f"{_MEASURES_G2} SELECT round(quantile_cont(harmonic, 0.25), 6) AS q1, round(quantile_cont(harmonic, 0.5), 6) AS q2, round(quantile_cont(harmonic, 0.75), 6) AS q3 FROM measures")(
    lambda s, d: rounded(_measures(s, d, "g2").agg(*[F.percentile("harmonic", F.lit(q)).alias(n) for q, n in ((0.25, "q1"), (0.5, "q2"), (0.75, "q3"))]), ["q1", "q2", "q3"])
)
query("farthest_source", f"{S.pairs('g10')} SELECT node, arg_max(source, dist * 1000000 - source) AS farthest, bool_and(dist >= 0) AS sane, min(dist) AS nearest FROM reach GROUP BY node")(
    lambda s, d: exact_pairs(views.graph(s, d, "g10")).outermost(1000000).groupBy("node").agg(F.max_by("source", F.col("dist").cast("long") * 1000000 - F.col("source")).alias("farthest"), F.bool_and(F.col("dist") >= 0).alias("sane"), F.min("dist").alias("nearest"))
)
query("fm_union", "SELECT event_type, bit_or(1::BIGINT << (user_id % 60)::INTEGER) AS bits FROM events GROUP BY event_type")(lambda s, d: T(s, d, "events").groupBy("event_type").agg(F.expr("bit_or(shiftleft(1L, CAST(user_id % 60 AS INT)))").alias("bits")))

_RANKED = "SELECT p_brand, node, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, round(percent_rank() OVER v, 6) AS pr, ntile(4) OVER w AS nt FROM (SELECT p_brand, node, round(harmonic, 9) AS h FROM measures JOIN part ON node = p_partkey) WINDOW v AS (PARTITION BY p_brand ORDER BY h DESC), w AS (PARTITION BY p_brand ORDER BY h DESC, node)"


def _branded(s, d):
    return _measures(s, d, "g2").join(T(s, d, "part").select(F.col("p_partkey").alias("node"), "p_brand"), "node").select("p_brand", "node", F.round("harmonic", 9).alias("h"))


@query("rank_by_harmonic", f"{_MEASURES_G2} {_RANKED}")
def rank_by_harmonic(s, d):
    v, w = Window.partitionBy("p_brand").orderBy(F.desc("h")), Window.partitionBy("p_brand").orderBy(F.desc("h"), "node")
    return _branded(s, d).select("p_brand", "node", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.round(F.percent_rank().over(v), 6).alias("pr"), F.ntile(4).over(w).alias("nt"))


query("top_k_per_brand", f"{_MEASURES_G2} SELECT p_brand, node, rn FROM ({_RANKED}) WHERE rn <= 3")(
    lambda s, d: _branded(s, d).withColumn("rn", F.row_number().over(Window.partitionBy("p_brand").orderBy(F.desc("h"), "node"))).where("rn <= 3").select("p_brand", "node", "rn")
)
query("top_k_harmonic", f"{_MEASURES_G2} SELECT node, round(harmonic, 6) AS value, row_number() OVER (ORDER BY round(harmonic, 9) DESC, node) AS place FROM (SELECT * FROM measures ORDER BY round(harmonic, 9) DESC, node LIMIT 25)")(
    lambda s, d: rounded(M.ranking(rounded(_measures(s, d, "g2"), ["harmonic"], 9), "harmonic", 25), ["value"])
)
query("sample_nodes", f"WITH {S.graph('g1')} SELECT id AS node FROM nodes WHERE ('0x' || substr(md5('s:' || id), 1, 15))::BIGINT % 10 = 0")(
    lambda s, d: views.graph(s, d, "g1").vertices.where(F.conv(F.substring(F.md5(F.concat(F.lit("s:"), F.col("id").cast("string")).cast("binary")), 1, 15), 16, 10).cast("long") % 10 == 0).select(F.col("id").alias("node"))
)

_P9 = f"{S.sketch_counts('g9')}"


def _by_time():
    return Window.partitionBy("node").orderBy("t")



def _profile(s, d):
    return sketch_of(s, d, "g9").profile().select("node", "t", "size")


query("profile_lag", f"{_P9} SELECT node, t, round(size - coalesce(lag(size) OVER (PARTITION BY node ORDER BY t), 0), 6) AS grown FROM profile")(
    lambda s, d: _profile(s, d).select("node", "t", F.round(F.col("size") - F.coalesce(F.lag("size").over(_by_time()), F.lit(0.0)), 6).alias("grown"))
)
query(
    "profile_lead_first_last",
    f"{_P9} SELECT node, t, round(lead(size) OVER w, 6) AS following, round(first_value(size) OVER w, 6) AS smallest, round(last_value(size) OVER u, 6) AS largest, round(nth_value(size, 2) OVER u, 6) AS second FROM profile WINDOW w AS (PARTITION BY node ORDER BY t), u AS (PARTITION BY node ORDER BY t ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
)(
    lambda s, d: (lambda u: rounded(_profile(s, d).select("node", "t", F.lead("size").over(_by_time()).alias("following"), F.first("size").over(_by_time()).alias("smallest"), F.last("size").over(u).alias("largest"), F.nth_value("size", 2).over(u).alias("second")), ["following", "smallest", "largest", "second"]))(
        _by_time().rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    )
)
_C9 = f"{S.exact_counts('g9')}"
query("running_ball_size", f"{_C9} SELECT node, t, sum(n) OVER (PARTITION BY node ORDER BY t ROWS UNBOUNDED PRECEDING) AS size FROM counts")(
    lambda s, d: counts_of(s, d, "g9").select("node", "t", F.sum("n").over(_by_time().rowsBetween(Window.unboundedPreceding, 0)).alias("size"))
)
query("moving_gain", f"{_C9} SELECT node, t, round(avg(n / (t + 1)) OVER (PARTITION BY node ORDER BY t ROWS BETWEEN 1 PRECEDING AND 1 FOLLOWING), 6) AS gain FROM counts")(
    lambda s, d: counts_of(s, d, "g9").select("node", "t", F.round(F.avg(F.col("n") / (F.col("t") + 1)).over(_by_time().rowsBetween(-1, 1)), 6).alias("gain"))
)
query("range_frame_distance", f"{_C9} SELECT node, t, sum(n) OVER (PARTITION BY node ORDER BY t RANGE BETWEEN 2 PRECEDING AND CURRENT ROW) AS near FROM counts")(
    lambda s, d: counts_of(s, d, "g9").select("node", "t", F.sum("n").over(_by_time().rangeBetween(-2, 0)).alias("near"))
)

# --- scalar, array, map, JSON, date functions ----------------------------------------------

query("page_links", f"SELECT page_id, len(links)::INTEGER AS n, coalesce(links[1], '') AS first, coalesce(links[-1], '') AS last FROM {S._LINKS}")(
    lambda s, d: views.page_links(s, d).select("page_id", F.size("links").alias("n"), F.coalesce(F.get("links", F.lit(0)), F.lit("")).alias("first"), F.coalesce(F.try_element_at("links", F.lit(-1)), F.lit("")).alias("last"))
)
query("url_host", "SELECT regexp_extract(url, '://([^/?#]*)', 1) AS host, count(*) AS n FROM pages GROUP BY ALL")(lambda s, d: T(s, d, "pages").select(F.parse_url("url", F.lit("HOST")).alias("host")).groupBy("host").agg(F.count(F.lit(1)).alias("n")))
query("shingles8", f"SELECT item_id, count(*) AS n FROM {S._shingles('benchmark', 'item_id', 8)} GROUP BY item_id")(lambda s, d: views.shingles(T(s, d, "benchmark"), "item_id", "text", 8).groupBy("item_id").agg(F.count(F.lit(1)).alias("n")))
query("handoff_by_day", "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, count(*) AS n, count(DISTINCT user_id) AS users FROM events GROUP BY ALL")(
    lambda s, d: T(s, d, "events").groupBy(F.date_format(F.date_trunc("day", "ts"), "yyyy-MM-dd").alias("day")).agg(F.count(F.lit(1)).alias("n"), F.countDistinct("user_id").alias("users"))
)
query("orders_by_month", "SELECT strftime(o_orderdate, '%Y-%m') AS month, count(*) AS n, max(datediff('day', TIMESTAMP '1992-01-01', o_orderdate))::INTEGER AS days FROM orders GROUP BY ALL")(
    lambda s, d: T(s, d, "orders").groupBy(F.date_format("o_orderdate", "yyyy-MM").alias("month")).agg(F.count(F.lit(1)).alias("n"), F.max(F.datediff("o_orderdate", F.lit("1992-01-01").cast("date"))).alias("days"))
)
query("discount_table", "SELECT t::INTEGER AS t, round(1.0 / t, 9) AS reciprocal, round(1 / log2(t + 1), 9) AS logarithmic, round(1.0 / (t * t), 9) AS quadratic, 1.0::DOUBLE AS constant FROM (SELECT DISTINCT l_linenumber AS t FROM lineitem)")(
    lambda s, d: rounded(T(s, d, "lineitem").select(F.col("l_linenumber").alias("t")).distinct().select("t", *[M.DISCOUNTS[n](F.col("t")).alias(n) for n in ("reciprocal", "logarithmic", "quadratic", "constant")]), ["reciprocal", "logarithmic", "quadratic"], 9)
)
query("harmonic_from_array", f"{_C9} SELECT node, round(coalesce(sum(n / t) FILTER (WHERE t > 0), 0), 6) AS harmonic, max(t) AS last FROM counts GROUP BY node")(
    lambda s, d: counts_of(s, d, "g9").groupBy("node").agg(F.array_sort(F.collect_list(F.struct("t", "n"))).alias("steps")).select(
        "node", F.round(F.aggregate(F.filter("steps", lambda x: x["t"] > 0), F.lit(0.0), lambda a, x: a + x["n"] / x["t"]), 6).alias("harmonic"), F.element_at("steps", -1)["t"].alias("last")
    )
)
query("profile_array", f"{_P9} SELECT node, string_agg(t::VARCHAR, ',' ORDER BY t) AS ts, count(*)::INTEGER AS k FROM profile GROUP BY node")(
    lambda s, d: _profile(s, d).groupBy("node").agg(F.array_sort(F.collect_list("t")).alias("a")).select("node", F.array_join("a", ",").alias("ts"), F.size("a").alias("k"))
)
query("measures_map", f"{_MEASURES_G9} SELECT node, (closeness > 0)::INTEGER + (lin > 1)::INTEGER + (harmonic > 1)::INTEGER AS large FROM measures")(
    lambda s, d: _measures(s, d).select("node", F.size(F.map_filter(F.create_map(F.lit("closeness"), F.col("closeness"), F.lit("lin"), F.col("lin") - 1, F.lit("harmonic"), F.col("harmonic") - 1), lambda k, v: v > 0)).alias("large"))
)
query("event_props", "SELECT event_id, (props->>'$.k')::BIGINT AS k FROM events")(lambda s, d: T(s, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k")))
query("result_json", f"{_MEASURES_G9} SELECT node, '{{\"coreach\":' || coreach::BIGINT || '}}' AS j FROM measures")(lambda s, d: _measures(s, d).select("node", F.to_json(F.struct(F.col("coreach").cast("long").alias("coreach"))).alias("j")))
query("profile_struct", f"{_C9} SELECT node, max(t) AS t, arg_max(n, t) AS n FROM counts GROUP BY node")(lambda s, d: counts_of(s, d, "g9").groupBy("node").agg(F.max(F.struct("t", "n")).alias("m")).select("node", "m.t", "m.n"))


@query("register_assign", "SELECT user_id, (h >> 54)::INTEGER AS reg, (CASE WHEN h & 18014398509481983 = 0 THEN 55 ELSE 55 - length(bin(h & 18014398509481983)) END)::INTEGER AS rho FROM (SELECT DISTINCT user_id, ('0x' || substr(md5('0:' || user_id), 1, 15))::BIGINT AS h FROM events)")
def register_assign(s, d):
    """The SQL surface: functions that the optimiser inlines."""
    sketching.register_sql(s)
    T(s, d, "events").createOrReplaceTempView("events_of_users")
    return s.sql("SELECT user_id, hll_reg(h) AS reg, hll_rho(h) AS rho FROM (SELECT DISTINCT user_id, hll_hash(concat('0:', user_id)) AS h FROM events_of_users)")


@query("sql_discounted_gain", f"{_P9} SELECT node, round(coalesce(sum(n / log2(t + 1)) FILTER (WHERE t > 0), 0), 6) AS gain FROM counts GROUP BY node")
def sql_discounted_gain(s, d):
    sketching.register_sql(s)
    _profile(s, d).createOrReplaceTempView("ball_profile")
    return s.sql("SELECT node, round(coalesce(sum(CASE WHEN t > 0 THEN (size - before) * discount_log(t) END), 0), 6) AS gain FROM (SELECT node, t, size, coalesce(lag(size) OVER (PARTITION BY node ORDER BY t), 0) AS before FROM ball_profile) GROUP BY node")


@query("packed_estimate", f"{_P9} SELECT node, round(arg_max(size, t), 6) AS size FROM profile GROUP BY node")
def packed_estimate(s, d):
    """A vectorised function over packed counters equals the built-in path."""
    packed = pack_registers(sketch_of(s, d, "g9").registers().drop("run"), 64)
    return packed.select("node", F.round(estimate_packed(64)("regs"), 6).alias("size"))


@query("node_balls", f"{_P9} SELECT node, t, round(n, 6) AS grown FROM counts")
def node_balls(s, d):
    sketching.register_node_balls(s)
    _profile(s, d).groupBy("node").agg(F.collect_list(F.struct("t", "size")).alias("steps")).createOrReplaceTempView("profiles")
    return s.sql("SELECT node, b.t, round(b.grown, 6) AS grown FROM profiles, LATERAL node_balls(steps) b")


query("knn_graph", f"SELECT src, dst FROM ({S.ARCS['g12']})")(lambda s, d: views.vector_knn(s, d, 3))

# --- streams -------------------------------------------------------------------------------

query("stream_arcs", f"SELECT src, dst FROM ({S.ARCS['g4']})")(lambda s, d: ingest.stream_arcs(s, f"{d}/events.parquet"))
_DAY = "SELECT strftime(date_trunc('day', ts), '%Y-%m-%d') AS day, event_type, count(*) AS n FROM events GROUP BY ALL"
query("stream_degree_tumbling", _DAY)(
    lambda s, d: ingest.run_to_end(ingest.counts_by_window(ingest.event_stream(s, f"{d}/events.parquet"), "1 day"), "complete").select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n")
)
query("stream_degree_sliding", "SELECT strftime(start, '%Y-%m-%d %H') AS start, event_type, count(*) AS n FROM (SELECT event_type, unnest([time_bucket(INTERVAL 6 HOUR, ts) - i * INTERVAL 6 HOUR for i in range(4)]) AS start FROM events) GROUP BY ALL")(
    lambda s, d: ingest.run_to_end(ingest.counts_by_window(ingest.event_stream(s, f"{d}/events.parquet"), "1 day", "6 hours"), "complete").select(F.date_format("start", "yyyy-MM-dd HH").alias("start"), "event_type", "n")
)
query("stream_sessions", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), n AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, fresh DESC ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, count(DISTINCT k) AS sessions, count(*) AS n FROM n GROUP BY user_id")(
    lambda s, d: ingest.run_to_end(ingest.sessions(ingest.event_stream(s, f"{d}/events.parquet")), "complete").groupBy("user_id").agg(F.count(F.lit(1)).alias("sessions"), F.sum("n").alias("n"))
)
query("stream_distinct_users", ORACLES["hll_registers_events"])(lambda s, d: ingest.run_to_end(ingest.registers_by_type(ingest.event_stream(s, f"{d}/events.parquet")), "complete"))
query("stream_static_join", "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY ALL")(
    lambda s, d: ingest.run_to_end(ingest.event_stream(s, f"{d}/events.parquet").join(T(s, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id").groupBy("c_mktsegment").agg(F.count(F.lit(1)).alias("n")), "complete")
)
query("stream_dedupe", "SELECT DISTINCT event_id, user_id FROM events")(
    lambda s, d: ingest.run_to_end(ingest.event_stream(s, f"{d}/events.parquet").withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"))
)


_SNAPSHOT = {g: f"{S.sketch_counts(g)} SELECT (node >> 40)::INTEGER AS day, node & {(1 << 40) - 1} AS node, round(arg_max(size, t), 6) AS size FROM profile GROUP BY ALL" for g in ("days", "all_days")}


@query("snapshot_centrality", _SNAPSHOT["all_days"])
def snapshot_centrality(s, d):
    """Per day the coreachable estimates in that day's own graph."""
    return rounded(ingest.snapshot_centrality(T(s, d, "events")), ["size"])


@query("stream_snapshots", _SNAPSHOT["days"])
def stream_snapshots(s, d):
    """The same of error events from a stream: each batch brings the days that its events are of up to date."""
    return rounded(ingest.stream_snapshots(s, f"{d}/events.parquet", "event_type = 'error'"), ["size"])


@query("full_ranking_g2", f"{_MEASURES_G2} SELECT node, round(harmonic, 6) AS value, row_number() OVER (ORDER BY round(harmonic, 9) DESC, node) AS place FROM measures")
def full_ranking_g2(s, d):
    return rounded(M.ranking(rounded(_measures(s, d, "g2"), ["harmonic"], 9), "harmonic"), ["value"])


@query("stream_state_sizes", ORACLES["hll_count_users_by_type"])
def stream_state_sizes(s, d):
    """A counter of users for each type in a state of its own, read off at the end of each batch."""
    return rounded(ingest.run_to_end(ingest.counters_by_type(ingest.event_stream(s, f"{d}/events.parquet")), "update").groupBy("event_type").agg(F.max("size").alias("size")), ["size"])


@query("packed_union_by_brand", f"{S.sketch_counts('g2')}, last_of AS (SELECT p_brand, reg, max(rho) AS rho FROM registers JOIN part ON node = p_partkey GROUP BY ALL), s AS (SELECT p_brand, 64 - sum(1 - pow(2.0, -rho)) AS s, 64 - count(*) AS z FROM last_of GROUP BY p_brand) SELECT p_brand, round(CASE WHEN 0.709 * 4096 / s <= 160 AND z > 0 THEN 64 * ln(64.0 / z) ELSE 0.709 * 4096 / s END, 6) AS size FROM s")
def packed_union_by_brand(s, d):
    """A grouped aggregate over packed counters: how many nodes coreach any of a brand's."""
    packed = pack_registers(packed_balls(views.graph(s, d, "g2")).registers().drop("run"), 64)
    rows = packed.join(T(s, d, "part").select(F.col("p_partkey").alias("node"), "p_brand"), "node")
    return rows.groupBy("p_brand").agg(union_packed()("regs").alias("regs")).select("p_brand", F.round(estimate_packed(64)("regs"), 6).alias("size"))


@query("expand_registers_g9", ORACLES["ball_registers_g9"])
def expand_registers_g9(s, d):
    sketching.register_expand_registers(s)
    pack_registers(sketch_of(s, d, "g9").registers().drop("run"), 64).createOrReplaceTempView("packed_counters")
    return s.sql("SELECT node, e.reg, e.rho FROM packed_counters, LATERAL expand_registers(regs) e")
