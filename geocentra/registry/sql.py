"""DuckDB SQL that answers the same questions by another route: materialised balls instead of propagated registers."""

from __future__ import annotations

from geocentra.graph.model import KINDS
from geocentra.sketch.registers import MD5_BITS, alpha, log2_registers


def kind(name: str, key: str) -> str:
    return f"({KINDS[name]}::BIGINT * {1 << 56} + {key}::BIGINT)"


def text_id(name: str, text: str) -> str:
    return kind(name, f"('0x' || substr(md5({text}), 1, 14))::BIGINT")


def _succession(source: str, group: str, order: str, node: str, where: str = "true") -> str:
    return f"SELECT DISTINCT src, dst FROM (SELECT {node} AS src, lead({node}) OVER (PARTITION BY {group} ORDER BY {order}) AS dst FROM {source} WHERE {where}) WHERE dst IS NOT NULL AND src <> dst"


_LINKS = "(SELECT page_id, url, regexp_extract_all(html, 'href=\"([^\"]*)\"', 1) AS links FROM pages)"
_LINES = "(SELECT DISTINCT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE length(line) >= 40)"


def _shingles(table: str, key: str, n: int) -> str:
    words = r"list_filter(regexp_split_to_array(lower(text), '[^\p{L}\p{N}]+'), lambda w: w <> '')"
    return f"(SELECT DISTINCT {key}, array_to_string(ws[i : i + {n - 1}], ' ') AS shingle FROM (SELECT {key}, ws, unnest(range(1, len(ws) - {n - 2})) AS i FROM (SELECT {key}, {words} AS ws FROM {table}) WHERE len(ws) >= {n}))"


ARCS: dict[str, str] = {
    "g1": _succession("lineitem", "l_orderkey", "l_linenumber, l_partkey, l_suppkey", "l_partkey"),
    "g2": _succession("lineitem", "l_orderkey", "l_linenumber, l_partkey, l_suppkey", "l_partkey", "l_returnflag = 'R' AND l_quantity <= 15"),
    "g3": f"SELECT DISTINCT {kind('customer', 'o_custkey')} AS src, {kind('supplier', 'l_suppkey')} AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey",
    "g4": _succession("events", "ts::DATE", "ts, event_id", "user_id"),
    "g5": _succession("events", "ts::DATE", "ts, event_id", "user_id", "event_type = 'error'"),
    "g6": f"SELECT DISTINCT {kind('page', 'page_id')} AS src, {text_id('term', 'link')} AS dst FROM (SELECT page_id, unnest(links) AS link FROM {_LINKS})",
    "g7": f"SELECT DISTINCT {text_id('host', 'host')} AS src, {text_id('term', 'link')} AS dst FROM (SELECT regexp_extract(url, '://([^/?#]*)', 1) AS host, unnest(links) AS link FROM {_LINKS})",
    "g8": f"SELECT DISTINCT a.page_id AS src, b.page_id AS dst FROM (SELECT page_id, unnest(links) AS link FROM {_LINKS}) a JOIN {_LINKS} b ON len(b.links) > 0 AND a.link = b.links[-1] WHERE a.page_id <> b.page_id",
    "g9": _succession("(SELECT conv_id, turn, CASE WHEN turn < 1000 THEN conv_id * 1000 + turn ELSE -(conv_id * 1048576 + turn) END AS node FROM conversations)", "conv_id", "turn", "node"),
    "g10": _succession(_LINES, "line", "doc_id", "doc_id"),
    "days": "SELECT DISTINCT src, dst FROM (SELECT day * 1099511627776 + user_id AS src, day * 1099511627776 + lead(user_id) OVER (PARTITION BY day ORDER BY ts, event_id) AS dst FROM (SELECT date_diff('day', DATE '1970-01-01', ts::DATE) AS day, user_id, ts, event_id FROM events WHERE event_type = 'error')) WHERE dst IS NOT NULL AND src <> dst",
    "all_days": "SELECT DISTINCT src, dst FROM (SELECT day * 1099511627776 + user_id AS src, day * 1099511627776 + lead(user_id) OVER (PARTITION BY day ORDER BY ts, event_id) AS dst FROM (SELECT date_diff('day', DATE '1970-01-01', ts::DATE) AS day, user_id, ts, event_id FROM events)) WHERE dst IS NOT NULL AND src <> dst",
    "g11": f"SELECT {kind('customer', 'c_custkey')} AS src, {kind('nation', 'c_nationkey')} AS dst FROM customer UNION SELECT {kind('supplier', 's_suppkey')}, {kind('nation', 's_nationkey')} FROM supplier UNION SELECT {kind('nation', 'n_nationkey')}, {kind('region', 'n_regionkey')} FROM nation",
    "g12": "WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: x::DOUBLE) AS v FROM embeddings), p AS (SELECT a.vec_id AS src, b.vec_id AS dst, round(list_dot_product(a.v, b.v) / (sqrt(list_dot_product(a.v, a.v)) * sqrt(list_dot_product(b.v, b.v))), 9) AS sim FROM v a JOIN v b ON a.vec_id <> b.vec_id) SELECT src, dst FROM (SELECT src, dst, row_number() OVER (PARTITION BY src ORDER BY sim DESC, dst) AS r FROM p) WHERE r <= 3",
    "g13": f"SELECT DISTINCT {kind('doc', 'doc_id')} AS src, {kind('item', 'item_id')} AS dst FROM {_shingles('documents', 'doc_id', 8)} d JOIN {_shingles('benchmark', 'item_id', 8)} i USING (shingle)",
}


def graph(g: str, direction: str = "in", symmetric: bool = False) -> str:
    """CTEs arcs(src, dst) in propagation order and nodes(id)."""
    arcs = ARCS[g]
    if symmetric:
        arcs = f"SELECT src, dst FROM ({arcs}) UNION SELECT dst, src FROM ({arcs})"
    if direction == "out":
        arcs = f"SELECT dst AS src, src AS dst FROM ({arcs})"
    return f"arcs AS MATERIALIZED ({arcs}), nodes AS (SELECT src AS id FROM arcs UNION SELECT dst FROM arcs)"


REACH = """reach(node, source, dist) USING KEY (node, source) AS (
  SELECT id, id, 0 FROM nodes
  UNION
  SELECT DISTINCT a.dst, r.source, r.dist + 1 FROM reach r JOIN arcs a ON a.src = r.node LEFT JOIN recurring.reach x ON x.node = a.dst AND x.source = r.source WHERE x.node IS NULL)"""


def pairs(g: str, direction: str = "in", symmetric: bool = False) -> str:
    """The start of a statement that has reach(node, source, dist): exact distances."""
    return f"WITH RECURSIVE {graph(g, direction, symmetric)}, {REACH}"


def exact_counts(g: str, direction: str = "in", weights: str | None = None, symmetric: bool = False) -> str:
    """... and counts(node, run, t, n)."""
    if weights is None:
        return f"{pairs(g, direction, symmetric)}, counts AS (SELECT node, 0 AS run, dist AS t, count(*)::DOUBLE AS n FROM reach GROUP BY ALL)"
    return f"{pairs(g, direction, symmetric)}, weights AS ({weights}), counts AS (SELECT node, 0 AS run, dist AS t, sum(coalesce(weight, 1))::DOUBLE AS n FROM reach LEFT JOIN weights w ON w.id = source GROUP BY ALL)"


def sketch_counts(g: str, p: int = 64, runs: int = 1, direction: str = "in", weights: str | None = None, symmetric: bool = False) -> str:
    """... and registers, profile(node, run, t, size) and counts, from the exact balls of every radius."""
    b = log2_registers(p)
    width = MD5_BITS - b
    replicas = f"SELECT id, run, run || ':' || id AS text FROM nodes, (SELECT unnest(range({runs})) AS run)"
    weighted = "" if weights is None else f"weights AS ({weights}),"
    if weights is not None:
        replicas = f"SELECT id, run, run || ':' || id || ':' || i AS text FROM (SELECT n.id, run, unnest(range(1, coalesce(w.weight, 1) + 1)) AS i FROM nodes n LEFT JOIN weights w ON w.id = n.id, (SELECT unnest(range({runs})) AS run))"
    return f"""{pairs(g, direction, symmetric)}, {weighted}
hashed AS (SELECT id, run, ('0x' || substr(md5(text), 1, 15))::BIGINT AS h FROM ({replicas})),
items AS (SELECT id, run, h >> {width} AS reg, CASE WHEN h & {(1 << width) - 1} = 0 THEN {width + 1} ELSE {width + 1} - length(bin(h & {(1 << width) - 1})) END AS rho FROM hashed),
met AS (SELECT r.node, i.run, i.reg, r.dist AS t, max(i.rho) AS rho FROM reach r JOIN items i ON i.id = r.source GROUP BY ALL),
risen AS (SELECT *, max(rho) OVER (PARTITION BY node, run, reg ORDER BY t ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS old FROM met),
registers AS (SELECT node, run, t, reg, rho, old FROM risen WHERE old IS NULL OR rho > old),
steps AS (SELECT node, run, t, sum(pow(2.0, -rho) - CASE WHEN old IS NULL THEN 1.0 ELSE pow(2.0, -old) END) AS ds, sum(CASE WHEN old IS NULL THEN 1 ELSE 0 END) AS dz FROM registers GROUP BY ALL),
sums AS (SELECT node, run, t, {p} + sum(ds) OVER w AS s, {p} - sum(dz) OVER w AS z FROM steps WINDOW w AS (PARTITION BY node, run ORDER BY t)),
profile AS (SELECT node, run, t, CASE WHEN {alpha(p) * p * p!r} / s <= {2.5 * p} AND z > 0 THEN {p} * ln({p}.0 / z) ELSE {alpha(p) * p * p!r} / s END AS size FROM sums),
counts AS (SELECT node, run, t, size - coalesce(lag(size) OVER (PARTITION BY node, run ORDER BY t), 0) AS n FROM profile)"""


MEASURES = """sums_of AS (SELECT node, run, sum(n * t) AS sum_dist, coalesce(sum(n / t) FILTER (WHERE t > 0), 0) AS harmonic, sum(n) AS coreach,
  coalesce(sum(n / log2(t + 1)) FILTER (WHERE t > 0), 0) AS logarithmic, coalesce(sum(n / (t * t)) FILTER (WHERE t > 0), 0) AS quadratic, coalesce(sum(n) FILTER (WHERE t > 0), 0) AS constant, coalesce(sum(n * pow(0.5, t)) FILTER (WHERE t > 0), 0) AS exponential
  FROM counts GROUP BY node, run),
measures AS (SELECT *, CASE WHEN sum_dist > 0 THEN 1 / sum_dist ELSE 0 END AS closeness, CASE WHEN sum_dist > 0 THEN coreach * coreach / sum_dist ELSE 1 END AS lin FROM sums_of)"""


def rounded(names: list[str], digits: int = 6) -> str:
    return ", ".join(f"round({n}, {digits}) AS {n}" for n in names)
