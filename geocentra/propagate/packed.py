"""Counters packed in blocks: the layout for large graphs and many registers.

Nodes are dealt once to blocks by a hash, and so are arcs, by their sender. Blocks are
rows of tables that are bucketed by block, so that neither the state nor the arcs are
ever shuffled again. In a round the blocks that hold changed counters meet their arcs
and send unions to the receivers' blocks, which are all that travels; a receiving block
streams its messages over its state and writes only counters that rose. Blocks that
nothing changed in are not read: their buckets are pruned.

Senders with very many arcs are spread: their arcs go to several blocks, and only their
own counter is sent there. The number of blocks follows from bytes and not from the
session, whose settings stay as they are: rounds run in a session of their own.
"""

from __future__ import annotations

import math
import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from geocentra.errors import ParameterError
from geocentra.graph.model import Graph
from geocentra.plans.checkpoint import delete_folder, own_folder
from geocentra.propagate import blocks as K
from geocentra.propagate import local as L
from geocentra.propagate import packed_local as W
from geocentra.propagate.balls import PATTERN_BIAS, pattern_seeds, rank_seeds
from geocentra.propagate.fixpoint import oriented
from geocentra.sketch.registers import alpha, estimate, log2_registers

#: Bytes of counters, and of arcs, that one block holds.
STATE_BYTES = 16 << 20
ARC_BYTES = 64 << 20
#: Below a block for each core, blocks hold at least so many bytes of counters or so many arcs.
SMALL_STATE, SMALL_ARCS = 256 << 10, 32 << 10
#: A sender of more arcs is spread over several blocks.
HUB_ARCS = 1 << 20
#: From so many blocks on, a round that few counters changed in looks first which blocks its messages reach.
TAIL_BLOCKS, TAIL_SHARE = 16, 0.02
#: Changed counters since the first table, as a share of it, and the tables they lie in, at which one table is made of all.
COMPACT_AT, MAX_TABLES = 0.5, 4

#: Bytes of counters, and of what all arcs carry, up to which a run's rounds are one task's (and no more arcs than HUB_ARCS).
LOCAL_BYTES = 64 << 20

Gain = Callable[[int], float]


@dataclass
class PackedRun:
    """What a run leaves: changed counters of each round, or only each node's sums; and what the rounds cost."""

    spark: SparkSession
    counter: K.Counter
    kind: str
    runs: int
    gains: list[str] | None
    rounds_at: list[str] = field(default_factory=list)
    state_at: list[str] = field(default_factory=list)
    seconds: list[float] = field(default_factory=list)
    changed: list[int] = field(default_factory=list)
    sent_bytes: list[int] = field(default_factory=list)
    grown: list[dict[int, float]] = field(default_factory=list)
    truncated: bool = False

    @property
    def p(self) -> int:
        return self.counter.width

    @property
    def rounds(self) -> PackedRun:
        return self

    @property
    def last(self) -> int:
        return len(self.seconds) - 1

    def _rows(self, paths: list[str]) -> DataFrame:
        return self.spark.read.schema(K.ROW).parquet(*paths).where("n > 0")

    def profile(self) -> DataFrame:
        """node, run, t, size: a row for t = 0 and for each later t at which a counter rose."""
        if self.gains is not None:
            raise ParameterError("a run that keeps sums has no profile")
        rows = self._rows(self.rounds_at).select("kind", "run", "a", "c", "d").mapInArrow(K.steps, "node long, run int, t int, s double, z int")
        return rows.select("node", "run", "t", size_of(F.col("s"), F.col("z"), self.counter, self.kind).alias("size"))

    def final(self) -> DataFrame:
        """node, run, item, value after the last round, of all that are not zero."""
        rows = self._rows(self.state_at)
        if len(self.state_at) > 1:
            rows = rows.repartition("block").sortWithinPartitions("block", "kind").groupBy("block").applyInArrow(K.fold(self.counter), K.ROW)
        return rows.select("run", "a", "b").mapInArrow(K.registers(self.counter), "node long, run int, item long, value long")

    def registers(self) -> DataFrame:
        """node, run, reg, rho of all registers that are not zero."""
        return self.final().select("node", "run", F.col("item").cast("int").alias("reg"), F.col("value").cast("int").alias("rho"))

    def sums(self) -> DataFrame:
        """node, run, coreach, sum_dist, harmonic and one column for each further gain."""
        if self.gains is None:
            raise ParameterError("this run keeps a profile, not sums")
        rows = self._rows(self.state_at).select("run", "a", "e").mapInArrow(K.sums, "node long, run int, sums array<double>")
        return rows.select("node", "run", *[F.get("sums", F.lit(i)).alias(n) for i, n in enumerate(["coreach", *self.gains])])

    def neighbourhood_function(self) -> DataFrame:
        """run, t, pairs within distance t: sums that rounds add up by block, for which no node keeps anything beside its counter."""
        if self.gains is None:
            raise ParameterError("this run keeps a profile, not sums")
        rows = [(r, t, sum(step.get(r, 0.0) for step in self.grown[: t + 1])) for t in range(len(self.grown)) for r in range(self.runs)]
        return self.spark.createDataFrame(rows, "run int, t int, pairs double")

    def stats(self) -> DataFrame:
        """t, changed counters, bytes of messages and seconds of every round."""
        rows = list(zip(range(len(self.seconds)), self.changed, self.sent_bytes, self.seconds, strict=True))
        return self.spark.createDataFrame(rows, "t int, changed long, sent_bytes long, seconds double")


def size_of(s: Column, z: Column, counter: K.Counter, kind: str) -> Column:
    if kind == "hll":
        return estimate(s, z, counter.width)
    size = F.pow(F.lit(2.0), s / counter.width) / PATTERN_BIAS
    return size * counter.width if kind == "fm_stochastic" else size


def _size(counter: K.Counter, kind: str):
    """The same on arrays."""
    p = counter.width

    def size(s: np.ndarray, z: np.ndarray) -> np.ndarray:
        if kind != "hll":
            return 2.0 ** (s / p) / PATTERN_BIAS * (p if kind == "fm_stochastic" else 1)
        raw = alpha(p) * p * p / s
        return np.where((raw <= 2.5 * p) & (z > 0), p * np.log(p / np.maximum(z, 1)), raw)

    return size


def n_blocks(state: int, arcs: int, seeds: int, cores: int) -> int:
    """Blocks for so many bytes of counters, arcs and seeds; not so many that messages between two of them become few."""
    large = math.ceil(max(state / STATE_BYTES, 12 * arcs / ARC_BYTES, 28 * seeds / ARC_BYTES))
    if large >= cores:
        return min(large, max(cores, math.isqrt(arcs // 64)), 100_000)
    return max(1, min(cores, math.ceil(max(state / SMALL_STATE, arcs / SMALL_ARCS))))


class _Tables:
    """Bucketed tables of a session of their own, in the shared folder."""

    def __init__(self, spark: SparkSession, name: str):
        self.folder, self.name, self.blocks = f"{own_folder(spark)}/{name}", name.replace("-", "_"), 1
        self.names: list[int] = []
        self.work = spark.newSession()
        # Rows, not columns: a union of columnar scans would not keep the tables' dealing.
        self.settings({"spark.sql.parquet.enableVectorizedReader": "false", "spark.sql.adaptive.enabled": "false", "spark.sql.unionOutputPartitioning": "true", "spark.sql.sources.bucketing.autoBucketedScan.enabled": "false", "spark.sql.execution.arrow.maxRecordsPerBatch": "16", "spark.sql.sources.bucketing.maxBuckets": "100000"})
        self.made: dict[str, str] = {}

    def settings(self, values: dict[str, str]) -> None:
        for key, value in values.items():
            self.work.conf.set(key, value)

    def path(self, name: str) -> str:
        return f"{self.folder}/{name}"

    def plain(self, name: str) -> DataFrame:
        return self.work.read.parquet(self.path(name))

    def rows(self, name: str) -> DataFrame:
        """A kept table read as plain files."""
        return self.work.read.schema(K.ROW).parquet(self.path(name))

    def keep(self, df: DataFrame, name: str) -> str:
        table = f"{self.name}_{name}"
        df.write.format("parquet").bucketBy(self.blocks, "block").option("path", self.path(name)).saveAsTable(table)
        self.made[name] = table
        return name

    def read(self, name: str, only: list[int] | None = None) -> DataFrame:
        rows = self.work.table(self.made[name])
        return rows if only is None else rows.where(F.col("block").isin(only))

    def by_block(self, tables: list[DataFrame], run, schema: str = K.ROW) -> DataFrame:
        """Tables of one dealing, their rows by kind, to a function of a block's rows: no shuffle.

        Where the session does not keep the dealing (no bucketed scans, other numbers of
        partitions), rows are dealt before they are sorted: dealt after it, they would
        lose their order by kind.
        """
        both = tables[0]
        for df in tables[1:]:
            both = both.unionByName(df)
        if both._jdf.queryExecution().executedPlan().outputPartitioning().getClass().getSimpleName() != "HashPartitioning":
            both = self.dealt(both)
        return both.sortWithinPartitions("block", "kind").groupBy("block").applyInArrow(run, schema)

    def dealt(self, df: DataFrame) -> DataFrame:
        return df.repartition(self.blocks, "block")

    def drop(self, name: str, files: bool) -> None:
        self.work.sql(f"DROP TABLE IF EXISTS {self.made.pop(name)}")
        if files:
            delete_folder(self.work, self.path(name))


_NAMES: dict[int, list[int]] = {}


def block_names(spark: SparkSession, n: int) -> list[int]:
    """n numbers of which each alone is dealt to one of n partitions, so that no task has two blocks while another has none."""
    if n not in _NAMES:
        tried = spark.range(int(n * (math.log(n) + 12)) + 1).select(F.col("id").cast("int").alias("name"))
        found = tried.groupBy(F.pmod(F.hash("name"), F.lit(n)).alias("part")).agg(F.min("name").alias("name")).orderBy("part").collect()
        if len(found) < n:
            raise RuntimeError(f"no names for {n} blocks")
        _NAMES[n] = [r["name"] for r in found]
    return _NAMES[n]


def _named(place: Column, names: list[int]) -> Column:
    return F.get(F.array(*[F.lit(x) for x in names]), place.cast("int")) if len(names) > 1 else F.lit(names[0])


def _block(column: str, names: list[int]) -> Column:
    return _named(F.pmod(F.xxhash64(column), F.lit(len(names))), names)


def packed_rounds(seeds: DataFrame, graph: Graph, counter: K.Counter, kind: str = "hll", runs: int = 1, direction: str = "in", propagation: str = "delta", max_iter: int | None = None, gains: dict[str, Gain] | None = None) -> PackedRun:
    """Grow seeds (node, run, item, value) along the arcs until a round changes nothing.

    Without `gains` every round's changed counters are kept, from which profiles are
    read. With gains (name: weight of a distance) each node carries one number for each
    of them, and for sum_dist and harmonic, which grow in the round itself; rounds
    leave nothing else behind. propagation="full" sends all counters in every round.
    """
    if propagation not in ("delta", "full"):
        raise ParameterError(f"propagation must be 'delta' or 'full', not {propagation!r}")
    spark = seeds.sparkSession
    tables = _Tables(spark, f"packed-{uuid.uuid4().hex}")
    named = None if gains is None else {"sum_dist": float, "harmonic": lambda t: 1.0 / t} | gains
    out = PackedRun(spark, counter, kind, runs, None if named is None else list(named))
    began = time.time()
    n_seeds, n, m = _written(tables, seeds, graph, direction)
    if max_iter is None and 0 < n_seeds and m <= HUB_ARCS and max(n, m) * counter.bytes <= LOCAL_BYTES:
        return _whole_runs(tables, out, named, propagation == "full")
    hubs = _deal(tables, counter, n_seeds, n * runs, m)
    size = _size(counter, kind)
    first = tables.by_block([tables.dealt(tables.plain("seeds").withColumns({"block": _block("node", tables.names), "kind": F.lit(0)}))], K.pack_seeds(counter))
    tables.settings({"spark.sql.execution.arrow.maxRecordsPerBatch": "65536"})
    tables.keep(first, "first")
    tables.settings({"spark.sql.execution.arrow.maxRecordsPerBatch": "16"})
    state = ["first"]
    if named is not None:
        # mapInArrow loses the dealing, so that the first rows are dealt once more.
        state = [tables.keep(tables.dealt(tables.read("first").mapInArrow(K.start_sums(size, len(named)), K.ROW)), "begun")]
    keep_all = named is None
    out.rounds_at.append(tables.path("first"))
    delta, since, t = state[0], 0, 0
    told, grown = _summary(tables, delta)
    n = sum(x[1] for x in told)
    out.seconds.append(time.time() - began)
    out.changed.append(n)
    out.sent_bytes.append(0)
    out.grown.append(grown)
    while n:
        if max_iter is not None and t >= max_iter:
            out.truncated = True
            break
        began = time.time()
        t += 1
        weights = None if named is None else np.array([float(f(t)) for f in named.values()])
        few = out.changed[-1] < TAIL_SHARE * n and tables.blocks >= TAIL_BLOCKS and propagation == "delta"
        messages = _messages(tables, counter, state if propagation == "full" else [delta], told, hubs, propagation)
        reached = None
        if few:
            tables.keep(messages, f"messages{t}")
            reached = sorted(r["block"] for r in tables.rows(f"messages{t}").select("block").distinct().collect())
            messages = tables.read(f"messages{t}", reached)
        rows = tables.by_block([*[tables.read(s, reached) for s in state], messages], K.receive(counter, t, size, weights))
        delta = tables.keep(rows, f"round{t}")
        if few:
            tables.drop(f"messages{t}", True)
        told, grown = _summary(tables, delta)
        changed = sum(x[1] for x in told)
        if not changed:
            tables.drop(delta, True)
            break
        out.seconds.append(time.time() - began)
        out.changed.append(changed)
        out.sent_bytes.append(sum(x[2] for x in told))
        out.grown.append(grown)
        if keep_all:
            out.rounds_at.append(tables.path(delta))
        state.append(delta)
        since += changed
        if since > COMPACT_AT * n or len(state) > MAX_TABLES:
            # What changed last is what is sent next, and stays.
            whole = tables.keep(tables.dealt(tables.by_block([tables.read(s) for s in state], K.fold(counter))), f"state{t}")
            _forget(tables, [s for s in state if s != delta], out, keep_all)
            state, since = [whole], 0
    if not keep_all and len(state) > 1:
        whole = tables.keep(tables.dealt(tables.by_block([tables.read(s) for s in state], K.fold(counter))), "sums")
        _forget(tables, state, out, keep_all)
        state = [whole]
    out.state_at = [tables.path(s) for s in state]
    for name in list(tables.made):
        tables.drop(name, files=tables.path(name) not in [*out.state_at, *(out.rounds_at if keep_all else [])])
    return out


def _forget(tables: _Tables, names: list[str], out: PackedRun, keep_all: bool) -> None:
    for name in names:
        if name in tables.made:
            tables.drop(name, files=not (keep_all and tables.path(name) in out.rounds_at))


def _written(tables: _Tables, seeds: DataFrame, graph: Graph, direction: str) -> tuple[int, int, int]:
    """Writes seeds and arcs as they come; returns how many seeds, nodes (about) and arcs."""
    typed = seeds.select(F.col("node").cast("long").alias("node"), F.col("run").cast("int").alias("run"), F.col("item").cast("long").alias("item"), F.col("value").cast("long").alias("value"))
    typed.write.parquet(tables.path("seeds"))
    oriented(graph, direction).where("tx is not null and rx is not null").write.parquet(tables.path("plain"))
    n_seeds = tables.plain("seeds").count()
    n = 0 if not n_seeds else tables.plain("seeds").agg(F.approx_count_distinct("node").alias("n")).first()["n"]
    return n_seeds, n, tables.plain("plain").count()


def _whole_runs(tables: _Tables, out: PackedRun, named: dict[str, Gain] | None, full: bool) -> PackedRun:
    """All rounds in tasks that each hold the arcs and some of the runs; no round is a job."""
    run = W.whole_runs(out.counter, _size(out.counter, out.kind), None if named is None else list(named.values()), full)
    arcs = tables.plain("plain").select(F.col("tx").cast("long").alias("tx"), F.col("rx").cast("long").alias("rx"))
    tables.settings({"spark.sql.execution.arrow.maxRecordsPerBatch": "65536"})
    L.packed_graph(arcs).write.parquet(tables.path("graph"))
    rows = L.dealt(tables.plain("seeds"), tables.plain("graph"), min(out.runs, L.n_tasks(tables.work)), run, W.ROW, whole_runs=True)
    rows.write.partitionBy("part").parquet(tables.path("runs"))
    cost = tables.work.read.schema(W.ROW.removesuffix(", part int")).parquet(tables.path("runs/part=0"))
    by_run = cost.groupBy("kind", "run").agg(*(F.sum(c).alias(c) for c in ("n", "got", "grown", "seconds"))).orderBy("kind", "run").collect()
    for r in by_run:
        if r["kind"] == len(out.seconds):
            for held, none in ((out.seconds, 0.0), (out.changed, 0), (out.sent_bytes, 0), (out.grown, {})):
                held.append(none)
        t = r["kind"]
        out.seconds[t] = max(out.seconds[t], r["seconds"])
        out.changed[t] += r["n"]
        out.sent_bytes[t] += r["got"]
        out.grown[t] = out.grown[t] | {r["run"]: r["grown"]}
    out.rounds_at, out.state_at = [tables.path("runs/part=0")], [tables.path("runs/part=1")]
    return out


def _deal(tables: _Tables, counter: K.Counter, n_seeds: int, n: int, m: int):
    """Writes the arcs in packed chunks by block of the sender; returns where hubs are."""
    work, arcs = tables.work, tables.plain("plain")
    tables.blocks = n_blocks(n * counter.bytes, m, n_seeds, work.sparkContext.defaultParallelism)
    tables.names = block_names(work, tables.blocks)
    tables.settings({"spark.sql.shuffle.partitions": str(tables.blocks), "spark.sql.execution.arrow.maxRecordsPerBatch": "65536"})
    hubs = None
    dealt = arcs.select("tx", "rx", _block("rx", tables.names).alias("rb"), _block("tx", tables.names).alias("block"))
    most = max(HUB_ARCS, m // (8 * tables.blocks))
    if m > most:
        # At most m / HUB_ARCS rows, and no more than eight times the blocks.
        wide = arcs.groupBy("tx").agg(F.count(F.lit(1)).alias("k")).where(F.col("k") > most).select(F.col("tx").alias("hub"), F.ceil(F.col("k") / most).cast("int").alias("parts"))
        wide.write.parquet(tables.path("hubs"))
        wide = tables.plain("hubs")
        if not wide.isEmpty():
            at = lambda part: _named(F.pmod(F.xxhash64("tx", part), F.lit(tables.blocks)), tables.names)
            part = F.pmod(F.xxhash64("rx"), F.col("parts")).cast("int")
            dealt = dealt.join(F.broadcast(wide), F.col("tx") == F.col("hub"), "left").select("tx", "rx", "rb", F.when(F.col("hub").isNull(), F.col("block")).otherwise(at(part)).alias("block"))
            places = wide.withColumnRenamed("hub", "tx").select("tx", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part")).select("tx", at(F.col("part")).alias("block")).distinct().orderBy("tx", "block").toArrow()
            hubs = work.sparkContext.broadcast((places.column("tx").to_numpy(), places.column("block").to_numpy()))
    # Each partition is one block. One number to sort by: the receiver's block, then a hash of the receiver.
    key = F.shiftleft(F.col("rb").cast("long"), 40) + F.pmod(F.xxhash64("rx"), F.lit(1 << 40))
    tables.keep(tables.dealt(dealt).withColumn("key", key).sortWithinPartitions("key").drop("key").mapInArrow(K.pack_arcs, K.ROW), "arcs")
    return hubs


def _summary(tables: _Tables, name: str) -> tuple[list[tuple[int, int, int]], dict[int, float]]:
    """(block, changed counters, bytes that came), and by run what all balls grew by: a row for each block and run, each met in one task."""
    rows = tables.rows(name).select("block", "run", "n", "got", "grown").collect()
    if len({(r["block"], r["run"]) for r in rows}) < len(rows):
        raise RuntimeError(f"a block of {name} was dealt to several tasks")
    grown: dict[int, float] = {}
    for r in rows:
        grown[r["run"]] = grown.get(r["run"], 0.0) + (r["grown"] or 0.0)
    return [(r["block"], r["n"], r["got"]) for r in rows], grown


def _messages(tables: _Tables, counter: K.Counter, sending: list[str], told: list[tuple[int, int, int]], hubs, propagation: str) -> DataFrame:
    live = sorted({b for b, n, _ in told if n})
    only = live if propagation == "delta" and 2 * len(live) <= tables.blocks else None
    rows = [tables.read(s, only).where("n > 0") for s in sending]
    sources = list(rows)
    if hubs is not None:
        only = None
        sources += [tables.dealt(r.mapInArrow(K.hub_rows(hubs), K.ROW)) for r in rows]
    sent = tables.by_block([*sources, tables.read("arcs", only)], K.send(counter))
    return tables.dealt(sent)


def packed_balls(graph: Graph, p: int = 64, runs: int = 1, direction: str = "in", hash: str = "md5", weighted: bool = False, propagation: str = "delta", max_iter: int | None = None, gains: dict[str, Gain] | None = None) -> PackedRun:
    """Ball sketches in the packed layout; parameters as those of ball_sketches. With `gains` (may be {}) sums instead of a profile."""
    log2_registers(p)
    return packed_rounds(rank_seeds(graph, p, runs, hash, weighted), graph, K.Counter(p), "hll", runs, direction, propagation, max_iter, gains)


def packed_patterns(graph: Graph, patterns: int = 32, runs: int = 1, direction: str = "in", averaging: str = "independent", propagation: str = "full", max_iter: int | None = None, gains: dict[str, Gain] | None = None) -> PackedRun:
    """The baseline of bit-pattern counters in the packed layout; parameters as those of pattern_balls."""
    seeds, kind = pattern_seeds(graph, patterns, runs, averaging)
    return packed_rounds(seeds, graph, K.Counter(patterns, bits=True), kind, runs, direction, propagation, max_iter, gains)
