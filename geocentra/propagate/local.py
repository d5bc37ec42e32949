"""Rounds of graphs whose arcs fit in a task: all of them in memory, and tasks share the counters instead of the arcs.

Registers, patterns and sources do not depend on each other, so each task follows some
of them over the whole graph and no round costs a job. The arcs go to every task once.
Nothing is dropped and no number of rounds is assumed; larger graphs take the tables of
`fixpoint` or `packed`.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Arcs that a task holds; a graph of more takes the tables.
LOCAL_ARCS = 2 << 20
#: Bytes of counters, and of what arcs carry in a round, that a task holds at once.
TASK_BYTES = 32 << 20
#: Tasks for each core, so that uneven ones even out.
TASKS_A_CORE = 4
#: Rows of one batch of results.
OUT_ROWS = 1 << 16

CHANGES = "node long, run int, item long, value long, old long, t int"
PAIRS = "root long, found long, dist int"
COUNTS = "root long, t int, n long"
SUMS = "root long, sum_dist double, harmonic double, coreach double"
_ROW = "bucket int, kind int, node long, run int, item long, value long, a binary, b binary, c binary"


def packed_graph(arcs: DataFrame) -> DataFrame:
    """One row (a: nodes, b: places of each sender's arcs, c: receivers) from arcs (tx, rx)."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [(b.column("tx").to_numpy(), b.column("rx").to_numpy()) for b in batches if b.num_rows]
        tx, rx = (np.concatenate(x) for x in zip(*held, strict=True)) if held else (np.zeros(0, np.int64),) * 2
        nodes = np.unique(np.concatenate((tx, rx)))
        src, dst = np.searchsorted(nodes, tx), np.searchsorted(nodes, rx)
        order = np.argsort(src, kind="stable")
        places = np.concatenate(([0], np.cumsum(np.bincount(src, minlength=len(nodes)))))
        blobs = (nodes.astype(np.int64).tobytes(), places.astype(np.int64).tobytes(), dst[order].astype(np.int32).tobytes())
        yield pa.RecordBatch.from_arrays([pa.array([x], pa.binary()) for x in blobs], names=["a", "b", "c"])

    return arcs.where("tx is not null and rx is not null").select("tx", "rx").coalesce(1).mapInArrow(run, "a binary, b binary, c binary")


class LocalGraph:
    def __init__(self, nodes: bytes, places: bytes, receivers: bytes):
        self.nodes, self.places, self.receivers = np.frombuffer(nodes, np.int64), np.frombuffer(places, np.int64), np.frombuffer(receivers, np.int32)

    def index(self, nodes: np.ndarray) -> np.ndarray:
        """The places of nodes; -1 for those without an arc."""
        if not len(self.nodes):
            return np.full(len(nodes), -1, np.int64)
        at = np.minimum(np.searchsorted(self.nodes, nodes), len(self.nodes) - 1)
        return np.where(self.nodes[at] == nodes, at, -1)

    def columns(self, bytes_each: int) -> int:
        """How many values of so many bytes a node a task follows at once."""
        return max(1, TASK_BYTES // (bytes_each * max(1, len(self.nodes), len(self.receivers))))

    def unions(self, live: np.ndarray, values: np.ndarray, ufunc: np.ufunc) -> tuple[np.ndarray, np.ndarray]:
        """(receivers, what they get): the values of live senders, a row each, along their arcs."""
        count = self.places[live + 1] - self.places[live]
        ends = np.cumsum(count)
        if not len(ends) or not ends[-1]:
            return np.zeros(0, np.int64), values[:0]
        rx = self.receivers[np.repeat(self.places[live] - (ends - count), count) + np.arange(ends[-1])]
        order = np.argsort(rx, kind="stable")
        rx = rx[order]
        first = np.flatnonzero(np.diff(rx, prepend=-1))
        got = values[np.repeat(np.arange(len(live)), count)[order]]
        return rx[first].astype(np.int64), got if len(first) == len(rx) else ufunc.reduceat(got, first, axis=0)


def dealt(seeds: DataFrame, blob: DataFrame, tasks: int, run, schema: str, whole_runs: bool = False) -> DataFrame:
    """Seeds (node, run, item, value), dealt by run and item, or by run alone, to a function of a task's rows; the graph's row comes first."""
    null = lambda kind: F.lit(None).cast(kind)
    bucket = F.pmod(F.col("run") if whole_runs else F.xxhash64("run", "item"), F.lit(tasks)).cast("int")
    rows = seeds.select(bucket.alias("bucket"), F.lit(1).alias("kind"), "node", "run", "item", "value", *(null("binary").alias(x) for x in "abc"))
    graph = blob.select(F.explode(F.sequence(F.lit(0), F.lit(tasks - 1))).alias("bucket"), F.lit(0).alias("kind"), null("long").alias("node"), null("int").alias("run"), null("long").alias("item"), null("long").alias("value"), "a", "b", "c")
    return rows.unionByName(graph).repartition(tasks, "bucket").sortWithinPartitions("bucket", "kind").groupBy("bucket").applyInArrow(run, schema)


def n_tasks(spark: SparkSession) -> int:
    return TASKS_A_CORE * max(1, spark.sparkContext.defaultParallelism)


def _taken(batches: Iterable[pa.RecordBatch]) -> tuple[LocalGraph, list[np.ndarray]]:
    """The graph, and node, run, item, value of the seeds."""
    graph, held = None, []
    for batch in batches:
        kind = batch.column("kind").to_numpy()
        if len(kind) and kind[0] == 0:
            graph = LocalGraph(*(batch.column(x)[0].as_py() for x in "abc"))
            batch, kind = batch.slice(1), kind[1:]
        if len(kind):
            held.append([batch.column(x).to_numpy(zero_copy_only=False).astype(np.int64) for x in ("node", "run", "item", "value")])
    return graph, [np.concatenate(x) for x in zip(*held, strict=True)] if held else [np.zeros(0, np.int64)] * 4


def _out(schema: str, parts: Iterable[tuple]) -> Iterator[pa.RecordBatch]:
    """Column arrays (an old of None: null) gathered into batches."""
    fields = [x.split() for x in schema.split(", ")]
    kinds = [{"long": pa.int64(), "int": pa.int32(), "double": pa.float64()}[k] for _, k in fields]
    held: list[tuple] = []
    size = 0

    def batch() -> pa.RecordBatch:
        columns = []
        for i, kind in enumerate(kinds):
            column = np.concatenate([np.broadcast_to(np.asarray(h[i]), len(h[0])) for h in held])
            columns.append(pa.array(column, mask=column == 0).cast(kind) if fields[i][0] == "old" else pa.array(column).cast(kind))
        return pa.RecordBatch.from_arrays(columns, names=[n for n, _ in fields])

    for part in parts:
        for lo in range(0, len(part[0]), OUT_ROWS):
            held.append(tuple(x[lo : lo + OUT_ROWS] if isinstance(x, np.ndarray) else x for x in part))
            size += len(held[-1][0])
            if size >= OUT_ROWS:
                yield batch()
                held, size = [], 0
    if size:
        yield batch()


def value_rounds(bits: bool, full: bool, last: bool):
    """Changes of counters whose values are above 0 and meet by maximum or bitwise or; with `last` only the values after the last round."""
    ufunc, dtype = (np.bitwise_or, np.int64) if bits else (np.maximum, np.uint8)

    def parts(graph: LocalGraph, seeds: list[np.ndarray]) -> Iterator[tuple]:
        node, turn, item, value = seeds
        if len(value) and (value.min() <= 0 or value.max() > np.iinfo(dtype).max):
            raise ValueError("a seed's value is out of range")
        keys, key = np.unique(np.stack((turn, item)), axis=1, return_inverse=True)
        nodes = np.unique(np.concatenate((graph.nodes, node)))  # with nodes that touch no arc
        at, inside = np.searchsorted(nodes, node), np.searchsorted(nodes, graph.nodes)
        width = graph.columns(np.dtype(dtype).itemsize)
        for lo in range(0, keys.shape[1], width):
            mine = (key >= lo) & (key < lo + width)
            turns, name = keys[:, lo : lo + width]
            state = np.zeros((len(nodes), len(turns)), dtype)
            ufunc.at(state, (at[mine], key[mine] - lo), value[mine].astype(dtype))
            row, col = np.nonzero(state)
            if not last:
                yield nodes[row], turns[col], name[col], state[row, col].astype(np.int64), np.zeros(len(row), np.int64), 0
            live, t = np.flatnonzero(state[inside].any(axis=1)), 0
            while len(live):
                t += 1
                rx, got = graph.unions(live, state[inside[live]], ufunc)
                rx = inside[rx]
                old = state[rx]
                new = ufunc(old, got)
                row, col = np.nonzero(new != old)
                if not len(row):
                    break
                state[rx] = new
                if not last:
                    yield nodes[rx[row]], turns[col], name[col], new[row, col].astype(np.int64), old[row, col].astype(np.int64), t
                live = np.flatnonzero(state[inside].any(axis=1)) if full else np.searchsorted(inside, rx[np.flatnonzero(np.bincount(row, minlength=len(rx)))])
            if last:
                row, col = np.nonzero(state)
                yield nodes[row], turns[col], name[col], state[row, col].astype(np.int64), np.zeros(len(row), np.int64), t

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _out(CHANGES, parts(*_taken(batches)))

    return run


class Sums:
    """What distances of some roots add up to."""

    def __init__(self, roots: int):
        self.sum_dist, self.harmonic, self.coreach = np.zeros(roots), np.zeros(roots), np.zeros(roots)

    def add(self, t: int, n: np.ndarray) -> None:
        """So many nodes at distance t from each root."""
        self.sum_dist += n * float(t)
        self.harmonic += n / float(t) if t else 0.0
        self.coreach += n


class Outermost:
    """Of each root's pairs the one of the largest dist * step - found."""

    def __init__(self, roots: int, step: int):
        self.step, self.key = step, np.full(roots, np.iinfo(np.int64).min)
        self.found, self.dist = np.zeros(roots, np.int64), np.zeros(roots, np.int64)

    def meet(self, at: np.ndarray, found: np.ndarray, dist: np.ndarray | int) -> None:
        """At most one pair of each of the roots at these places."""
        key = dist * self.step - found
        more = key > self.key[at]
        for mine, new in ((self.key, key), (self.found, found), (self.dist, np.broadcast_to(dist, len(at)))):
            mine[at[more]] = new[more]


def visits(graph: LocalGraph, roots: np.ndarray, kind: str, step: int = 0) -> Iterator[tuple]:
    """Breadth-first visits from the roots, 64 in a word.

    `pairs`: root, found, dist of all that are reached; `counts`: root, t, n, how many at each distance;
    `sums`: root and what its distances add up to; `outermost`: of a root's pairs the one of the
    largest dist * step - found, and the nearest, which is the root itself.
    """
    index = graph.index(roots)
    alone = roots[index < 0]
    yield {"counts": (alone, 0, np.ones(len(alone), np.int64)), "sums": (alone, 0.0, 0.0, 1.0)}.get(kind, (alone, alone, 0))
    roots, index = roots[index >= 0], index[index >= 0]
    width = 64 * graph.columns(8)
    for lo in range(0, len(roots), width):
        names, start = roots[lo : lo + width], index[lo : lo + width]
        place = np.arange(len(names))
        seen = np.zeros((len(graph.nodes), -(-len(names) // 64)), np.uint64)
        seen[start, place // 64] = np.uint64(1) << (place % 64).astype(np.uint64)
        live, t = start, 0
        fresh = seen[live]
        sums, outermost = Sums(len(names)), Outermost(len(names), step)
        while len(live):
            found = np.zeros(64 * fresh.shape[1], np.int64)
            some = max(1, TASK_BYTES // (64 * fresh.shape[1]))
            for part in range(0, len(live), some):
                bits = np.unpackbits(fresh[part : part + some].view(np.uint8), axis=1, bitorder="little")
                if kind in ("counts", "sums"):
                    found += bits.sum(axis=0, dtype=np.int32)
                    continue
                row, col = np.nonzero(bits)
                if kind == "pairs":
                    yield names[col], graph.nodes[live[part : part + some][row]], t
                else:
                    # Nodes are in order, so that of a distance the smallest is met first.
                    hit, first = np.unique(col, return_index=True)
                    outermost.meet(hit, graph.nodes[live[part : part + some][row[first]]], t)
            if kind == "counts":
                hit = np.flatnonzero(found)
                yield names[hit], t, found[hit]
            sums.add(t, found[: len(names)])
            t += 1
            rx, got = graph.unions(live, fresh, np.bitwise_or)
            got = got & ~seen[rx]
            hit = got.any(axis=1)
            live, fresh = rx[hit], got[hit]
            seen[live] |= fresh
        if kind == "sums":
            yield names, sums.sum_dist, sums.harmonic, sums.coreach
        if kind == "outermost":
            yield names, names, 0
            apart = outermost.found != names
            yield names[apart], outermost.found[apart], outermost.dist[apart]
