"""Packed rounds of a graph that fits in a task: a run's rounds are all one task's, and leave the rows that rounds of tables leave."""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from geocentra.propagate import blocks as K
from geocentra.propagate import local as L

#: `part` 0: changed counters of each round (with gains only what a round cost); 1: the last state.
ROW = f"{K.ROW}, seconds double, part int"
#: Bytes of counters in one row.
ROW_BYTES = 8 << 20


def _batch(row: tuple, seconds: float, part: int) -> pa.RecordBatch:
    batch = K.rows_of([row])
    return pa.RecordBatch.from_arrays([*batch.columns, pa.array([seconds]), pa.array([part], pa.int32())], names=[*batch.schema.names, "seconds", "part"])


def whole_runs(counter: K.Counter, size, gains: list | None, full: bool):
    """A task's runs, each from its seeds to the round that changes nothing; `gains` as in `packed_rounds`, without names."""

    def slices(turn: int, t: int, nodes: np.ndarray, regs: np.ndarray, s, z, carried, cost: tuple, part: int) -> Iterator[pa.RecordBatch]:
        got, grown, seconds = cost
        step = max(1, ROW_BYTES // counter.bytes)
        for lo in range(0, max(1, len(nodes)), step):
            blobs = [None if x is None else x[lo : lo + step].tobytes() for x in (nodes, regs, s, z, carried)]
            yield _batch((turn, t, turn, len(nodes[lo : lo + step]), got, grown, *blobs), seconds, part)
            got, grown, seconds = 0, 0.0, 0.0

    def one(graph: L.LocalGraph, turn: int, node: np.ndarray, item: np.ndarray, value: np.ndarray) -> Iterator[pa.RecordBatch]:
        began = time.time()
        nodes, at = np.unique(node, return_inverse=True)
        state = np.zeros((len(nodes), counter.width), counter.dtype)
        ufunc = np.bitwise_or if counter.bits else np.maximum
        ufunc.at(state, (at, item), value.astype(counter.dtype))
        # Places of the graph's nodes among those with a counter, and the other way round; -1: none.
        row = np.minimum(np.searchsorted(nodes, graph.nodes), len(nodes) - 1)
        row = np.where(nodes[row] == graph.nodes, row, -1)
        place = graph.index(nodes)
        s, z = counter.sums(state)
        carried, grown = None, 0.0
        if gains is not None:
            carried = np.zeros((len(nodes), len(gains) + 1))
            carried[:, 0] = size(s, z)
            grown = float(carried[:, 0].sum())

        def told(t: int, at: np.ndarray, s, z, got: int, grown: float) -> Iterator[pa.RecordBatch]:
            if gains is None:
                yield from slices(turn, t, nodes[at], state[at], s, z, None, (got, grown, time.time() - began), 0)
            else:
                yield _batch((turn, t, turn, len(at), got, grown, *[None] * 5), time.time() - began, 0)

        yield from told(0, np.arange(len(nodes)), s, z, 0, grown)
        everyone = place[place >= 0]
        live, t = everyone, 0
        while len(live):
            began = time.time()
            t += 1
            sent = state[row[live]]
            rose, got = np.zeros(len(nodes), bool), 0
            ends = np.cumsum(graph.places[live + 1] - graph.places[live])
            most, lo = max(1, L.TASK_BYTES // counter.bytes), 0
            while lo < len(live):
                hi = max(lo + 1, int(np.searchsorted(ends, (ends[lo - 1] if lo else 0) + most, side="right")))
                rx, union = graph.unions(live[lo:hi], sent[lo:hi], ufunc)
                lo = hi
                to = row[rx]
                if len(to) and to.min() < 0:
                    to, union = to[to >= 0], union[to >= 0]
                got += len(to) * (8 + counter.bytes)
                old = state[to]
                new = counter.meet(old, union)
                changed = (new != old).any(axis=1)
                state[to[changed]] = new[changed]
                rose[to[changed]] = True
            at = np.flatnonzero(rose)
            if not len(at):
                break
            s, z = counter.sums(state[at])
            grown = 0.0
            if gains is not None:
                now, was = size(s, z), carried[at, 0]
                grown = float((now - was).sum())
                carried[at, 1:] += np.outer(now - was, [float(f(t)) for f in gains])
                carried[at, 0] = now
            yield from told(t, at, s, z, got, grown)
            live = everyone if full else place[at][place[at] >= 0]
        yield from slices(turn, t, nodes, state, None, None, carried, (0, 0.0, 0.0), 1)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        graph, (node, turn, item, value) = L._taken(batches)
        for r in np.unique(turn).tolist():
            mine = turn == r
            yield from one(graph, r, node[mine], item[mine], value[mine])

    return run
