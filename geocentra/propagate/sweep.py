"""Exact distances in deep graphs without a cycle: nodes are passed once for many roots, not once a distance.

In an order in which all arcs lead onward, a node's distances from many roots are the
least of its senders' distances and one more: a row of numbers, one a root. A row is held
until the last of its receivers is passed. So a chain of any length costs a row a node,
where visits by distance cost a round a link. Components are passed one by one. Graphs with
a cycle, components whose paths are short, and orders that hold too many rows at once take
the visits of `local`; results are the same.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from geocentra.graph.components import smallest_of
from geocentra.propagate import local as L

#: A component with a path of so many arcs is passed in order.
DEEP = 128
#: Roots passed at once: at least, else visits are cheaper; and at most.
LEAST, MOST = 64, 4096
#: Bytes of rows held, as a multiple of a task's bytes.
HELD = 4
#: Rows handed on at once.
BLOCK = 64
#: The distance of what is not reached; it may grow by one a node.
FAR = 1 << 30


def onward(graph: L.LocalGraph, tx: np.ndarray) -> np.ndarray | None:
    """The place of each node in an order in which all arcs lead onward, or None."""
    n, rx = len(graph.nodes), graph.receivers
    if (tx < rx).all():
        return np.arange(n)
    if (tx > rx).all():
        return np.arange(n)[::-1]
    left, places, receivers = np.bincount(rx, minlength=n).tolist(), graph.places.tolist(), rx.tolist()
    ready, place, k = [x for x in range(n) if not left[x]], np.zeros(n, np.int64), 0
    while ready:
        x = ready.pop()
        place[x] = k
        k += 1
        for y in receivers[places[x] : places[x + 1]]:
            left[y] -= 1
            if not left[y]:
                ready.append(y)
    return place if k == n else None


class Order:
    """Deep components of a graph in an order in which arcs lead onward: where each begins and ends, and which row of the held ones a node takes."""

    def __init__(self, graph: L.LocalGraph):
        n = len(graph.nodes)
        self.deep, self.columns = np.zeros(n, bool), 0
        tx = np.repeat(np.arange(n), np.diff(graph.places))
        place = onward(graph, tx) if n else None
        if place is None:
            return
        component = smallest_of(tx, graph.receivers)[1]
        self.node = np.lexsort((place, component))
        self.place = np.empty(n, np.int64)
        self.place[self.node] = np.arange(n)
        a, b = self.place[tx], self.place[graph.receivers]
        by_receiver = np.lexsort((a, b))
        senders, at = a[by_receiver].tolist(), np.searchsorted(b[by_receiver], np.arange(n + 1)).tolist()
        self.senders = [senders[at[i] : at[i + 1]] for i in range(n)]
        depth = [0] * n
        for i, s in enumerate(self.senders):
            if s:
                depth[i] = 1 + max(depth[j] for j in s)
        inside = component[self.node]
        self.start = np.searchsorted(inside, inside)
        self.end = np.searchsorted(inside, inside, side="right")
        deepest = np.maximum.reduceat(depth, np.unique(self.start))
        self.depth = int(deepest.max())
        is_deep = np.repeat(deepest >= DEEP, np.diff(np.append(np.unique(self.start), n)))
        self.deep[self.node] = is_deep
        last = np.arange(n)
        np.maximum.at(last, a, b)
        done = np.argsort(last, kind="stable").tolist()
        last, free, rows, k = last.tolist(), [], [0] * n, 0
        self.held = 0
        for i, deep in enumerate(is_deep.tolist()):
            if deep:
                if free:
                    rows[i] = free.pop()
                else:
                    rows[i] = self.held
                    self.held += 1
            while k < n and last[done[k]] == i:
                if deep:
                    free.append(rows[done[k]])
                k += 1
        self.rows = rows
        self.columns = min(MOST, HELD * L.TASK_BYTES // (4 * max(1, self.held)))
        if self.columns < LEAST:
            self.deep[:] = False

    def passed(self, roots: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(places, distances from each of the roots, FAR if there is none) of what some root reaches. Roots are places in order, of one component."""
        lo, end, width = int(roots[0]), int(self.end[roots[0]]), len(roots)
        held, block = np.empty((self.held, width), np.int32), np.empty((BLOCK, width), np.int32)
        column = dict(zip(roots.tolist(), range(width), strict=True))
        reached, rows, some = bytearray(end - lo), self.rows, []
        for i in range(lo, end):
            live = [rows[j] for j in self.senders[i] if j >= lo and reached[j - lo]]
            root = column.get(i)
            if not live and root is None:
                continue
            row = held[rows[i]]
            if not live:
                row.fill(FAR)
            elif len(live) == 1:
                np.add(held[live[0]], 1, out=row)
            else:
                np.minimum(held[live[0]], held[live[1]], out=row)
                for j in live[2:]:
                    np.minimum(row, held[j], out=row)
                row += 1
            if root is not None:
                row[root] = 0
            reached[i - lo] = 1
            block[len(some)] = row
            some.append(i)
            if len(some) == BLOCK:
                yield np.array(some), block
                some = []
        if some:
            yield np.array(some), block[: len(some)]

    def batches(self, roots: np.ndarray) -> Iterator[np.ndarray]:
        """Places of roots (nodes of deep components), those of a component together."""
        places = np.sort(self.place[roots])
        for mine in np.split(places, np.flatnonzero(np.diff(self.start[places])) + 1):
            for lo in range(0, len(mine), self.columns):
                yield mine[lo : lo + self.columns]


def _pairs(order: Order, graph: L.LocalGraph, roots: np.ndarray) -> Iterator[tuple]:
    """A found node's pairs follow each other, in the order of roots: files keep both in few bytes."""
    names = graph.nodes[order.node[roots]]
    for places, block in order.passed(roots):
        row, col = np.nonzero(block < FAR)
        yield names[col], graph.nodes[order.node[places]][row], block[row, col]


def _sums(order: Order, graph: L.LocalGraph, roots: np.ndarray) -> L.Sums:
    sums = L.Sums(len(roots))
    # 1/t by t: nothing for a node itself, nor, in the last place, for what is not reached.
    far = order.depth + 1
    gain = np.zeros(far + 1)
    gain[1:far] = 1 / np.arange(1, far)
    for _, block in order.passed(roots):
        dist = np.minimum(block, far)
        reached = (dist < far).sum(axis=0)
        sums.sum_dist += dist.sum(axis=0, dtype=np.int64) - far * (len(dist) - reached)
        sums.harmonic += gain.take(dist).sum(axis=0)
        sums.coreach += reached
    return sums


def _outermost(order: Order, graph: L.LocalGraph, roots: np.ndarray, step: int) -> L.Outermost:
    outermost = L.Outermost(len(roots), step)
    none = np.iinfo(np.int64).min
    for places, block in order.passed(roots):
        found = graph.nodes[order.node[places]]
        key = block.astype(np.int64) * step - found[:, None]
        key[block >= FAR] = none
        at = np.flatnonzero(key.max(axis=0) > outermost.key)
        if len(at):
            best = key[:, at].argmax(axis=0)
            outermost.meet(at, found[best], block[best, at].astype(np.int64))
    return outermost


def visits(kind: str, schema: str, step: int = 0):
    """As `local.visits` for a task's rows. A root's visit is one task's, so that nothing is left to be added up."""

    def parts(graph: L.LocalGraph, seeds: list[np.ndarray]) -> Iterator[tuple]:
        roots = np.unique(seeds[0])
        if kind != "counts" and len(roots):
            order, index = Order(graph), graph.index(roots)
            deep = (index >= 0) & order.deep[index] if len(graph.nodes) else index >= 0
            for batch in order.batches(index[deep]) if deep.any() else ():
                names = graph.nodes[order.node[batch]]
                if kind == "pairs":
                    yield from _pairs(order, graph, batch)
                elif kind == "sums":
                    sums = _sums(order, graph, batch)
                    yield names, sums.sum_dist, sums.harmonic, sums.coreach
                else:
                    outermost = _outermost(order, graph, batch, step)
                    yield names, names, 0
                    apart = outermost.found != names
                    yield names[apart], outermost.found[apart], outermost.dist[apart]
            roots = roots[~deep]
        yield from L.visits(graph, roots, kind, step)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from L._out(schema, parts(*L._taken(batches)))

    return run
