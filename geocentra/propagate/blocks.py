"""Blocks of counters and blocks of arcs as numpy arrays: what one task of a packed round does.

A block of counters is a matrix with one row a node; a block of arcs is held by
receiver, receivers with most arcs first, so that the k-th arcs of all receivers are
one contiguous run: a union over all arcs is a few dozen whole-array operations.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

#: Arcs of one packed chunk, and the most that one receiver has in it before it is split in pieces.
CHUNK_ARCS = 1 << 20
PIECE_ARCS = 1024
#: Bytes of counters that are unioned at a time, so that they stay in the processor's cache.
CACHE_BYTES = 1 << 20
#: With fewer changed senders than this share of a chunk's, only their arcs are visited.
SPARSE_SHARE = 0.125
#: Rows of messages and of arcs come after all rows of state, whose kind is their round.
LATE = 1 << 30

ROW = "block int, kind int, run int, n long, got long, grown double, a binary, b binary, c binary, d binary, e binary"
_NAMES = ["block", "kind", "run", "n", "got", "grown", "a", "b", "c", "d", "e"]
_KINDS = [pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.float64(), *[pa.binary()] * 5]


@dataclass(frozen=True)
class Counter:
    """How counters look: `width` values a node, and how two of them meet."""

    width: int
    bits: bool = False

    @property
    def dtype(self) -> np.dtype:
        return np.dtype(np.uint64 if self.bits else np.uint8)

    @property
    def bytes(self) -> int:
        return self.width * self.dtype.itemsize

    def meet(self, a: np.ndarray, b: np.ndarray, out: np.ndarray | None = None) -> np.ndarray:
        return (np.bitwise_or if self.bits else np.maximum)(a, b, out=out)

    def meet_runs(self, rows: np.ndarray, first: np.ndarray) -> np.ndarray:
        return (np.bitwise_or if self.bits else np.maximum).reduceat(rows, first, axis=0)

    def matrix(self, blob: bytes) -> np.ndarray:
        return np.frombuffer(blob, self.dtype).reshape(-1, self.width)

    def sums(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """What sizes are read off: for ranks the sum of 2**-rank and the number of zeros; for patterns the sum of the places of the lowest zero bits."""
        s, z = np.empty(len(rows)), np.zeros(len(rows), np.int32)
        step = max(1, CACHE_BYTES // (8 * self.width))
        for lo in range(0, len(rows), step):
            part = rows[lo : lo + step]
            if self.bits:
                low = part & ~(part + np.uint64(1))
                s[lo : lo + step] = np.bitwise_count(low).sum(axis=1)
            else:
                s[lo : lo + step] = _HALVES[part].sum(axis=1)
                z[lo : lo + step] = (part == 0).sum(axis=1)
        return s, z


_HALVES = 2.0 ** -np.arange(256)


def rows_of(found: list[tuple]) -> pa.RecordBatch:
    columns = zip(*found, strict=True) if found else [()] * len(_NAMES)
    return pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(columns, _KINDS, strict=True)], names=_NAMES)


def in_order(rows: Iterable[dict]) -> Iterator[dict]:
    """A block's rows, which must come by kind: a counter that came after messages or arcs would be lost."""
    last = None
    for row in rows:
        if last is not None and row["kind"] < last:
            raise RuntimeError(f"block {row['block']}: a row of kind {row['kind']} comes after one of kind {last}")
        last = row["kind"]
        yield row


def each_row(batches: Iterable[pa.RecordBatch]) -> Iterator[dict]:
    for batch in batches:
        for i in range(batch.num_rows):
            yield {n: batch.column(n)[i].as_py() for n in _NAMES}


# --- packing -------------------------------------------------------------------------------


def pack_seeds(counter: Counter):
    """A block's seeds (node, run, item, value) as its first counters."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(batches))
        block = table.column("block")[0].as_py()
        node, turn, item, value = (table.column(c).to_numpy() for c in ("node", "run", "item", "value"))
        out = []
        for r in np.unique(turn).tolist():
            mine = turn == r
            nodes, at = np.unique(node[mine], return_inverse=True)
            regs = np.zeros((len(nodes), counter.width), counter.dtype)
            (np.bitwise_or if counter.bits else np.maximum).at(regs, (at, item[mine]), value[mine].astype(counter.dtype))
            s, z = counter.sums(regs)
            out.append((block, 0, r, len(nodes), 0, 0.0, nodes.tobytes(), regs.tobytes(), s.tobytes(), z.tobytes(), None))
        yield rows_of(out)

    return run


def pack_arcs(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Arcs (tx, rx, rb, block), those of a receiver together, in chunks of one block each."""
    held: list[pa.RecordBatch] = []
    size = 0
    for batch in batches:
        held.append(batch)
        size += batch.num_rows
        if size >= CHUNK_ARCS:
            yield from _chunks(held)
            held, size = [], 0
    if size:
        yield from _chunks(held)


def _chunks(held: list[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    table = pa.Table.from_batches(held)
    block = table.column("block").to_numpy()
    for one in np.unique(block).tolist():
        yield _packed(one, *(table.column(c).to_numpy()[block == one] for c in ("tx", "rx", "rb")))


def _packed(block: int, tx: np.ndarray, rx: np.ndarray, rb: np.ndarray) -> pa.RecordBatch:
    senders, src = np.unique(tx, return_inverse=True)
    new = np.ones(len(rx), bool)
    new[1:] = rx[1:] != rx[:-1]
    head = np.maximum.accumulate(np.where(new, np.arange(len(rx)), 0))
    new |= (np.arange(len(rx)) - head) % PIECE_ARCS == 0
    first = np.flatnonzero(new)
    count = np.diff(np.append(first, len(rx)))
    order = np.argsort(-count, kind="stable")
    place = np.empty(len(order), np.int64)
    place[order] = np.arange(len(order))
    piece = np.cumsum(new) - 1
    rank = np.arange(len(rx)) - first[piece]
    diagonal = np.lexsort((place[piece], rank))
    lengths = np.bincount(rank)
    at = first[order]
    return rows_of([(block, LATE, 0, len(rx), 0, 0.0, senders.tobytes(), src[diagonal].astype(np.uint32).tobytes(), rx[at].tobytes(), lengths.astype(np.int32).tobytes(), rb[at].astype(np.int32).tobytes())])


# --- state ---------------------------------------------------------------------------------


class State:
    """The counters of one block and run: a first table, and later rows that replace earlier ones."""

    def __init__(self, counter: Counter):
        self.counter = counter
        self.nodes: np.ndarray | None = None
        self.regs = self.carried = None
        self.own = False

    def add(self, row: dict) -> None:
        nodes, regs = np.frombuffer(row["a"], np.int64), self.counter.matrix(row["b"])
        carried = np.frombuffer(row["e"]).reshape(len(nodes), -1) if row["e"] is not None and len(nodes) else np.zeros((len(nodes), 0))
        if self.nodes is None:
            self.nodes, self.regs, self.carried = nodes, regs, carried
            return
        if carried.shape[1] != self.carried.shape[1]:  # a hub's copy comes without sums, and senders need none
            carried, self.carried = carried[:, :0], self.carried[:, :0]
        at = np.minimum(np.searchsorted(self.nodes, nodes), max(0, len(self.nodes) - 1))
        known = self.nodes[at] == nodes if len(self.nodes) else np.zeros(len(nodes), bool)
        self.writable()
        self.regs[at[known]], self.carried[at[known]] = regs[known], carried[known]
        if not known.all():
            every = np.concatenate((self.nodes, nodes[~known]))
            order = np.argsort(every, kind="stable")
            self.nodes = every[order]
            self.regs = np.concatenate((self.regs, regs[~known]))[order]
            self.carried = np.concatenate((self.carried, carried[~known]))[order]

    def writable(self) -> None:
        if not self.own:
            self.regs, self.carried, self.own = self.regs.copy(), self.carried.copy(), True


def _states(counter: Counter, rows: Iterable[dict]) -> tuple[dict[int, State], Iterator[dict]]:
    """The states by run, from the rows that come first, and the rows that follow them."""
    states: dict[int, State] = {}
    rows = in_order(rows)
    late: list[dict] = []
    for row in rows:
        if row["kind"] >= LATE:
            late.append(row)
            break
        if row["n"]:
            states.setdefault(row["run"], State(counter)).add(row)

    def following() -> Iterator[dict]:
        while late:
            yield late.pop()
        yield from rows

    return states, following()


# --- sending -------------------------------------------------------------------------------


def _chunk_union(counter: Counter, state: State, senders: np.ndarray, src: np.ndarray, lengths: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(pieces, counters): of the chunk's receiver pieces that changed senders reach, the unions of what these send."""
    none = np.zeros(0, np.int64), np.zeros((0, counter.width), counter.dtype)
    at = np.minimum(np.searchsorted(senders, state.nodes), len(senders) - 1)
    known = np.flatnonzero(senders[at] == state.nodes)
    if not len(known):
        return none
    at = at[known]
    starts = np.cumsum(lengths) - lengths
    if len(at) < SPARSE_SHARE * len(senders):
        row = np.full(len(senders), -1, np.int64)
        row[at] = known
        hit = np.flatnonzero((row >= 0)[src])
        if not len(hit):
            return none
        piece = hit - starts[np.searchsorted(starts, hit, side="right") - 1]
        order = np.argsort(piece, kind="stable")
        piece, rows = piece[order], row[src[hit[order]]]
        new = np.ones(len(piece), bool)
        new[1:] = piece[1:] != piece[:-1]
        first = np.flatnonzero(new)
        return piece[first], counter.meet_runs(state.regs[rows], first)
    table = np.zeros((len(senders), counter.width), counter.dtype)
    table[at] = state.regs[known]
    out = np.empty((int(lengths[0]), counter.width), counter.dtype)
    step = max(64, CACHE_BYTES // counter.bytes)
    for lo in range(0, len(out), step):
        mine = out[lo : lo + step]
        np.take(table, src[lo : lo + len(mine)], axis=0, out=mine, mode="clip")
        for start, n in zip(starts[1:].tolist(), lengths[1:].tolist(), strict=True):
            n = min(n, lo + len(mine)) - lo
            if n <= 0:
                break
            counter.meet(mine[:n], np.take(table, src[start + lo : start + lo + n], axis=0, mode="clip"), out=mine[:n])
    reached = np.arange(len(out)) if len(at) == len(senders) else np.flatnonzero(out.any(axis=1))
    return reached, out if len(reached) == len(out) else out[reached]


def send(counter: Counter):
    """One block of arcs and what its senders have to tell: messages to the blocks of the receivers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        states, arcs = _states(counter, each_row(batches))
        if not states:
            return
        for row in arcs:
            senders, src = np.frombuffer(row["a"], np.int64), np.frombuffer(row["b"], np.uint32)
            rx, lengths, rb = np.frombuffer(row["c"], np.int64), np.frombuffer(row["d"], np.int32).astype(np.int64), np.frombuffer(row["e"], np.int32)
            for turn, state in states.items():
                piece, regs = _chunk_union(counter, state, senders, src, lengths)
                if not len(piece):
                    continue
                node, to = rx[piece], rb[piece]
                order = np.lexsort((node, to))
                node, to, regs = node[order], to[order], regs[order]
                new = np.ones(len(node), bool)
                new[1:] = node[1:] != node[:-1]
                if not new.all():  # a receiver's pieces
                    first = np.flatnonzero(new)
                    node, to, regs = node[first], to[first], counter.meet_runs(regs, first)
                edges = np.append(np.flatnonzero(np.diff(to, prepend=-1)), len(to)).tolist()
                yield rows_of([(int(to[lo]), LATE, turn, hi - lo, 0, 0.0, node[lo:hi].tobytes(), regs[lo:hi].tobytes(), None, None, None) for lo, hi in zip(edges, edges[1:], strict=False)])

    return run


def hub_rows(hubs):
    """Of rows of state, those of hubs again for each block that holds some of a hub's arcs."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        nodes, blocks = hubs.value  # ascending; the same node once a block
        for row in each_row(batches):
            mine = np.frombuffer(row["a"], np.int64)
            at = np.minimum(np.searchsorted(mine, nodes), max(0, len(mine) - 1))
            hit = np.flatnonzero(mine[at] == nodes) if len(mine) else np.zeros(0, np.int64)
            regs = np.frombuffer(row["b"], np.uint8).reshape(len(mine), -1) if len(mine) else None
            for b in np.unique(blocks[hit]).tolist():
                k = at[hit[blocks[hit] == b]]
                yield rows_of([(b, row["kind"], row["run"], len(k), 0, 0.0, mine[k].tobytes(), regs[k].tobytes(), None, None, None)])

    return run


# --- receiving -----------------------------------------------------------------------------


def receive(counter: Counter, t: int, size, weights: np.ndarray | None):
    """One block's state and the messages to it: a row a run with the nodes whose counters rose.

    With `weights` (one for each sum that is kept), what the ball has grown by is added
    to a node's sums on the spot, times the weight of distance t; `size` gives sizes.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        states, messages = _states(counter, each_row(batches))
        rose: dict[int, np.ndarray] = {}
        got: dict[int, int] = {}
        block = None
        for row in messages:
            block, turn = row["block"], row["run"]
            got[turn] = got.get(turn, 0) + len(row["a"]) + len(row["b"])
            state = states.get(turn)
            if state is None:
                continue
            nodes, regs = np.frombuffer(row["a"], np.int64), counter.matrix(row["b"])
            at = np.minimum(np.searchsorted(state.nodes, nodes), len(state.nodes) - 1)
            known = state.nodes[at] == nodes
            if not known.all():
                at, regs = at[known], regs[known]
            old = state.regs[at]
            new = counter.meet(old, regs)
            changed = (new != old).any(axis=1)
            if changed.any():
                state.writable()
                state.regs[at[changed]] = new[changed]
                rose.setdefault(turn, np.zeros(len(state.nodes), bool))[at[changed]] = True
        out = []
        for turn in sorted(got):
            at = np.flatnonzero(rose[turn]) if turn in rose else np.zeros(0, np.int64)
            if not len(at):
                out.append((block, t, turn, 0, got[turn], 0.0, b"", b"", b"", b"", b""))
                continue
            state = states[turn]
            regs = state.regs[at]
            s, z = counter.sums(regs)
            carried, grown = None, 0.0
            if weights is not None:
                carried = state.carried[at]
                now = size(s, z)
                grown = float((now - carried[:, 0]).sum())
                carried[:, 1:] += np.outer(now - carried[:, 0], weights)
                carried[:, 0] = now
                carried = carried.tobytes()
            out.append((block, t, turn, len(at), got[turn], grown, state.nodes[at].tobytes(), regs.tobytes(), s.tobytes(), z.tobytes(), carried))
        yield rows_of(out)

    return run


def fold(counter: Counter):
    """One block's state as one row a run."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        block, states = None, {}
        for row in in_order(each_row(batches)):
            block = row["block"]
            if row["n"]:
                states.setdefault(row["run"], State(counter)).add(row)
        yield rows_of([(block, 0, turn, len(s.nodes), 0, 0.0, s.nodes.tobytes(), s.regs.tobytes(), None, None, s.carried.tobytes()) for turn, s in sorted(states.items())])

    return run


def start_sums(size, k: int):
    """The first rows with sizes and k sums of nothing yet."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in each_row(batches):
            carried = np.zeros((row["n"], k + 1))
            carried[:, 0] = size(np.frombuffer(row["c"]), np.frombuffer(row["d"], np.int32))
            row["grown"] = float(carried[:, 0].sum())
            yield rows_of([(*(row[n] for n in _NAMES[:-1]), carried.tobytes())])

    return run


# --- reading -------------------------------------------------------------------------------


def steps(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """node, run, t, s, z of rows (kind, run, a, c, d)."""
    for batch in batches:
        for t, turn, a, c, d in zip(*(batch.column(n).to_pylist() for n in ("kind", "run", "a", "c", "d")), strict=True):
            nodes = np.frombuffer(a, np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(np.full(len(nodes), turn, np.int32)), pa.array(np.full(len(nodes), t, np.int32)), pa.array(np.frombuffer(c)), pa.array(np.frombuffer(d, np.int32))], names=["node", "run", "t", "s", "z"])


def registers(counter: Counter):
    """node, run, item, value of all values that are not zero."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for turn, a, b in zip(*(batch.column(n).to_pylist() for n in ("run", "a", "b")), strict=True):
                nodes, regs = np.frombuffer(a, np.int64), counter.matrix(b)
                step = max(1, CACHE_BYTES // counter.bytes)
                for lo in range(0, len(nodes), step):
                    row, item = np.nonzero(regs[lo : lo + step])
                    value = regs[lo : lo + step][row, item].astype(np.int64)
                    yield pa.RecordBatch.from_arrays([pa.array(nodes[lo : lo + step][row]), pa.array(np.full(len(row), turn, np.int32)), pa.array(item), pa.array(value)], names=["node", "run", "item", "value"])

    return run


def sums(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """node, run, sums of rows (run, a, e)."""
    for batch in batches:
        for turn, a, e in zip(*(batch.column(n).to_pylist() for n in ("run", "a", "e")), strict=True):
            nodes, table = np.frombuffer(a, np.int64), np.frombuffer(e)
            width = len(table) // max(1, len(nodes))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(nodes) + 1, dtype=np.int32) * width), pa.array(table))
            yield pa.RecordBatch.from_arrays([pa.array(nodes), pa.array(np.full(len(nodes), turn, np.int32)), lists], names=["node", "run", "sums"])
