"""Exact repeated byte strings: breadth-first backward extension on Burrows-Wheeler transforms, stopped at a length.

Any repeated string of `length` bytes holds the same anchor in every text: its least
rolling hash of `ANCHOR` bytes. Anchors that several documents share name regions of
text, and regions that may repeat each other meet in one bucket, where a transform of
their bytes tells which strings of `length` bytes repeat.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from geocentra.llm import blocks as B
from geocentra.llm.exchange import ask, asked_of, doc_table, requests, slices
from geocentra.llm.plan import cut_by, load, parts_for, text_bytes

GROUP_BYTES = 8 << 20
BUCKET_BYTES = 24 << 20
PIECE_BYTES = 1 << 20
TRANSFORM_BYTES = 1 << 20
ANCHOR = 24
#: A route is split once this many documents share an anchor.
SPLIT = 1024


# --- the transform -------------------------------------------------------------------------


#: Symbols that one 64-bit key holds: 257 ** 7 < 2 ** 63.
KEY = 7


def _keys(text: np.ndarray, end: np.ndarray) -> np.ndarray:
    """The first KEY symbols of every suffix, up to its end mark, as one number."""
    n = len(text)
    place = np.arange(n)
    padded = np.concatenate((text, np.zeros(KEY, np.uint16))).astype(np.uint64)
    key = padded[:n].copy()
    for j in range(1, KEY):
        key = key * np.uint64(257) + np.where(place + j <= end, padded[j : j + n], np.uint64(0))
    return key


def _order(key: np.ndarray, end: np.ndarray, depth: int) -> np.ndarray:
    """Places of suffixes in order of their first `depth` symbols, up to their own end mark, by doubling from their keys."""
    n = len(key)
    place, h = np.arange(n), KEY
    order = np.argsort(key)
    while h < depth:
        ranked = key[order]
        new = np.ones(n, bool)
        new[1:] = ranked[1:] != ranked[:-1]
        if new.all():
            break
        rank = np.empty(n, np.uint64)
        rank[order] = np.cumsum(new).astype(np.uint64)
        after = np.zeros(n, np.uint64)
        after[:-h] = rank[h:]
        after[place + h > end] = 0
        key = rank * np.uint64(n + 1) + after
        order = np.argsort(key)
        h *= 2
    return order


def repeats(text: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """(order, new): suffixes in order, and where one does not share `length` symbols with the one before it.

    `text` is of bytes plus one, each segment ended by a 0. Common prefixes shorter
    than `length` are found by increasing value: a level holds the intervals of all
    strings of its length that end where the level before has told suffixes apart;
    extended to the left by each symbol before them they give the next level's, and
    the right end of each new interval is where suffixes part. Prefixes shorter than
    KEY are read off the keys, so the first level is that of KEY symbols.
    """
    n = len(text)
    ends = np.flatnonzero(text == 0)
    end = np.repeat(ends, np.diff(ends, prepend=-1))
    key = _keys(text, end)
    order = _order(key, end, length)
    before = text[order - 1]  # the transform; the first suffix has the last symbol, an end, before it
    # Where the suffix that starts one symbol earlier stands: by that symbol, then in the order that is.
    step = np.empty(n, np.int64)
    step[np.argsort(before, kind="stable")] = np.arange(n)
    before = before.astype(np.int64)
    ranked = key[order]
    new = np.ones(n + 1, bool)
    new[1:n] = ranked[1:] != ranked[:-1]
    if length <= KEY:
        raise ValueError(f"length must exceed {KEY}")
    part = np.zeros(n + 1, bool)
    part[1:n] = new[1:n] & (ranked[1:] // np.uint64(257) == ranked[:-1] // np.uint64(257))
    known = np.flatnonzero(new)
    hi = np.flatnonzero(part)
    lo = known[np.searchsorted(known, hi) - 1]
    for _ in range(KEY, length):
        size = hi - lo
        # Intervals of one suffix extend to one; others by each of their symbols.
        single = lo[size == 1]
        single = single[before[single] > 0]
        left, right = step[single], step[single] + 1
        many = size > 1
        if many.any():
            owner = np.repeat(np.arange(int(many.sum())), size[many])
            at = B.ranges(lo[many], size[many])
            symbol = before[at]
            use = symbol > 0
            to = step[at[use]]
            code = owner[use] * 257 + symbol[use]
            # Within an interval, equal symbols keep their order: the first and last of each are the new interval.
            if len(code):
                low = np.uint64((1 << max(1, int(len(code) - 1).bit_length())) - 1)
                packed = (code.astype(np.uint64) * (low + np.uint64(1))) | np.arange(len(code), dtype=np.uint64)
                packed.sort()
                pick = (packed & low).astype(np.int64)
                first, count = doc_table(code[pick])
                left = np.concatenate((left, to[pick[first]]))
                right = np.concatenate((right, to[pick[first + count - 1]] + 1))
        fresh = ~new[right]
        lo, hi = left[fresh], right[fresh]
        if not len(lo):
            break
        new[hi] = True
    return order, new[:n]


# --- anchors -------------------------------------------------------------------------------


def _slide(values: np.ndarray, width: int, pick) -> np.ndarray:
    """pick (minimum or maximum) of values[i : i + width] for every i that has them."""
    have, out = 1, values
    while 2 * have <= width:
        out = pick(out[:-have], out[have:])
        have *= 2
    return pick(out[: len(out) - (width - have)], out[width - have :]) if have < width else out


def anchors(raw: np.ndarray, offs: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Places and hashes of the anchors of all texts: in each string of `length` bytes, its least hashes of ANCHOR bytes."""
    starts = B.window_starts(offs, length)
    if not len(starts):
        return np.zeros(0, np.int64), np.zeros(0, np.uint64)
    h = B.window_hashes(raw, ANCHOR)
    rank = (h >> np.uint64(32)).astype(np.uint32) | np.uint32(1)
    width = length - ANCHOR + 1
    least = np.zeros(len(raw), np.uint32)
    least[starts] = _slide(rank, width, np.minimum)[starts]
    around = np.concatenate((np.zeros(width - 1, np.uint32), least))
    most = _slide(around, width, np.maximum)[: len(h)]
    at = np.flatnonzero((rank == most) & (most > 0))
    # Least hashes are small ones: scramble them again, so that they spread evenly.
    return at, B.mix(h[at]) & ~np.uint64(0xFF)


def _make_groups(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Numbered groups of texts, those with an id in its order."""
    task, k = TaskContext.get().partitionId(), 0
    for piece in B.chunks(batches, "text", GROUP_BYTES):
        ids = piece.column("id")
        order = np.argsort(ids.fill_null(np.iinfo(np.int64).max).to_numpy(), kind="stable")
        piece = piece.take(pa.array(order))
        raw, offs = B.text_block(piece.column("text"))
        known = piece.column("id").is_valid().to_numpy(zero_copy_only=False)
        blob = B.pack(piece.column("id").fill_null(0).to_numpy(), known.astype(np.uint8), np.diff(offs).astype(np.int32), raw)
        yield pa.RecordBatch.from_arrays([pa.array([(task << 24) + k], pa.int64()), pa.array([blob], pa.binary())], names=["g", "blob"])
        k += 1


class Group:
    def __init__(self, blob: bytes):
        self.ids, known, size, self.raw = B.unpack(blob)
        self.known = known.astype(bool)
        self.offs = np.concatenate(([0], np.cumsum(size.astype(np.int64))))

    def anchors(self, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Place, hash and text of every anchor; texts without an id have none."""
        places, hashes = [], []
        at, n = 0, int(self.known.sum())  # those without an id come last
        while at < n:
            to = max(at + 1, int(np.searchsorted(self.offs[: n + 1], self.offs[at] + PIECE_BYTES, side="right")) - 1)
            place, h = anchors(self.raw[self.offs[at] : self.offs[to]], self.offs[at : to + 1] - self.offs[at], length)
            places.append(place + self.offs[at])
            hashes.append(h)
            at = to
        place = np.concatenate(places) if places else np.zeros(0, np.int64)
        return place, np.concatenate(hashes) if hashes else np.zeros(0, np.uint64), np.searchsorted(self.offs, place, side="right") - 1


def _by_hash(group: Group, length: int) -> tuple[np.ndarray, ...]:
    """Anchors sorted by hash, then document; where a hash begins."""
    place, h, doc = group.anchors(length)
    order = np.lexsort((place, h))
    place, h, doc = place[order], h[order], doc[order]
    return place, h, doc, doc_table(h)[0]


def _ask_anchors(length: int, n_buckets: int):
    """Each distinct anchor of a group: in how many documents, and the least of their scrambled ids."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for g, blob in zip(batch.column("g").to_pylist(), batch.column("blob").to_pylist(), strict=True):
                B.release()
                group = Group(blob)
                _, h, doc, first = _by_hash(group, length)
                if not len(first):
                    continue
                other = np.ones(len(h), bool)
                other[1:] = (h[1:] != h[:-1]) | (group.ids[doc[1:]] != group.ids[doc[:-1]])
                count = np.add.reduceat(other.astype(np.int64), first)
                mark = (B.mix(group.ids[doc].view(np.uint64)) >> np.uint64(40)).astype(np.uint32)
                least = np.minimum.reduceat(mark, first)
                yield requests(ask(h[first], n_buckets, g, count.astype(np.int32), least.view(np.uint8).reshape(-1, 4)[:, :3]))

    return run


def _share(table: pa.Table) -> pa.Table:
    """One bucket of anchors: to each group, which of its anchors several documents share, and their route."""
    asked = [asked_of(b) for b in table.column("blob").to_pylist()]
    groups, bucket = table.column("g").to_numpy(), table.column("bucket")[0].as_py()
    h = np.concatenate([a[0] for a in asked])
    count = np.concatenate([a[1][0] for a in asked]).astype(np.int64)
    mark = B.from_bytes(np.concatenate([a[1][1] for a in asked])).astype(np.int64)
    who = np.repeat(np.arange(len(asked)), [len(a[0]) for a in asked])
    where = np.concatenate([np.arange(len(a[0])) for a in asked])
    order = np.argsort(h)
    first, _ = doc_table(h[order])
    total, least = np.add.reduceat(count[order], first), np.minimum.reduceat(mark[order], first)
    number = np.empty(len(h), np.int64)
    new = np.zeros(len(h), np.int64)
    new[first] = 1
    number[order] = np.cumsum(new) - 1
    live = np.flatnonzero(total[number] > 1)
    split = np.where(total > SPLIT, np.ceil(np.log2(np.maximum(total, 1) / SPLIT)), 0).astype(np.uint8)
    g, blob = [], []
    for i, s in slices(who[live], len(asked)):
        k = number[live[s]]
        g.append(int(groups[i]))
        blob.append(B.pack(B.gaps(where[live[s]], np.array([len(k)])), B.low_bytes(least[k].view(np.uint64), 3), split[k]))
    return pa.table({"g": pa.array(g, pa.int64()), "bucket": pa.array([bucket] * len(g), pa.int32()), "blob": pa.array(blob, pa.binary())})


def _send_regions(length: int, n_buckets: int):
    """The regions of text around shared anchors, by route; of equal regions only those of the smallest document.

    Blobs of two arrays or more carry regions; a later copy inside the group is told on as found (4 arrays).
    """

    def run(groups: pa.Table, answers: pa.Table) -> pa.Table:
        B.release()
        if not groups.num_rows or not answers.num_rows:
            return pa.Table.from_batches([requests([])])
        g, group = groups.column("g")[0].as_py(), Group(groups.column("blob")[0].as_py())
        place, h, doc, first = _by_hash(group, length)
        distinct = h[first]
        edges = dict(slices(B.bucket_of(distinct, n_buckets), n_buckets))
        route, live = np.zeros(len(distinct), np.uint64), np.zeros(len(distinct), bool)
        for k, blob in zip(answers.column("bucket").to_pylist(), answers.column("blob").to_pylist(), strict=True):
            gap, least, split = B.unpack(blob)
            at = edges[k].start + np.cumsum(gap.astype(np.int64))
            part = (distinct[at] >> np.uint64(8)) & ((np.uint64(1) << split.astype(np.uint64)) - np.uint64(1))
            route[at] = B.mix(B.from_bytes(least) | (part << np.uint64(24)))
            live[at] = True
        number = np.repeat(np.arange(len(first)), np.diff(np.concatenate((first, [len(h)]))))
        use = live[number]
        place, doc, route = place[use], doc[use], route[number[use]]
        order = np.argsort(place, kind="stable")
        place, doc, route = place[order], doc[order], route[order]
        if not len(place):
            return pa.Table.from_batches([requests([])])
        begin = np.maximum(place - (length - ANCHOR), group.offs[doc])
        end = np.minimum(place + length, group.offs[doc + 1])
        joins = np.zeros(len(place), bool)
        joins[1:] = (doc[1:] == doc[:-1]) & (route[1:] == route[:-1]) & (begin[1:] <= end[:-1])
        head = np.flatnonzero(~joins)
        tail = np.concatenate((head[1:], [len(place)])) - 1
        begin, end, doc, route = begin[head], end[tail], doc[head], route[head]
        # Of equal regions, only the smallest document's go on.
        ids = group.ids[doc]
        order, later = _copies(group.raw, begin, end - begin, route, ids)
        keep, late = np.sort(order[~later]), np.sort(order[later])
        bucket = B.bucket_of(route, n_buckets)
        out = []
        by = keep[np.argsort(bucket[keep], kind="stable")]
        for k, s in slices(bucket[by], n_buckets):
            r = by[s]
            text = group.raw[B.ranges(begin[r], end[r] - begin[r])]
            out.append((k, g, B.pack(route[r], ids[r], (begin[r] - group.offs[doc[r]]).astype(np.int32), (end[r] - begin[r]).astype(np.int32), text)))
        if len(late):
            f, c = doc_table(doc[late])
            out.append((g % n_buckets, g, B.pack(ids[late[f]], c.astype(np.int32), (begin[late] - group.offs[doc[late]]).astype(np.int32), (end[late] - begin[late]).astype(np.int32))))
        return pa.Table.from_batches([requests(out)])

    return run


def _copies(raw: np.ndarray, begin: np.ndarray, size: np.ndarray, route: np.ndarray, ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """An order of regions by content, and which of them, in it, equal the first of theirs, byte by byte, in a larger document."""
    same = B.word_hashes(raw, begin, begin + size) + route
    order = np.lexsort((begin, ids, same))
    f, c = doc_table(same[order])
    head = np.repeat(order[f], c)
    later = (ids[order] != ids[head]) & (size[order] == size[head]) & (route[order] == route[head])
    at = np.flatnonzero(later)
    later[at] = B.same_spans(raw, begin[order[at]], begin[head[at]], size[order[at]])
    return order, later


def _compare(length: int):
    """One bucket of regions: which starts of strings of `length` bytes also start in a smaller document."""

    def run(table: pa.Table) -> pa.Table:
        B.release()
        parts, found = [], []
        for g, blob in zip(table.column("g").to_pylist(), table.column("blob").to_pylist(), strict=True):
            arrays = B.unpack(blob)
            if len(arrays) == 4:
                ids, count, begin, size = arrays
                found.append((np.full(len(begin), g), np.repeat(ids, count), begin.astype(np.int64), begin.astype(np.int64) + size))
            else:
                parts.append((np.full(len(arrays[0]), g), *arrays))
        if parts:
            g, route, ids, begin, size, raw = (np.concatenate(x) for x in zip(*parts, strict=True))
            begin, size = begin.astype(np.int64), size.astype(np.int64)
            at = np.cumsum(size) - size
            # Copies of one region are one text of the smallest document's; the others' are repeats throughout.
            order, later = _copies(raw, at, size, route, ids)
            late = order[later]
            found.append((g[late], ids[late], begin[late], begin[late] + size[late]))
            kept = order[~later]
            kept = kept[np.argsort(route[kept], kind="stable")]
            f, c = doc_table(route[kept])
            several = np.repeat(np.maximum.reduceat(ids[kept], f) != np.minimum.reduceat(ids[kept], f), c) if len(f) else np.zeros(0, bool)
            kept = kept[several]
            for r in _batches(route[kept], size[kept]):
                found.append(_transformed(kept[r], g, ids, begin, size, at, raw, length))
        return _found(found)

    return run


def _batches(route: np.ndarray, size: np.ndarray) -> Iterator[slice]:
    """Whole routes together, up to TRANSFORM_BYTES, or one route."""
    first, count = doc_table(route)
    if not len(first):
        return
    total = np.add.reduceat(size, first)
    at = 0
    while at < len(first):
        to = max(at + 1, at + int(np.searchsorted(np.cumsum(total[at:]), TRANSFORM_BYTES, side="right")))
        yield slice(int(first[at]), int(first[to - 1] + count[to - 1]))
        at = to


def _transformed(rows: np.ndarray, g: np.ndarray, ids: np.ndarray, begin: np.ndarray, size: np.ndarray, at: np.ndarray, raw: np.ndarray, length: int) -> tuple[np.ndarray, ...]:
    """(group, document, begin, end) of the intervals that strings of a smaller document cover."""
    n = size[rows]
    text = np.zeros(int(n.sum()) + len(rows), np.uint16)
    first = np.cumsum(n + 1) - (n + 1)
    text[B.ranges(first, n)] = raw[B.ranges(at[rows], n)].astype(np.uint16) + 1
    order, new = repeats(text, length)
    segment = np.repeat(np.arange(len(rows), dtype=np.int32), n + 1)[order]
    run = np.cumsum(new)
    whole = order + length <= (first + n)[segment]
    order, segment, run = order[whole], segment[whole], run[whole]
    head, count = doc_table(run)
    doc = ids[rows][segment]
    late = doc > np.repeat(np.minimum.reduceat(doc, head), count) if len(doc) else np.zeros(0, bool)
    # Starts in a row become one interval; segments are apart by their end marks.
    start = np.sort(order[late])
    new = np.ones(len(start), bool)
    new[1:] = start[1:] != start[:-1] + 1
    a = np.flatnonzero(new)
    z = np.concatenate((a[1:], [len(start)])) - 1 if len(a) else a
    own = np.searchsorted(first, start[a], side="right") - 1
    shift = begin[rows][own] - first[own]
    return g[rows][own], ids[rows][own], start[a] + shift, start[z] + shift + length


def _found(found: list[tuple[np.ndarray, ...]]) -> pa.Table:
    g, blobs = [], []
    if found:
        group, doc, begin, end = (np.concatenate(x) for x in zip(*found, strict=True))
        order = np.lexsort((begin, doc, group))
        group, doc, begin, end = group[order], doc[order], begin[order], end[order]
        first, count = doc_table(group)
        for a, n in zip(first.tolist(), count.tolist(), strict=True):
            f, c = doc_table(doc[a : a + n])
            g.append(int(group[a]))
            blobs.append(B.pack(doc[a : a + n][f], c.astype(np.int32), B.gaps(begin[a : a + n], c), (end - begin)[a : a + n].astype(np.int32)))
    return pa.table({"g": pa.array(g, pa.int64()), "blob": pa.array(blobs, pa.binary())})


def _remove():
    def run(groups: pa.Table, late: pa.Table) -> pa.Table:
        B.release()
        names = ["id", "n_bytes", "n_removed", "spans", "kept"]
        if not groups.num_rows:
            z = np.zeros(0, np.int64)
            return pa.table([pa.array([], pa.int64())] * 3 + [B.span_lists(z, z, z, 0), pa.array([], pa.binary())], names=names)
        group = Group(groups.column("blob")[0].as_py())
        parts = [B.unpack(x) for x in late.column("blob").to_pylist()]
        doc, pos, wide = (np.concatenate([f(x) for x in parts]) if parts else np.zeros(0, np.int64) for f in (lambda x: np.repeat(x[0], x[1]), lambda x: B.ungaps(x[2], x[1].astype(np.int64)), lambda x: x[3].astype(np.int64)))
        order = np.argsort(doc, kind="stable")
        doc, pos, wide = doc[order], pos[order], wide[order]
        lo, hi = np.searchsorted(doc, group.ids, side="left"), np.searchsorted(doc, group.ids, side="right")
        count = np.where(group.known, hi - lo, 0)
        row = np.repeat(np.arange(len(group.ids)), count)
        at = B.ranges(lo, count)
        start = np.minimum(pos[at] + group.offs[row], group.offs[row + 1])
        gone = B.covered(start, np.minimum(start + wide[at], group.offs[row + 1]), len(group.raw))
        kept = np.concatenate(([0], np.cumsum(~gone)))
        a, z, owner = B.runs_by_text(gone, group.offs)
        size, n = np.diff(group.offs), np.diff(kept[group.offs])
        ids = pa.array(group.ids, mask=~group.known)
        offsets = pa.py_buffer(kept[group.offs].astype(np.int32))
        data = pa.Array.from_buffers(pa.binary(), len(n), [None, offsets, pa.py_buffer(np.ascontiguousarray(group.raw[~gone]))])
        return pa.table([ids, pa.array(size), pa.array(size - n), B.span_lists(a - group.offs[owner], z - group.offs[owner], owner, len(n)), data], names=names)

    return run


def suffix_dedup(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", length: int = 50) -> DataFrame:
    """Remove every byte covered by a string of `length` bytes that also starts in a document of a smaller id.

    Texts are UTF-8 bytes, matches do not cross texts, and strings are judged on the
    input. Returns id, n_bytes, n_removed, spans (maximal removed byte intervals) and
    kept (the remaining bytes).

    A null text is empty. Rows without an id cannot be ordered: they lose nothing and
    take nothing from others. Rows that repeat an id are versions of one document:
    they take nothing from each other, and what is found at a position holds for all of
    them. An empty table gives no rows.

    A group of texts sends each distinct anchor once, so an anchor that is everywhere
    costs one record a group; the regions of one with very many documents are spread
    over several routes. Copies of a region are compared once.
    """
    if length <= ANCHOR:
        raise ValueError(f"length must exceed {ANCHOR} bytes")
    spark = docs.sparkSession
    rows = docs.select(F.col(id_col).cast("long").alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    n_buckets = parts_for(spark, text_bytes(rows, "text"), BUCKET_BYTES)
    groups = cut_by(rows.mapInArrow(_make_groups, "g long, blob binary"), n_buckets, "g")
    asked = groups.mapInArrow(_ask_anchors(length, n_buckets), "bucket int, g long, blob binary")
    shared = asked.groupBy("bucket").applyInArrow(_share, "g long, bucket int, blob binary")
    regions = groups.groupBy("g").cogroup(shared.groupBy("g")).applyInArrow(_send_regions(length, n_buckets), "bucket int, g long, blob binary")
    late = regions.groupBy("bucket").applyInArrow(_compare(length), "g long, blob binary")
    spans = "array<struct<start:long,end:long>>"
    return groups.groupBy("g").cogroup(late.groupBy("g")).applyInArrow(_remove(), f"id long, n_bytes long, n_removed long, spans {spans}, kept binary")


ORACLE = r"""
WITH t AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS h FROM documents),
n AS (SELECT doc_id, h, (length(h) // 2)::BIGINT AS n FROM t),
windows AS (SELECT doc_id, i AS pos, substr(h, 2 * i + 1, 100) AS seq FROM (SELECT doc_id, h, unnest(range(0, n - 49)) AS i FROM n WHERE n >= 50)),
late AS (SELECT doc_id, pos FROM (SELECT doc_id, pos, min(doc_id) OVER (PARTITION BY seq) AS head FROM windows) WHERE doc_id > head),
runs AS (SELECT doc_id, pos, CASE WHEN pos - lag(pos) OVER w <= 50 THEN 0 ELSE 1 END AS fresh FROM late WINDOW w AS (PARTITION BY doc_id ORDER BY pos)),
spans AS (SELECT doc_id, min(pos) AS a, max(pos) + 50 AS z FROM (SELECT doc_id, pos, sum(fresh) OVER (PARTITION BY doc_id ORDER BY pos) AS k FROM runs) GROUP BY doc_id, k),
rest AS (SELECT doc_id, a, z, coalesce(lag(z) OVER w, 0) AS before, lead(a) OVER w IS NULL AS last FROM spans WINDOW w AS (PARTITION BY doc_id ORDER BY a)),
kept AS (SELECT n.doc_id, count(r.a) AS n_spans, coalesce(sum(r.z - r.a), 0)::BIGINT AS n_removed,
  CASE WHEN count(r.a) = 0 THEN any_value(n.h) ELSE string_agg(substr(n.h, 2 * r.before + 1, 2 * (r.a - r.before)) || CASE WHEN r.last THEN substr(n.h, 2 * r.z + 1) ELSE '' END, '' ORDER BY r.a) END AS h
  FROM n LEFT JOIN rest r ON n.doc_id = r.doc_id GROUP BY n.doc_id)
SELECT n.doc_id, n.n AS n_bytes, k.n_removed, k.n_spans, sha256(unhex(k.h)) AS kept_sha256 FROM n JOIN kept k ON n.doc_id = k.doc_id
"""


def op6_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = suffix_dedup(load(spark, sf_dir, "documents"))
    return got.select(F.col("id").alias("doc_id"), "n_bytes", "n_removed", F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))
