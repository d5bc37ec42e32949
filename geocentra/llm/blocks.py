"""Whole Arrow columns of text as numpy arrays: words, spans, rolling hashes, packed blobs.

Nothing here loops over words or bytes in Python. Working memory is bounded by
`CHUNK_BYTES` of text at a time (or by the longest single text, at 9 bytes a word).
"""

from __future__ import annotations

import contextlib
import ctypes
from collections.abc import Iterator

import numpy as np
import pyarrow as pa

CHUNK_BYTES = 4 << 20
HASH_SPAN = 1 << 18

U64 = np.uint64
_MASK64 = (1 << 64) - 1

# The white space of the word pattern [^\x20\x09-\x0D]+.
SPACE_BYTES = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)


def release() -> None:
    """Give memory that is free back to the machine: a Python worker otherwise keeps the most it ever used."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # only in the GNU C library
        ctypes.CDLL(None).malloc_trim(0)


def byte_table(separators: tuple[int, ...]) -> np.ndarray:
    table = np.ones(256, dtype=bool)
    table[list(separators)] = False
    return table


NON_SPACE = byte_table(SPACE_BYTES)
# Letters, digits and everything beyond ASCII: [^\x00-\x2F\x3A-\x60\x7B-\x7F]+ once lower-cased.
ALNUM = byte_table((*range(0x00, 0x30), *range(0x3A, 0x61), *range(0x7B, 0x80)))
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def text_block(column: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a string column and its n+1 offsets; a null is an empty text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks() if column.num_chunks != 1 else column.chunk(0)
    if isinstance(column, pa.ChunkedArray):
        column = pa.concat_arrays(column.chunks)
    if column.null_count:
        column = column.fill_null("" if pa.types.is_string(column.type) or pa.types.is_large_string(column.type) else b"")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    n = len(column)
    if n == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offs = np.frombuffer(offsets, dtype=np.int64 if wide else np.int32)[column.offset : column.offset + n + 1].astype(np.int64)
    raw = np.frombuffer(data, dtype=np.uint8)[offs[0] : offs[-1]] if data is not None and offs[-1] > offs[0] else np.zeros(0, np.uint8)
    return raw, offs - offs[0]


def chunks(batches: Iterator[pa.RecordBatch], text: str, limit: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """The batches cut between rows so that each piece has about `limit` bytes of text, one row at least."""
    for batch in batches:
        n = batch.num_rows
        if not n:
            continue
        _, offs = text_block(batch.column(text))
        at = 0
        while at < n:
            to = max(at + 1, int(np.searchsorted(offs, offs[at] + limit, side="right")) - 1)
            yield batch.slice(at, to - at)
            at = to


def gathered(batches: Iterator[pa.RecordBatch], text: str, limit: int) -> Iterator[list[pa.RecordBatch]]:
    """Lists of consecutive pieces of batches, each list of about `limit` bytes of text."""
    held, size = [], 0
    for piece in chunks(batches, text, limit):
        n = int(text_block(piece.column(text))[1][-1])
        if held and size + n > limit:
            yield held
            held, size = [], 0
        held.append(piece)
        size += n
    if held:
        yield held


def words(raw: np.ndarray, offs: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends (byte positions) of all words and, by text, the offsets into them. No word spans two texts."""
    keep = table[raw]
    n = len(raw)
    if n == 0:
        z = np.zeros(0, np.int64)
        return z, z, np.zeros(len(offs), np.int64)
    before = np.empty(n, bool)
    before[0] = False
    before[1:] = keep[:-1]
    inner = offs[(offs > 0) & (offs < n)]
    before[inner] = False
    starts = np.flatnonzero(keep & ~before)
    after = np.empty(n, bool)
    after[-1] = False
    after[:-1] = keep[1:]
    after[inner - 1] = False
    ends = np.flatnonzero(keep & ~after) + 1
    return starts, ends, np.searchsorted(starts, offs)


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit values (the public splitmix64 finaliser)."""
    h = h ^ (h >> U64(30))
    h = h * U64(0xBF58476D1CE4E5B9)
    h = h ^ (h >> U64(27))
    h = h * U64(0x94D049BB133111EB)
    return h ^ (h >> U64(31))


_POWERS: dict[tuple[int, int], np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64."""
    size = 1 << max(10, (n - 1).bit_length())
    if (base, size) not in _POWERS:
        full = np.full(size, base, dtype=U64)
        full[0] = 1
        _POWERS[(base, size)] = np.multiply.accumulate(full)
    return _POWERS[(base, size)][:n]


_BASE = 0x9E3779B97F4A7C15 | 1
_BASE_INV = pow(_BASE, -1, 1 << 64)
_ROLL = 0xD6E8FEB86659FD93 | 1
_ROLL_INV = pow(_ROLL, -1, 1 << 64)


def _span_sums(values: np.ndarray, first: np.ndarray, last: np.ndarray, base: int, inverse: int) -> np.ndarray:
    """For each span, sum of values[first + i] * base**i modulo 2**64. Spans must be in order of `first`."""
    out = np.empty(len(first), dtype=U64)
    at = 0
    n = len(first)
    while at < n:
        lo = int(first[at])
        to = max(at + 1, int(np.searchsorted(first, lo + HASH_SPAN, side="left")))
        hi = int(last[at:to].max())
        sums = np.empty(hi - lo + 1, dtype=U64)
        sums[0] = 0
        np.cumsum(values[lo:hi].astype(U64) * powers(base, hi - lo), out=sums[1:])
        a, b = first[at:to] - lo, last[at:to] - lo
        out[at:to] = (sums[b] - sums[a]) * powers(inverse, int(a[-1]) + 1)[a]
        at = to
    return out


def word_hashes(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, second: bool = False) -> np.ndarray:
    """A 64-bit hash of each word: a polynomial over its bytes, scrambled with its length. The `second` has another base."""
    h = _span_sums(raw, starts, ends, *((_ROLL, _ROLL_INV) if second else (_BASE, _BASE_INV)))
    return mix(h + (ends - starts).astype(U64) * U64(0xA0761D6478BD642F))


def window_hashes(items: np.ndarray, width: int, second: bool = False) -> np.ndarray:
    """Rabin-Karp: the rolling hash of items[i : i + width] for every i, from prefix sums."""
    n = len(items) - width + 1
    if n <= 0:
        return np.zeros(0, U64)
    first = np.arange(n, dtype=np.int64)
    return mix(_span_sums(items, first, first + width, *((_BASE, _BASE_INV) if second else (_ROLL, _ROLL_INV))))


def ranges(first: np.ndarray, count: np.ndarray) -> np.ndarray:
    """first[0], first[0]+1, ... (count[0] of them), then first[1], ...: all ranges in one array."""
    total = int(count.sum())
    if not total:
        return np.zeros(0, np.int64)
    before = np.cumsum(count) - count
    return np.arange(total, dtype=np.int64) + np.repeat(first - before, count)


def window_starts(offsets: np.ndarray, width: int) -> np.ndarray:
    """Item positions at which a window of `width` items lies in one text."""
    return ranges(offsets[:-1], np.maximum(np.diff(offsets) - width + 1, 0))


def covered(starts: np.ndarray, ends: np.ndarray, n: int) -> np.ndarray:
    """Which of n positions lie in one of the spans starts[i] .. ends[i]-1."""
    steps = np.bincount(starts, minlength=n + 1) - np.bincount(ends, minlength=n + 1)
    return np.cumsum(steps[:n]) > 0


def runs_by_text(mask: np.ndarray, by_text: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts, ends and texts of the maximal runs of True; a run ends where its text ends."""
    if not len(mask):
        z = np.zeros(0, np.int64)
        return z, z, z
    new_text = np.zeros(len(mask) + 1, bool)
    new_text[by_text] = True
    first = np.flatnonzero(mask & (np.concatenate(([True], ~mask[:-1])) | new_text[:-1]))
    last = np.flatnonzero(mask & (np.concatenate((~mask[1:], [True])) | new_text[1:])) + 1
    return first, last, np.searchsorted(by_text, first, side="right") - 1


def joined(raw: np.ndarray, starts: np.ndarray, ends: np.ndarray, counts: np.ndarray) -> pa.Array:
    """Texts of counts[i] of the spans each, joined by one space."""
    size = ends - starts + 1
    total = int(size.sum())
    at = np.cumsum(size) - size
    out = np.full(total, 0x20, np.uint8)
    inside = np.ones(total, bool)
    inside[at + size - 1] = False
    out[inside] = raw[ranges(starts, ends - starts)]
    by_text = np.concatenate(([0], np.cumsum(counts)))
    bounds = np.concatenate((at, [total]))[by_text]
    # Each text's last space goes.
    last = bounds[1:][counts > 0] - 1
    whole = np.ones(total, bool)
    whole[last] = False
    lengths = np.diff(bounds) - (counts > 0)
    return strings(out[whole], np.concatenate(([0], np.cumsum(lengths))))


def without(raw: np.ndarray, offs: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> pa.Array:
    """The texts without the bytes starts[i] .. ends[i]-1."""
    keep = ~covered(starts, ends, len(raw))
    kept = np.concatenate(([0], np.cumsum(keep)))
    return strings(raw[keep], kept[offs])


def strings(raw: np.ndarray, offs: np.ndarray) -> pa.Array:
    return pa.Array.from_buffers(pa.string(), len(offs) - 1, [None, pa.py_buffer(np.ascontiguousarray(offs, dtype=np.int32)), pa.py_buffer(np.ascontiguousarray(raw))])


def span_lists(starts: np.ndarray, ends: np.ndarray, owner: np.ndarray, n: int) -> pa.Array:
    """n lists of (start, end) structs; owner, ascending, tells whose each is."""
    offs = np.searchsorted(owner, np.arange(n + 1)).astype(np.int32)
    items = pa.StructArray.from_arrays([pa.array(starts, pa.int64()), pa.array(ends, pa.int64())], names=["start", "end"])
    return pa.ListArray.from_arrays(pa.array(offs), items)


# --- blobs ---------------------------------------------------------------------------------

_CODEC = "zstd"


def pack(*arrays: np.ndarray) -> bytes:
    """Arrays as one blob. A trailing dimension is kept raw (hash bytes do not compress); others are compressed."""
    head, body = [len(arrays)], []
    for a in arrays:
        a = np.ascontiguousarray(a)
        data = a.tobytes()
        small = data if a.ndim == 2 or len(data) < 64 else pa.Codec(_CODEC, compression_level=1).compress(data, asbytes=True)
        kind = ord(a.dtype.char)
        head += [kind, a.shape[1] if a.ndim == 2 else 0, len(a), -1 if small is data else len(small)]
        body.append(small)
    return np.array(head, dtype=np.int32).tobytes() + b"".join(body)


def unpack(blob: bytes) -> list[np.ndarray]:
    view = memoryview(blob)
    n = int(np.frombuffer(view[:4], np.int32)[0])
    head = np.frombuffer(view[4 : 4 + 16 * n], np.int32).reshape(n, 4)
    at, out = 4 + 16 * n, []
    for kind, width, rows, small in head.tolist():
        dtype = np.dtype(chr(kind))
        size = dtype.itemsize * rows * max(1, width)
        if small < 0:
            data, at = view[at : at + size], at + size
        else:
            data, at = pa.Codec(_CODEC).decompress(view[at : at + small], decompressed_size=size), at + small
        a = np.frombuffer(data, dtype)
        out.append(a.reshape(rows, width) if width else a)
    return out


def sorted_with_index(h: np.ndarray) -> np.ndarray:
    """An order that brings equal hashes together, earlier positions first.

    The high bits of each hash and its position share one 64-bit key, which sorts
    several times faster than an indirect stable sort. Different hashes that agree in
    those bits may lie interleaved, so equal neighbours are certain to be equal, while
    (rarely) equal hashes may be apart; callers only use it to thin out repeats.
    """
    bits = max(1, int(len(h) - 1).bit_length())
    low = U64((1 << bits) - 1)
    key = (h & ~low) | np.arange(len(h), dtype=U64)
    key.sort()
    return (key & low).astype(np.int64)


def gaps(positions: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Ascending positions within each of several lists, as differences."""
    if not len(positions):
        return np.zeros(0, np.uint32)
    d = np.empty(len(positions), np.int64)
    d[0] = positions[0]
    d[1:] = positions[1:] - positions[:-1]
    first = (np.cumsum(counts) - counts)[counts > 0]
    d[first] = positions[first]
    return d.astype(np.uint16 if d.max() < 65536 else np.uint32)


def ungaps(differences: np.ndarray, counts: np.ndarray) -> np.ndarray:
    if not len(differences):
        return np.zeros(0, np.int64)
    total = np.cumsum(differences.astype(np.int64))
    first = (np.cumsum(counts) - counts)[counts > 0]
    base = total[first] - differences[first]
    return total - np.repeat(base, counts[counts > 0])


def low_bytes(h: np.ndarray, n: int = 7) -> np.ndarray:
    """The low n bytes of 64-bit values, one row each."""
    return np.ascontiguousarray(h).view(np.uint8).reshape(-1, 8)[:, :n]


def same_spans(raw: np.ndarray, a: np.ndarray, b: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Whether the `size` bytes from a and from b are equal, one by one."""
    out = np.ones(len(size), bool)
    step = 1 << 22
    end = np.cumsum(size)
    lo = 0
    while lo < len(size):
        hi = max(lo + 1, int(np.searchsorted(end, (end[lo - 1] if lo else 0) + step, side="right")))
        some = np.flatnonzero(size[lo:hi]) + lo
        if len(some):
            n = size[some]
            equal = raw[ranges(a[some], n)] == raw[ranges(b[some], n)]
            out[some] = np.logical_and.reduceat(equal, np.cumsum(n) - n)
        lo = hi
    return out


def from_bytes(rows: np.ndarray) -> np.ndarray:
    wide = np.zeros((len(rows), 8), np.uint8)
    wide[:, : rows.shape[1]] = rows
    return wide.view(U64).ravel()


def bucket_of(h: np.ndarray, n: int) -> np.ndarray:
    """A bucket in 0..n-1 from the high 32 bits: ascending hashes have ascending buckets."""
    return (((h >> U64(32)) * U64(n)) >> U64(32)).astype(np.int64)
