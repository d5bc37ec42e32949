"""Groups of documents ask hash-partitioned tables: one compressed blob for each group and bucket."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

from geocentra.llm import blocks as B


def slices(part: np.ndarray, n: int) -> Iterator[tuple[int, slice]]:
    """The runs of an ascending array of part numbers."""
    edges = np.searchsorted(part, np.arange(n + 1))
    for k in np.flatnonzero(np.diff(edges)).tolist():
        yield k, slice(int(edges[k]), int(edges[k + 1]))


def doc_table(doc: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """First places and lengths of the runs in an array in which equal entries are adjacent."""
    if not len(doc):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    first = np.concatenate(([0], np.flatnonzero(doc[1:] != doc[:-1]) + 1))
    return first, np.diff(np.concatenate((first, [len(doc)])))


def ask(bucket_hash: np.ndarray, n_buckets: int, g: int, *columns: np.ndarray) -> list[tuple[int, int, bytes]]:
    """One blob for each bucket: hashes (ascending) and columns beside them."""
    bucket = B.bucket_of(bucket_hash, n_buckets)
    out = []
    for k, s in slices(bucket, n_buckets):
        # Ascending values share their leading bytes: planes of differences compress.
        step = np.diff(bucket_hash[s], prepend=np.uint64(0))
        planes = step.view(np.uint8).reshape(-1, 8)
        out.append((k, g, B.pack(*(np.ascontiguousarray(planes[:, i]) for i in range(8)), *(c[s] for c in columns))))
    return out


def asked_of(blob: bytes) -> tuple[np.ndarray, list[np.ndarray]]:
    arrays = B.unpack(blob)
    return np.cumsum(np.stack(arrays[:8], axis=1).view(np.uint64).ravel(), dtype=np.uint64), arrays[8:]


def requests(rows: list[tuple[int, int, bytes]]) -> pa.RecordBatch:
    bucket, g, blob = zip(*rows, strict=True) if rows else ((), (), ())
    return pa.RecordBatch.from_arrays([pa.array(bucket, pa.int32()), pa.array(g, pa.int64()), pa.array(blob, pa.binary())], names=["bucket", "g", "blob"])
