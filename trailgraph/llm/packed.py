"""Packed shuffles: the entries (hash, document) of a chunk of texts travel as one binary row per bucket.

A row per entry would cost several times the text. A packed row holds, for one bucket of the hash
space and one chunk, the documents present (id, row key, entries each) and the entries' hashes, or
hashes and positions. Buckets are streamed: rows of one bucket arrive ordered by ``kind``, so a
reducer holds a table of the distinct hashes of one bucket and one row at a time.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

ROW = pa.schema([("bucket", pa.int32()), ("kind", pa.int32()), ("ids", pa.binary()), ("keys", pa.binary()), ("runs", pa.binary()), ("hashes", pa.binary()), ("spots", pa.binary())])
ROW_SQL = "bucket int, kind int, ids binary, keys binary, runs binary, hashes binary, spots binary"


def bucket_of(h: np.ndarray, buckets: int) -> np.ndarray:
    """From bits 40 to 63; the low bits tell entries of a bucket apart."""
    return ((h >> np.uint64(40)) * np.uint64(buckets) >> np.uint64(24)).astype(np.uint16 if buckets <= 1 << 16 else np.int32)


def planes(a: np.ndarray) -> bytes:
    """Bytes of an integer array by significance, which compresses better than in order."""
    return np.ascontiguousarray(a.view(np.uint8).reshape(len(a), -1).T).tobytes()


def unplanes(b: bytes, dtype) -> np.ndarray:
    size = np.dtype(dtype).itemsize
    return np.ascontiguousarray(np.frombuffer(b, np.uint8).reshape(size, -1).T).view(dtype).ravel()


class Packer:
    """Collects packed rows and hands them on as Arrow batches."""

    def __init__(self, buckets: int):
        self.buckets, self.rows, self.size = buckets, [], 0

    def add(self, kind: int, h: np.ndarray, doc: np.ndarray, ids: np.ndarray, keys: np.ndarray, wide: bool, spots: np.ndarray | None = None) -> None:
        """Entries with hash h[k] of the document numbered doc[k] (ascending), whose id is ids[doc[k]]; ``spots`` are unsigned and keep their width."""
        if not len(h):
            return
        b = bucket_of(h, self.buckets)
        order = np.argsort(b, kind="stable")
        b, doc = b[order], doc[order]
        h = h[order] if wide else h[order].astype(np.uint32)
        spots = spots[order] if spots is not None else None
        new = np.ones(len(b), bool)
        new[1:] = (b[1:] != b[:-1]) | (doc[1:] != doc[:-1])
        run = np.flatnonzero(new)
        length = np.diff(np.append(run, len(b))).astype(np.uint32)
        first = np.flatnonzero(np.append(True, b[1:] != b[:-1]))
        for i, j in zip(first, np.append(first[1:], len(b))):
            x, y = np.searchsorted(run, (i, j))
            d = doc[run[x:y]]
            row = (int(b[i]), kind, planes(ids[d]), planes(keys[d]) if keys is not None else b"", planes(length[x:y]), h[i:j].tobytes(), b"" if spots is None else planes(spots[i:j]))
            self.rows.append(row)
            self.size += 64 + sum(map(len, row[2:]))

    def take(self, least: int = 8 << 20) -> Iterator[pa.RecordBatch]:
        if self.rows and self.size >= least:
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*self.rows), ROW.types)], schema=ROW)
            self.rows, self.size = [], 0


class Table:
    """Distinct hashes of one bucket with the least document id seen for each and the ``check`` that came with it."""

    def __init__(self, dtype):
        self.h, self.lo, self.check = np.zeros(0, dtype), np.zeros(0, np.int64), np.zeros(0, np.uint32)
        self.waiting: list = []
        self.size = 0

    def add(self, h: np.ndarray, ids: np.ndarray, check: np.ndarray | None = None) -> None:
        self.waiting.append((h, ids, np.zeros(len(h), np.uint32) if check is None else check))
        self.size += len(h)
        if self.size > max(1 << 18, len(self.h)):
            self.settle()

    def settle(self) -> None:
        if not self.waiting:
            return
        h = np.concatenate([self.h, *(x[0] for x in self.waiting)])
        lo = np.concatenate([self.lo, *(x[1] for x in self.waiting)])
        check = np.concatenate([self.check, *(x[2] for x in self.waiting)])
        order = np.argsort(lo, kind="stable")
        order = order[np.argsort(h[order], kind="stable")]
        h = h[order]
        first = np.flatnonzero(np.append(True, h[1:] != h[:-1]))
        self.h, self.lo, self.check = h[first], lo[order[first]], check[order[first]]
        self.waiting, self.size = [], 0

    def find(self, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places of ``h`` in the table, and whether they are there."""
        self.settle()
        if not len(self.h):
            return np.zeros(len(h), np.int64), np.zeros(len(h), bool)
        at = np.minimum(np.searchsorted(self.h, h), len(self.h) - 1)
        return at, self.h[at] == h


def reduce_buckets(packed: DataFrame, width: int, reducer: Callable, schema: str) -> DataFrame:
    """Stream every bucket through a reducer that is made anew for each task.

    ``step(state, kind, ids, keys, runs, hashes, spots)`` and, at the end, ``finish()`` give
    RecordBatches; ``state`` is a dict that is new for every bucket and holds its number.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work, state, now = reducer(), {}, None
        for b in batches:
            for r in range(b.num_rows):
                bucket, kind, ids, keys, runs, hashes, spots = (b.column(c)[r].as_py() for c in range(7))
                if bucket != now:
                    state, now = {"bucket": bucket}, bucket
                ids, runs = unplanes(ids, np.int64), unplanes(runs, np.uint32)
                yield from work.step(state, kind, ids, unplanes(keys, np.int64) if keys else None, runs, hashes, unplanes(spots, f"u{len(spots) // int(runs.sum())}") if spots else None)
        yield from work.finish()

    return packed.repartition(width, "bucket").sortWithinPartitions("bucket", "kind").mapInArrow(run, schema)
