"""Operator 7: benchmark decontamination by Wu-Manber multi-pattern search over words.

Patterns are the windows of ``WINDOW`` consecutive words of the benchmark's items (an item with fewer
words, but not none, is one pattern). For all patterns of one length m and blocks of B words a SHIFT
table says how far the search may move on: m - B + 1 for a block in no pattern, else the distance of its last occurrence from
the end. Where the shift is 0 the block's bucket of patterns is probed by hash and compared word by word. A text
without such a position is done; in the others most positions are skipped.

The patterns are broadcast in blocks of at most ``BLOCK_BYTES`` of item text: each block is built, searched in its own
pass and let go before the next, and the hits of a document are united by an aggregate. All tables are arrays of word
numbers: some 40 bytes a word of a block, 8 a byte of its text, and the block's vocabulary. An item longer than a
block is cut into overlapping pieces.

Defined cases: null and empty texts have no words and are clean; items without words have no pattern;
repeated items count by distinct item_id; rows that share an id are judged each for itself; texts
are searched whole. Null item_ids are passed over in ``items``. Empty tables give no rows, or no hits.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import chain, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from trailgraph.functions.runtime import materialize
from trailgraph.llm.textarrays import chunks, sums, windows

WINDOW, BLOCK_BYTES = 13, 16 << 20
_WORD_BYTES = b"0123456789abcdefghijklmnopqrstuvwxyz" + bytes(range(128, 256))
#: A-Z to lower case; every other byte that belongs to no word to a blank.
_FOLD = bytes(b if b in _WORD_BYTES else b + 32 if 65 <= b <= 90 else 32 for b in range(256))


def words_of(text: bytes) -> list[bytes]:
    return text.translate(_FOLD).split()


class _Patterns:
    """SHIFT table and suffix buckets of all patterns of ``m`` words, whose first words are at ``starts``."""

    def __init__(self, words: np.ndarray, base: int, m: int, starts: np.ndarray, items: np.ndarray, blocks: np.ndarray, shifts: np.ndarray):
        self.m, self.b, self.base, self.words = m, min(2, m), base, words
        order = np.lexsort((shifts, blocks))
        blocks, shifts = blocks[order], shifts[order]
        first = np.append(True, blocks[1:] != blocks[:-1])
        self.block, self.shift = blocks[first], shifts[first].astype(np.uint8)
        end = starts + m
        suffix = np.searchsorted(self.block, words[end - 1] if self.b == 1 else words[end - 2].astype(np.int64) * base + words[end - 1])
        h = windows(sums(words.astype(np.uint64) + np.uint64(1), 2), starts, end, 2)
        order = np.lexsort((items, starts, h, suffix))
        starts, items, h, suffix = starts[order], items[order], h[order], suffix[order]
        new = np.append(True, (h[1:] != h[:-1]) | (suffix[1:] != suffix[:-1]))
        for k in range(m):  # equal hashes are one pattern only if all words are equal
            new[1:] |= words[starts[1:] + k] != words[starts[:-1] + k]
        at = np.flatnonzero(new)
        self.start, self.hash, self.items = starts[at].astype(np.int32), h[at], items.astype(np.int32)
        self.of = np.append(at, len(items)).astype(np.int32)
        self.bucket = np.searchsorted(suffix[at], np.arange(len(self.block) + 1)).astype(np.int32)

    def search(self, ids: np.ndarray, prefix: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
        """(start, items) of every occurrence in a text of word numbers."""
        m, b = self.m, self.b
        if len(ids) < m:
            return
        code = ids if b == 1 else ids[:-1] * self.base + ids[1:]
        at = np.minimum(np.searchsorted(self.block, code), len(self.block) - 1)
        move = np.where(self.block[at] == code, self.shift[at], m - b + 1)
        if move[m - b :].all():
            return
        move, spots, i = move.tolist(), [], m - b
        while i < len(move):
            if move[i]:
                i += move[i]
            else:
                spots.append(i)
                i += 1
        where = np.array(spots, np.int64) + b - m
        for start, k, h in zip(where, at[spots], windows(prefix, where, where + m, 2)):
            lo, hi = self.bucket[k], self.bucket[k + 1]
            p = lo + int(np.searchsorted(self.hash[lo:hi], h))
            while p < hi and self.hash[p] == h:
                s = self.start[p]
                if (self.words[s : s + m] == ids[start : start + m]).all():
                    yield int(start), self.items[self.of[p] : self.of[p + 1]]
                p += 1


class Searcher:
    """The patterns of a block of items, by pattern length."""

    def __init__(self, items: list[tuple[str, bytes]], window: int = WINDOW):
        vocabulary: dict[bytes, int] = {}
        numbers, self.names = [], [name for name, _ in items]
        for _, raw in items:
            numbers.append(np.array([vocabulary.setdefault(w, len(vocabulary)) for w in words_of(raw)], np.int32))
        words = np.concatenate([np.zeros(0, np.int32), *numbers])
        self.vocabulary, self.unknown, base = vocabulary, len(vocabulary), len(vocabulary) + 1
        n = np.array([len(x) for x in numbers], np.int64)
        first = np.cumsum(n) - n
        self.tables = []
        for m in sorted(set(np.minimum(n, window).tolist()) - {0}):
            which = np.flatnonzero(np.minimum(n, window) == m)
            b, each = min(2, m), n[which] - m + 1
            within = np.arange(each.sum()) - np.repeat(np.cumsum(each) - each, each)
            starts, owner = np.repeat(first[which], each) + within, np.repeat(which, each)
            each = n[which] - b + 1
            t = np.arange(each.sum()) - np.repeat(np.cumsum(each) - each, each)
            at = np.repeat(first[which], each) + t
            blocks = words[at].astype(np.int64) if b == 1 else words[at].astype(np.int64) * base + words[at + 1]
            self.tables.append(_Patterns(words, base, m, starts, owner, blocks, np.maximum(0, m - b - t)))

    def search(self, words: list[bytes]) -> tuple[list[tuple[int, int]], set]:
        """(start, end) of every occurrence, and the items they come from."""
        hits, found = [], set()
        if self.tables and words:
            ids = np.fromiter(map(self.vocabulary.get, words, repeat(self.unknown)), np.int64, len(words))
            prefix = sums(ids.astype(np.uint64) + np.uint64(1), 2)
            for table in self.tables:
                for start, items in table.search(ids, prefix):
                    hits.append((start, start + table.m))
                    found.update(items.tolist())
        return hits, {self.names[i] for i in found}


def _pieces(raw: bytes, limit: int, window: int) -> list[bytes]:
    """An item's text, cut where it is longer than a block; each piece begins with the last window less a word of the one before."""
    if len(raw) <= limit:
        return [raw]
    words, step = words_of(raw), max(1, limit // 16)
    return [b" ".join(words[i : i + step + window - 1]) for i in range(0, max(1, len(words) - window + 1), step)]


def _blocks(benchmark: DataFrame, item_col: str, text_col: str, limit: int, window: int = WINDOW) -> Iterator[list[tuple[str, bytes]]]:
    """Items in blocks of bounded size; the driver holds two at a time."""
    now, size = [], 0
    for item, text in benchmark.select(F.col(f"`{item_col}`").cast("string"), F.col(f"`{text_col}`").cast("string")).toLocalIterator():
        for raw in _pieces((text or "").encode("utf-8", "surrogatepass"), limit, window):
            if now and size + len(raw) > limit:
                yield now
                now, size = [], 0
            now.append((item, raw))
            size += len(raw)
    yield now


def _runs(hits: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Disjoint runs that cover the same words."""
    out: list[list[int]] = []
    for a, b in sorted(hits):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def _digest(items) -> tuple[int, str]:
    names = sorted({x for x in items if x is not None})
    return len(names), hashlib.sha256(",".join(names).encode("utf-8", "surrogatepass")).hexdigest()


def _verdict(n: int, runs: list[tuple[int, int]], items) -> dict:
    hit = sum(b - a for a, b in runs)
    k, sha = _digest(items)
    return {"n_words": n, "n_hit": hit, "n_items": k, "items_sha256": sha, "contaminated": hit > 0 and 20 * hit >= n, "items": sorted({x for x in items if x is not None})}


_REPORT = T.StructType([T.StructField("n_words", T.LongType()), T.StructField("n_hit", T.LongType()), T.StructField("n_items", T.LongType()), T.StructField("items_sha256", T.StringType()), T.StructField("contaminated", T.BooleanType()), T.StructField("items", T.ArrayType(T.StringType()))])
_TYPES = [("n_words", pa.int64()), ("n_hit", pa.int64()), ("n_items", pa.int64()), ("items_sha256", pa.string()), ("contaminated", pa.bool_()), ("items", pa.list_(pa.string()))]


def _schema(rows: DataFrame) -> T.StructType:
    """The report's columns after doc_id and row, whatever the names inside row."""
    return T.StructType([rows.schema["doc_id"], rows.schema["row"], *_REPORT.fields])


def judge(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text", window: int = WINDOW, block_bytes: int = BLOCK_BYTES, keep_text: bool = False) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated, items of every row of ``docs``.

    With ``keep_text`` the row also carries its whole record as a struct ``row``.
    """
    spark = docs.sparkSession
    whole = F.struct(*[F.col(f"`{c}`") for c in docs.columns]) if keep_text else F.lit(None).cast("struct<x:int>")
    rows = docs.select(F.col(f"`{id_col}`").alias("doc_id"), F.col(f"`{text_col}`").cast("string").alias("text"), whole.alias("row"))
    blocks = _blocks(benchmark, item_col, item_text, block_bytes, window)
    one, two = next(blocks), next(blocks, None)
    if two is None:
        return _one_pass(rows, spark.sparkContext.broadcast(Searcher(one, window)))
    return _many_passes(rows, chain((one, two), blocks), window)


def _one_pass(rows: DataFrame, searcher) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for c in chunks(b.column(1)):
                for i in range(c.n):
                    w = words_of(c.text(i))
                    hits, items = searcher.value.search(w)
                    out.append(_verdict(len(w), _runs(hits), items))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), *[pa.array([x[k] for x in out], t) for k, t in _TYPES]], names=["doc_id", "row", *[k for k, _ in _TYPES]])

    return rows.mapInArrow(run, _schema(rows))


def _many_passes(rows: DataFrame, blocks: Iterator, window: int) -> DataFrame:
    """Hits per block of the benchmark, united by a key that names the row's id and text."""
    keyed = rows.withColumn("key", F.xxhash64("doc_id", "text"))

    def searching(s):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                out = []
                for c in chunks(b.column(1)):
                    for i in range(c.n):
                        hits, items = s.value.search(words_of(c.text(i)))
                        if hits:
                            out.append((b.column(0)[c.first + i].as_py(), [list(x) for x in _runs(hits)], sorted(x for x in items if x is not None)))
                if out:
                    k, h, t = zip(*out)
                    yield pa.RecordBatch.from_arrays([pa.array(k, pa.int64()), pa.array(h, pa.list_(pa.list_(pa.int32()))), pa.array(t, pa.list_(pa.string()))], names=["key", "hits", "items"])

        return run

    found = None
    for block in blocks:
        searcher = rows.sparkSession.sparkContext.broadcast(Searcher(block, window))
        part = keyed.select("key", "text").mapInArrow(searching(searcher), "key long, hits array<array<int>>, items array<string>").distinct()
        part, _ = materialize(part, "benchmark-hits")
        searcher.destroy()
        found = part if found is None else found.union(part)
    united = found.groupBy("key").agg(F.flatten(F.collect_list("hits")).alias("hits"), F.flatten(F.collect_list("items")).alias("items"))

    def settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for c in chunks(b.column(1)):
                for i in range(c.n):
                    hits = [tuple(x) for x in b.column(3)[c.first + i].as_py() or []]
                    out.append(_verdict(len(words_of(c.text(i))), _runs(hits), b.column(4)[c.first + i].as_py() or []))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(2), *[pa.array([x[k] for x in out], t) for k, t in _TYPES]], names=["doc_id", "row", *[k for k, _ in _TYPES]])

    joined = keyed.join(united, "key", "left").select("doc_id", "text", "row", "hits", "items")
    return joined.mapInArrow(settle, _schema(rows))


def clean(docs: DataFrame, benchmark: DataFrame, **kw) -> DataFrame:
    """The rows of ``docs`` that are not contaminated, with their own columns."""
    x = judge(docs, benchmark, keep_text=True, **kw).where(~F.col("contaminated"))
    return x.select(*[F.col("row").getField(c).alias(c) for c in docs.columns])
