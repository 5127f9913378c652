"""Operator 2: exact substring deduplication with fixed-block anchors.

A window is ``WINDOW`` consecutive words of a document; a word goes if a window over it also starts in
a document with a smaller id (as the input stands). Steps:

1. Anchors. Every document's non-overlapping blocks of ``BLOCK`` words are the index; every rolling
   ``BLOCK``-word window probes it. As 2 * BLOCK - 1 <= WINDOW, two equal windows always share an
   anchor: the block that lies whole in the one is hit by a probe of the other. Documents whose
   anchors meet no other document are done; of the rest the anchors that were hit are known.
2. Extension. A hit is extended to both sides by the windows that hold it, and by no others: each is looked up
   among the windows round the hits of all documents, the least document id with that hash is fetched, and a
   second hash of the words, from other bases, has to agree before anything is taken. Neighbouring windows
   that are taken merge into maximal repeats.
3. The words outside the repeats are joined again.

Both meetings are packed (see ``packed``); hot passages are streamed and never form pairs. Between
the steps only hashes travel: bitmaps, sized by count up to a fixed bound, say which texts and which anchors may
matter, and a meeting or a join decides. Windows are told apart by 96 bits: a collision of the first 64 alone removes nothing.

Defined cases: null and empty texts have no words; a null id neither lends nor loses words; rows with
the same id do not take words from each other; texts are used whole. An empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trailgraph.functions.runtime import materialize, shuffle_width
from trailgraph.llm import bitmaps
from trailgraph.llm.packed import ROW_SQL, Packer, Table, bucket_of, planes, reduce_buckets, unplanes
from trailgraph.llm.textarrays import chunks, longs, mix64, sums, windows, word_hashes

WINDOW, BLOCK = 50, 25
LEND, PROBE, ASK, FIRST, ALL = 0, 1, 2, 0, 1


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    t = F.col(f"`{text_col}`").cast("string")
    return docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.xxhash64(t).alias("rk"), t.alias("text"))


def _row_hash(ids: np.ndarray, keys: np.ndarray) -> np.ndarray:
    return mix64(ids.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) ^ keys.astype(np.uint64))


def _rolling(c, size: int, there: np.ndarray, least: int):
    """Windows of ``size`` words of the documents of ``least`` words or more.

    Word hashes, number of words, and each window's document, first word in the chunk and first word in the document.
    """
    s, e, first = c.words()
    n = np.diff(first)
    usable = (n >= least) & there
    if not usable.any():
        return None
    doc = np.repeat(np.arange(c.n), np.where(usable, n - size + 1, 0))
    start = np.concatenate([np.arange(a, b - size + 1) for a, b, u in zip(first[:-1], first[1:], usable) if u])
    return word_hashes(c, s, e), doc, start, start - first[doc]


def _anchor_marks(bucket: np.ndarray, low: np.ndarray) -> np.ndarray:
    """Names of anchors, from what a packed meeting knows of their hashes."""
    return mix64((bucket.astype(np.uint64) << np.uint64(32)) | low.astype(np.uint64))


def _anchors(rows: DataFrame, buckets: int, window: int, block: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = Packer(buckets)
        for b in batches:
            ids, there = longs(b.column(0))
            keys, _ = longs(b.column(1))
            for c in chunks(b.column(2)):
                i, k, t = (x[c.first : c.first + c.n] for x in (ids, keys, there))
                if (got := _rolling(c, block, t, window)) is None:
                    continue
                words, doc, start, at = got
                h = windows(sums(words, 1), start, start + block, 1)
                index = at % block == 0
                p.add(LEND, h[index], doc[index], i, k, False)
                p.add(PROBE, h, doc, i, k, False)
                p.add(ASK, h[index], doc[index], i, k, False)
                yield from p.take()
        yield from p.take(0)

    return rows.mapInArrow(run, ROW_SQL)


class _Meet:
    """Documents whose probe hit the block of a smaller id, or whose block was hit by a larger one; and the anchors that were hit."""

    def step(self, state: dict, kind: int, ids, keys, runs, hashes, _spots) -> Iterator[pa.RecordBatch]:
        h = np.frombuffer(hashes, np.uint32)
        doc = np.repeat(np.arange(len(ids)), runs)
        if kind == LEND:
            state.setdefault("index", Table(np.uint32)).add(h, ids[doc])
            return
        if "index" not in state:
            return
        table: Table = state["index"]
        at, there = table.find(h)
        at, doc = at[there], doc[there]
        marks = np.zeros(0, np.uint64)
        if kind == PROBE:
            if "most" not in state:
                state["most"] = np.full(len(table.h), np.iinfo(np.int64).min)
                state["told"] = np.zeros(len(table.h), bool)
            np.maximum.at(state["most"], at, ids[doc])
            met = table.lo[at] < ids[doc]
            hit, new = np.unique(doc[met]), np.unique(at[met])
            new = new[~state["told"][new]]
            state["told"][new] = True
            marks = _anchor_marks(np.full(len(new), state["bucket"]), table.h[new])
        elif "most" in state:
            hit = np.unique(doc[state["most"][at] > ids[doc]])
        else:
            return
        if len(hit):
            row = np.concatenate([_row_hash(ids[hit], keys[hit]), marks])
            anchor = np.arange(len(row)) >= len(hit)
            yield pa.RecordBatch.from_arrays([pa.array(row.view(np.int64)), pa.array(anchor)], names=["mark", "anchor"])

    def finish(self) -> Iterator[pa.RecordBatch]:
        return iter(())


def _round_hits(words: np.ndarray, start: np.ndarray, window: int, block: int, buckets: int, hits: np.ndarray) -> np.ndarray:
    """Which of the windows that begin at ``start`` hold an anchor that was hit."""
    edge = np.zeros(len(words) + 2, np.int64)
    np.add.at(edge, start, 1)
    np.add.at(edge, start + window - block + 1, -1)
    at = np.flatnonzero(np.cumsum(edge) > 0)
    h = windows(sums(words, 1), at, at + block, 1)
    flag = np.zeros(len(words) + 1, np.int64)
    flag[at] = bitmaps.has(hits, _anchor_marks(bucket_of(h, buckets), h.astype(np.uint32)))
    before = np.concatenate([[0], np.cumsum(flag)])
    return before[start + window - block + 1] > before[start]


def _extend(rows: DataFrame, buckets: int, window: int, block: int, near, hits) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = Packer(buckets)
        for b in batches:
            ids, there = longs(b.column(0))
            keys, _ = longs(b.column(1))
            there = there & bitmaps.has(near.value, _row_hash(ids, keys))
            for c in chunks(b.column(2)):
                i, k, t = (x[c.first : c.first + c.n] for x in (ids, keys, there))
                if (got := _rolling(c, window, t, window)) is None:
                    continue
                words, doc, start, at = got
                some = _round_hits(words, start, window, block, buckets, hits.value)
                doc, start, at = doc[some], start[some], at[some]
                h = windows(sums(words, 2), start, start + window, 2)
                check = windows(sums(words, 0), start, start + window, 0) >> np.uint64(32)
                by = np.lexsort((i[doc], h))
                one = by[np.append(True, h[by][1:] != h[by][:-1])] if len(by) else by
                one.sort()
                p.add(FIRST, h[one], doc[one], i, k, True, check[one].astype(np.uint32))
                p.add(ALL, h, doc, i, k, True, check << np.uint64(32) | at.astype(np.uint64))
                yield from p.take()
        yield from p.take(0)

    return rows.mapInArrow(run, ROW_SQL)


class _Taken:
    """Window starts that a smaller id has too, packed by the part of the documents they go to."""

    def __init__(self, parts: int):
        self.parts, self.held, self.size = parts, [], 0

    def step(self, state: dict, kind: int, ids, keys, runs, hashes, spots) -> Iterator[pa.RecordBatch]:
        h = np.frombuffer(hashes, np.uint64)
        doc = np.repeat(np.arange(len(ids)), runs)
        if kind == FIRST:
            state.setdefault("index", Table(np.uint64)).add(h, ids[doc], spots)
            return
        table: Table = state["index"]
        at, there = table.find(h)
        hit = there & (table.lo[at] < ids[doc]) & (table.check[at] == spots >> np.uint64(32))
        self.held.append((ids[doc[hit]], keys[doc[hit]], spots[hit].astype(np.uint32)))
        self.size += int(hit.sum())
        if self.size > 1 << 21:
            yield from self.finish()

    def finish(self) -> Iterator[pa.RecordBatch]:
        if not self.size:
            return
        ids, keys, spots = (np.concatenate(x) for x in zip(*self.held))
        self.held, self.size = [], 0
        part = (_row_hash(ids, keys) % np.uint64(self.parts)).astype(np.int32)
        order = np.lexsort((spots, keys, ids, part))
        ids, keys, spots, part = ids[order], keys[order], spots[order], part[order]
        new = np.append(True, (part[1:] != part[:-1]) | (ids[1:] != ids[:-1]) | (keys[1:] != keys[:-1]))
        run = np.flatnonzero(new)
        length = np.diff(np.append(run, len(ids))).astype(np.uint32)
        first = np.flatnonzero(np.append(True, part[1:] != part[:-1]))
        out = []
        for i, j in zip(first, np.append(first[1:], len(ids))):
            x, y = np.searchsorted(run, (i, j))
            out.append((int(part[i]), ids[run[x:y]].tobytes(), keys[run[x:y]].tobytes(), length[x:y].tobytes(), planes(spots[i:j])))
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), [pa.int32(), *[pa.binary()] * 4])], names=["part", "ids", "keys", "runs", "spots"])


_PARTS_SQL = "part int, ids binary, keys binary, runs binary, spots binary"


def _by_document(packed: DataFrame, width: int) -> DataFrame:
    """(doc_id, rk, spots): one row per document that loses words."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []
        for b in batches:
            for r in range(b.num_rows):
                part = b.column(0)[r].as_py()
                if part != now:
                    yield from _merged(held)
                    now, held = part, []
                i, k, n, s = (b.column(c)[r].as_py() for c in range(1, 5))
                runs = np.frombuffer(n, np.uint32)
                held.append((np.repeat(np.frombuffer(i, np.int64), runs), np.repeat(np.frombuffer(k, np.int64), runs), unplanes(s, np.uint32)))
        yield from _merged(held)

    return packed.repartition(width, "part").sortWithinPartitions("part").mapInArrow(run, "doc_id long, rk long, spots binary")


def _merged(held: list) -> Iterator[pa.RecordBatch]:
    if not held:
        return
    ids, keys, spots = (np.concatenate(x) for x in zip(*held))
    order = np.lexsort((spots, keys, ids))
    ids, keys, spots = ids[order], keys[order], spots[order]
    first = np.flatnonzero(np.append(True, (ids[1:] != ids[:-1]) | (keys[1:] != keys[:-1])))
    parts = [np.unique(spots[a:b]).tobytes() for a, b in zip(first, np.append(first[1:], len(ids)))]
    yield pa.RecordBatch.from_arrays([pa.array(ids[first]), pa.array(keys[first]), pa.array(parts, pa.binary())], names=["doc_id", "rk", "spots"])


def _kept(text: bytes, spots: np.ndarray, window: int) -> tuple[list[bytes], int]:
    words = text.split()
    if not len(spots):
        return words, len(words)
    edge = np.zeros(len(words) + 1, np.int64)
    np.add.at(edge, spots, 1)
    np.add.at(edge, np.minimum(spots + window, len(words)), -1)
    keep = np.cumsum(edge[:-1]) == 0
    return [w for w, k in zip(words, keep.tolist()) if k], len(words)


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", window: int = WINDOW, with_text: bool = False) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 (and, if asked for, kept_text) of every row of ``docs``."""
    block = (window + 1) // 2
    rows = _rows(docs, id_col, text_col)
    spark = rows.sparkSession
    width = shuffle_width(docs, 32 << 20, 2.0)
    buckets = 2 * width
    flagged, _ = materialize(reduce_buckets(_anchors(rows, buckets, window, block), width, _Meet, "mark long, anchor boolean").distinct(), "anchors")
    met, total = flagged.where("anchor"), flagged.count()
    hits = spark.sparkContext.broadcast(bitmaps.build(met, F.col("mark"), total))
    near = spark.sparkContext.broadcast(bitmaps.build(flagged.where("not anchor"), F.col("mark"), total))
    taken = reduce_buckets(_extend(rows, buckets, window, block, near, hits), width, lambda: _Taken(buckets), _PARTS_SQL)
    losing, _ = materialize(_by_document(taken, width), "repeats")

    digest = lambda words: hashlib.sha256(b" ".join(words)).hexdigest()

    def settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Digests of what surely loses nothing; the texts of the rest."""
        for b in batches:
            ids, there = longs(b.column(0))
            keys, _ = longs(b.column(1))
            maybe = there & bitmaps.has(near.value, _row_hash(ids, keys))
            words, shas, texts = [], [], []
            for c in chunks(b.column(2)):
                for i in range(c.n):
                    if maybe[c.first + i]:
                        words.append(None), shas.append(None), texts.append(c.text(i).decode("utf-8", "surrogatepass"))
                    else:
                        w = c.text(i).split()
                        words.append(len(w)), shas.append(digest(w)), texts.append(b" ".join(w).decode("utf-8", "surrogatepass") if with_text else None)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(words, pa.int64()), pa.array(shas, pa.string()), pa.array(texts, pa.string())], names=["doc_id", "rk", "n_words", "sha", "text"])

    first = rows.mapInArrow(settle, "doc_id long, rk long, n_words long, sha string, text string")
    joined = first.join(losing, ["doc_id", "rk"], "left").select("doc_id", "n_words", "sha", "text", "spots")

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n, sha, text, spots = (b.column(k) for k in (1, 2, 3, 4))
            out = []
            for r in range(b.num_rows):
                if n[r].is_valid:
                    out.append((n[r].as_py(), 0, sha[r].as_py(), text[r].as_py()))
                    continue
                at = np.frombuffer(spots[r].as_py() or b"", np.uint32).astype(np.int64)
                kept, m = _kept(text[r].as_py().encode("utf-8", "surrogatepass"), at, window)
                out.append((m, m - len(kept), digest(kept), b" ".join(kept).decode("utf-8", "surrogatepass") if with_text else None))
            a, c, d, e = zip(*out) if out else ((), (), (), ())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(a, pa.int64()), pa.array(c, pa.int64()), pa.array(d, pa.string()), pa.array(e, pa.string())], names=["doc_id", "n_words", "n_removed", "kept_sha256", "kept_text"])

    done = joined.mapInArrow(finish, "doc_id long, n_words long, n_removed long, kept_sha256 string, kept_text string")
    return done if with_text else done.drop("kept_text")
