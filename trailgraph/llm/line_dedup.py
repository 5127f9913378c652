"""Operator 10: near-duplicate lines by a deletion-neighbourhood join.

A line is what stands between two line feeds, as its sequence of words; lines without a word are left
alone. Two lines are near duplicates if one edit (insertion, deletion or substitution) turns one into
the other: of a word where both have ``LEAST`` words or more, of a character where both have fewer
words and, joined by single blanks, ``LEAST`` characters or more (0.8 similarity at least either way). Lines shorter
still must be equal. As a changed letter is a changed word, typos in long lines are among the word edits. A line goes if an earlier line - by (doc_id, line number), as the input stands - equals it or
is near it; so the earliest stays.

1. Screening. One edit leaves the first or the last half of the shorter line as it is. Lines whose
   halves meet no other line are done; a bitmap of fixed size, filled with the halves that lines
   share, carries the rest to the next scan.
2. Neighbourhood. Each remaining distinct line emits the hash of itself and of itself without its
   i-th word or character, for every i. Equal hashes join: a line meets a longer one where it equals a deletion of it,
   and a line of its length where both lack the same place i.
3. Verification. For each line the earliest partner is fetched and the edit distance is worked out.
   Where it fails (a collision of 64-bit hashes) all partners of that line are fetched and the earliest that
   passes counts.
4. Lines that go are cut out of their documents.

Only distinct (hash, place, line) rows travel (told apart within each chunk of text before the
shuffle), so a line in a third of all documents is a handful of rows; a line's partner is the earliest
of its group by an aggregate, so no pairs are made. Occurrences of the most frequent lines are told by broadcast
whether they go, so no task gets all of one line.

Defined cases: null or empty text has one line without words; null doc_id sorts before all others;
repeated rows: the second loses its lines (positions are told apart by the row's text only where texts
differ, so identical rows with the same id count as one); an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trailgraph.functions.runtime import materialize
from trailgraph.llm import bitmaps
from trailgraph.llm.textarrays import chunks, longs, mix64, powers, sums, windows, word_hashes

LEAST = 5
PIECE = 1 << 19  # bytes of text taken at a time: each character of a short line is a variant, and a variant takes some hundred bytes
FREQUENT = 1000  # a line that is more than one in so many meets its verdict by broadcast
_NULL = np.iinfo(np.int64).min
_CHARACTER = np.uint64(0x5851F42D4C957F2D)  # keeps characters apart from words


class Lines:
    """The worded lines of a chunk: document, number in it, first and last word, key."""

    def __init__(self, c):
        s, e, first = c.words()
        doc = np.repeat(np.arange(c.n), np.diff(first))
        feeds = np.cumsum(c.data == 10) if len(c.data) else np.zeros(0, np.int64)
        total = np.concatenate([[0], feeds])
        self.line_of_word = total[s] - total[c.off[doc]]
        new = np.ones(len(s), bool)
        new[1:] = (doc[1:] != doc[:-1]) | (self.line_of_word[1:] != self.line_of_word[:-1])
        self.at = np.flatnonzero(new)
        self.to = np.append(self.at[1:], len(s))[: len(self.at)]
        self.doc, self.no = doc[self.at], self.line_of_word[self.at]
        self.h = word_hashes(c, s, e)
        self.prefix = sums(self.h, 1)
        self.key = windows(self.prefix, self.at, self.to, 1)
        self.n = self.to - self.at

    def words(self) -> Units:
        """The lines of ``LEAST`` words or more, by words."""
        return Units(np.flatnonzero(self.n >= LEAST), self.prefix, self.at, self.to, self.key)

    def characters(self, c) -> Units:
        """The other lines, by characters: their words joined by single blanks. Places are those of all lines of the chunk."""
        s, e, _ = c.words()
        length, parts = np.zeros(len(self.at), np.int64), []
        for x in np.flatnonzero(self.n < LEAST).tolist():
            line = b" ".join(c.data[s[i] : e[i]].tobytes() for i in range(self.at[x], self.to[x]))
            parts.append(np.frombuffer(line.decode("utf-8", "replace").encode("utf-32-le"), np.uint32))
            length[x] = len(parts[-1])
        values = np.concatenate(parts) if parts else np.zeros(0, np.uint32)
        prefix, to = sums(mix64(values.astype(np.uint64) + _CHARACTER), 1), np.cumsum(length)
        at = to - length
        return Units(np.flatnonzero(length >= LEAST), prefix, at, to, windows(prefix, at, to, 1))


class Units:
    """Lines ``which`` as sequences of hashed words or characters: ``prefix`` their sums, ``whole`` the hash of each line."""

    def __init__(self, which, prefix, at, to, whole):
        self.which, self.prefix, self.at, self.to, self.whole = which, prefix, at, to, whole

    def halves(self) -> tuple[np.ndarray, np.ndarray]:
        """(place of the line, hash) of the first and last half for a partner as long or one unit shorter."""
        which, out = self.which, []
        for less in (0, 1):
            m = self.to[which] - self.at[which] - less
            k = m // 2
            tag = mix64(m.astype(np.uint64) * np.uint64(2))
            out.append(windows(self.prefix, self.at[which], self.at[which] + k, 1) ^ tag)
            out.append(windows(self.prefix, self.to[which] - k, self.to[which], 1) ^ ~tag)
        return np.tile(which, 4), mix64(np.concatenate(out))

    def neighbours(self, which: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(place of the line, unit left out or -1, hash) of every variant of the lines ``which``."""
        n = self.to[which] - self.at[which]
        line = np.repeat(which, n)
        begin = np.cumsum(n) - n
        i = np.arange(n.sum()) - np.repeat(begin, n)
        a, b = self.at[line], self.to[line]
        base, inverse = powers(len(self.prefix) + 1, 1)
        left = self.prefix[a + i] - self.prefix[a]
        right = (self.prefix[b] - self.prefix[a + i + 1]) * inverse[1]
        h = mix64((left + right) * inverse[a] + (b - a - 1).astype(np.uint64) * np.uint64(0x9FB21C651E98DF25))
        return np.concatenate([which, line]), np.concatenate([np.full(len(which), -1), i]), np.concatenate([self.whole[which], h])


def _rows(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    t = F.col(f"`{text_col}`").cast("string")
    return docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.xxhash64(t).alias("rk"), t.alias("text"))


def _i64(a: np.ndarray) -> pa.Array:
    return pa.array(a.view(np.int64) if a.dtype == np.uint64 else a.astype(np.int64))


def _scan(rows: DataFrame, make, schema: str) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids, there = longs(b.column(0))
            ids = np.where(there, ids, _NULL)
            rk, _ = longs(b.column(1))
            for c in chunks(b.column(2), PIECE):
                part = slice(c.first, c.first + c.n)
                if (out := make(Lines(c), ids[part], rk[part], c)) is not None:
                    yield out

    return rows.mapInArrow(run, schema)


def _near(a: list[bytes], b: list[bytes]) -> bool:
    """Whether one edit at most turns the words a into b: of a word, or of a character where both are short."""
    if max(len(a), len(b)) < LEAST:
        return _one_edit(*(b" ".join(x).decode("utf-8", "replace") for x in (a, b)))
    return min(len(a), len(b)) >= LEAST and _one_edit(a, b)


def _one_edit(a, b) -> bool:
    if abs(len(a) - len(b)) > 1 or min(len(a), len(b)) < LEAST:
        return a == b
    i = 0
    while i < min(len(a), len(b)) and a[i] == b[i]:
        i += 1
    j = 0
    while j < min(len(a), len(b)) - i and a[-1 - j] == b[-1 - j]:
        j += 1
    return max(len(a), len(b)) - i - j <= 1


def removed_lines(rows: DataFrame, near: Callable[[list[bytes], list[bytes]], bool] = _near) -> DataFrame:
    """(doc_id, rk, no): numbers of the lines that go; ``near`` verifies two lines whose variants met."""

    def occurrences(x: Lines, ids, rk, c):
        if not len(x.at):
            return None
        ends, screened = np.zeros((len(x.at), 4), np.int64), np.zeros(len(x.at), bool)
        for units in (x.words(), x.characters(c)):
            _, h = units.halves()
            ends[units.which], screened[units.which] = h.view(np.int64).reshape(4, -1).T, True
        offsets = np.concatenate([[0], np.cumsum(np.where(screened, 4, 0))]).astype(np.int32)
        halves = pa.ListArray.from_arrays(pa.array(offsets), pa.array(ends[screened].ravel()))
        return pa.RecordBatch.from_arrays([_i64(x.key), _i64(ids[x.doc]), _i64(rk[x.doc]), _i64(x.no), halves], names=["k", "doc_id", "rk", "no", "h"])

    spark = rows.sparkSession
    seen, _ = materialize(_scan(rows, occurrences, "k long, doc_id long, rk long, no long, h array<bigint>"), "lines")
    ends = seen.select("k", F.explode("h").alias("h")).groupBy("h").agg(F.min("k").alias("lo"), F.max("k").alias("hi")).where("lo <> hi")
    met_half = spark.sparkContext.broadcast(bitmaps.build(ends, F.col("h")))

    def variants(x: Lines, ids, _rk, c):
        """Hashes of lines that share a half with another, whole (-1) and without unit i; and their words (-2)."""
        found, texts = [], {}
        s, e, _ = c.words()
        for units in (x.words(), x.characters(c)):
            at, h = units.halves()
            which = np.unique(at[bitmaps.has(met_half.value, h)])
            which = which[np.unique(x.key[which], return_index=True)[1]]
            texts.update((j, c.data[s[x.at[j]] : e[x.to[j] - 1]].tobytes().decode("utf-8", "replace")) for j in which.tolist())
            found.append(units.neighbours(which))
        if not texts:
            return None
        at, left_out, h = (np.concatenate(y) for y in zip(*found))
        lines = np.array(list(texts), np.int64)
        v, i, k = np.concatenate([x.key[lines], h]), np.concatenate([np.full(len(lines), -2), left_out]), np.concatenate([x.key[lines], x.key[at]])
        return pa.RecordBatch.from_arrays([_i64(v), pa.array(i.astype(np.int32)), _i64(k), pa.array([*texts.values()] + [None] * len(h), pa.string())], names=["v", "i", "k", "line"])

    all_variants, _ = materialize(_scan(rows, variants, "v long, i int, k long, line string").distinct(), "line-variants")
    hashes = all_variants.where("i >= -1").select("v", "i", "k")
    shared = hashes.groupBy("v").agg(F.min("k").alias("lo"), F.max("k").alias("hi")).where("lo <> hi").select("v")
    first = seen.groupBy("k").agg(F.min(F.struct("doc_id", "no")).alias("p"), F.count("*").alias("n"))
    met, _ = materialize(hashes.join(shared, "v", "left_semi").join(first, "k").select("v", "i", "k", F.struct("p.doc_id", "p.no", "k").alias("p")), "lines-met")
    whole = met.where("i = -1").groupBy("v").agg(F.min("p").alias("q"))
    lacking = met.where("i >= 0").groupBy("v").agg(F.min("p").alias("q"))
    same_place = met.where("i >= 0").groupBy("v", "i").agg(F.min("p").alias("q"))
    meetings = lambda mine, whole, lacking, same_place: (
        mine.where("i = -1").join(lacking, "v").select("k", "q")
        .union(mine.where("i >= 0").join(whole, "v").select("k", "q"))
        .union(mine.where("i >= 0").join(same_place, ["v", "i"]).select("k", "q"))
        .where("q.k <> k")
    )
    found = meetings(met, whole, lacking, same_place).groupBy("k").agg(F.min("q").alias("q"))
    lines = all_variants.where("i = -2").groupBy("k").agg(F.min("line").alias("line"))

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ok = [near(x.encode().split(), y.encode().split()) for x, y in zip(b.column(3).to_pylist(), b.column(4).to_pylist())]
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in range(3)), pa.array(ok, pa.bool_())], names=["k", "pd", "pn", "ok"])

    def verified(found: DataFrame) -> DataFrame:
        pairs = found.select("k", F.col("q.doc_id").alias("pd"), F.col("q.no").alias("pn"), F.col("q.k").alias("pk"))
        told = pairs.join(lines, "k").join(lines.select(F.col("k").alias("pk"), F.col("line").alias("partner")), "pk")
        return told.select("k", "pd", "pn", "line", "partner").mapInArrow(verify, "k long, pd long, pn long, ok boolean")

    first_tried, _ = materialize(verified(found), "lines-verified")
    passed = first_tried.where("ok").drop("ok")
    if not (failed := first_tried.where("not ok").select("k")).isEmpty():  # only where 64-bit hashes collide
        each = [met.where(w).select("v", *by, F.col("p").alias("q")) for w, by in (("i = -1", []), ("i >= 0", []), ("i >= 0", ["i"]))]
        every = verified(meetings(met.join(failed, "k", "left_semi"), *each).distinct()).where("ok")
        again = every.groupBy("k").agg(F.min(F.struct("pd", "pn")).alias("x")).select("k", F.col("x.pd").alias("pd"), F.col("x.pn").alias("pn"))
        passed = passed.unionByName(again)
    earliest = F.least(F.struct(F.col("p.doc_id").alias("d"), F.col("p.no").alias("n")), F.struct(F.coalesce("pd", "p.doc_id").alias("d"), F.coalesce("pn", "p.no").alias("n")))
    best, _ = materialize(first.join(passed, "k", "left").select("k", earliest.alias("e"), "n"), "lines-best")
    often = best.where(F.col("n") * FREQUENT > seen.count()).drop("n")  # fewer than ``FREQUENT`` lines
    every = seen.select("k", "doc_id", "rk", "no")
    x = every.join(F.broadcast(often.select("k")), "k", "left_anti").join(best.drop("n"), "k").unionByName(every.join(F.broadcast(often), "k"))
    return x.where(F.struct(F.col("doc_id").alias("d"), F.col("no").alias("n")) > F.col("e")).select("doc_id", "rk", "no")


def deduplicate(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False) -> DataFrame:
    """doc_id, n_lines (with a word), n_removed, kept_sha256 (and kept_text): kept lines joined by a line feed."""
    rows = _rows(docs, id_col, text_col)
    gone, _ = materialize(removed_lines(rows).groupBy("doc_id", "rk").agg(F.sort_array(F.collect_set("no")).alias("gone")), "lines-gone")
    mark = F.xxhash64("doc_id", "rk")
    near = rows.sparkSession.sparkContext.broadcast(bitmaps.build(gone.select(mark.alias("m")), F.col("m")))

    def facts(text: bytes, out: set) -> tuple:
        lines = text.split(b"\n")
        kept = b"\n".join(x for i, x in enumerate(lines) if i not in out) if out else text
        return sum(1 for x in lines if x.split()), len(out), hashlib.sha256(kept).hexdigest(), kept.decode("utf-8", "surrogatepass") if with_text else None

    names = ["doc_id", "n_lines", "n_removed", "kept_sha256", "kept_text"]
    types = [pa.int64(), pa.int64(), pa.string(), pa.string()]

    def settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            m, _ = longs(b.column(3))
            maybe = bitmaps.has(near.value, m)
            out, texts = [], []
            for c in chunks(b.column(2)):
                for i in range(c.n):
                    text = c.text(i)
                    later = maybe[c.first + i]
                    out.append((None,) * 4 if later else facts(text, set()))
                    texts.append(text.decode("utf-8", "surrogatepass") if later else None)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(texts, pa.string()), *[pa.array([x[k] for x in out], t) for k, t in enumerate(types)]], names=["doc_id", "rk", "text", *names[1:]])

    kinds = "n_lines long, n_removed long, kept_sha256 string, kept_text string"
    first = rows.withColumn("m", mark_of(F.coalesce("doc_id", F.lit(_NULL)), F.col("rk"))).mapInArrow(settle, f"doc_id long, rk long, text string, {kinds}")
    g = gone.select(F.col("doc_id").alias("gd"), F.col("rk").alias("gk"), "gone")
    joined = first.join(g, (F.coalesce("doc_id", F.lit(_NULL)) == F.col("gd")) & (F.col("rk") == F.col("gk")), "left").select("doc_id", "text", "gone", *names[1:])

    def finish(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for r in range(b.num_rows):
                if b.column(1)[r].is_valid:
                    out.append(facts(b.column(1)[r].as_py().encode("utf-8", "surrogatepass"), set(b.column(2)[r].as_py() or ())))
                else:
                    out.append(tuple(b.column(k)[r].as_py() for k in range(3, 7)))
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array([x[k] for x in out], t) for k, t in enumerate(types)]], names=names)

    done = joined.mapInArrow(finish, f"doc_id long, {kinds}")
    return done if with_text else done.drop("kept_text")


def mark_of(doc_id, rk):
    return F.xxhash64(doc_id, rk)
