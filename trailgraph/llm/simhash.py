"""Operator 5: SimHash near-duplicates by the generalised pigeonhole principle.

Fingerprint: bit b is set if it is set in over half of the XXH64 (seed 42) of a text's three-word
shingles, repeats included. Search for pairs within ``BOUND`` bits:

1. Distinct fingerprints only; each stands for all its documents and for the least doc_id of them.
2. Bits that go together share a partition (greedy, by the correlation matrix of all fingerprints),
   so that partitions are as independent of each other as can be.
3. Partition i gets a threshold t_i >= -1 with sum t_i = BOUND - m + 1: a pair within BOUND is then
   within t_i of each other in some partition i. Dynamic programming finds the thresholds (and the
   number of partitions m) with the least estimated cost. Candidates at threshold 0 are not estimated but
   counted, as the pairs of all fingerprints that agree on a partition; at threshold 1 the count grows as it would for
   independent bits.
4. Probing: a partition value and, for t_i = 1, its one-bit neighbours are join keys. Buckets of up to
   ``HOT`` fingerprints are verified pair by pair. Larger ones link every fingerprint to all points one bit away
   and meet there - two fingerprints are within two bits exactly if they share such a point - which
   is exact, linear in the bucket and makes no pairs.
5. Components over the verified links, by star contraction.

Defined cases: null and wordless texts have fingerprint 0 and link like any other; fewer than three
words make one shingle; null doc_ids take part and never name a component unless all members are
null; repeated rows are linked; an empty table gives no rows.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from trailgraph.functions.runtime import fresh, materialize
from trailgraph.llm import near_text
from trailgraph.llm.textarrays import chunks
from trailgraph.operators.components import wcc

SEED, SHINGLE, BOUND, HOT = 42, 3, 2, 64


def fingerprint(text: bytes) -> int:
    """Of one text, as an unsigned number."""
    words = text.lower().split()
    if not words:
        return 0
    if len(words) <= SHINGLE:
        shingles = [b" ".join(words)]
    else:
        shingles = [b"%b %b %b" % x for x in zip(words, words[1:], words[2:])]
    hashes = np.array(list(map(_HASH, shingles)), np.uint64)
    return int(_majority(hashes))


def _HASH(shingle: bytes) -> int:
    return xxhash.xxh64_intdigest(shingle, SEED)


def _majority(hashes: np.ndarray) -> int:
    n, ones = len(hashes), np.zeros(64, np.int64)
    for i in range(0, n, 1 << 14):
        ones += np.unpackbits(hashes[i : i + (1 << 14)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > n, bitorder="little").view(np.uint64)[0])


def row_keys(text: Column) -> list[Column]:
    """Two independent 64-bit hashes of a text (k1, k2), which with the doc_id name a row."""
    return [F.xxhash64(text).alias("k1"), F.xxhash64(F.lit(1), text).alias("k2")]


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, k1, k2, fp bigint) of every row."""
    text = F.col(f"`{text_col}`").cast("string")
    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), *row_keys(text), text.alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = [fingerprint(c.text(i)) for c in chunks(b.column(3)) for i in range(c.n)]
            yield pa.RecordBatch.from_arrays([*b.columns[:3], pa.array(np.array(out, np.uint64).view(np.int64))], names=["doc_id", "k1", "k2", "fp"])

    return rows.mapInArrow(run, "doc_id long, k1 long, k2 long, fp long")


def bit_statistics(fps: DataFrame) -> tuple[int, np.ndarray]:
    """Number of fingerprints and how many have both bit i and bit j, over all of them: 64 rows reach the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        both, n = np.zeros((64, 64)), 0
        for b in batches:
            x = np.asarray(b.column(0)).view(np.uint8).reshape(-1, 8)
            bits = np.unpackbits(x, axis=1, bitorder="little").astype(np.float32)
            both += bits.T @ bits
            n += len(bits)
        if n:
            yield pa.RecordBatch.from_arrays([pa.array(range(65), pa.int32()), pa.array([*both.astype(np.int64).tolist(), [n] * 64], pa.list_(pa.int64()))], names=["i", "row"])

    got = fps.select("fp").mapInArrow(run, "i int, row array<bigint>").groupBy("i").agg(*[F.sum(F.col("row")[j]).alias(f"c{j}") for j in range(64)]).collect()
    if not got:
        return 0, np.zeros((64, 64))
    m = {r[0]: np.array(r[1:], float) for r in got}
    return int(m[64][0]), np.array([m[i] for i in range(64)])


def partitions(n: int, both: np.ndarray, m: int) -> list[list[int]]:
    """64 bits in m groups of near-equal size; each group grows by the bit that goes with it most."""
    p = np.diag(both) / max(n, 1)
    cov = both / max(n, 1) - np.outer(p, p)
    sd = np.sqrt(np.maximum(p * (1 - p), 1e-12))
    corr = np.abs(cov / np.outer(sd, sd))
    left, out = set(range(64)), []
    for k in range(m):
        size = (64 - sum(map(len, out))) // (m - k)
        group = [max(left, key=lambda b: (sum(corr[b][j] for j in left) - corr[b][b], -b))]
        left.discard(group[0])
        while len(group) < size:
            best = max(left, key=lambda b: (corr[b][group].sum(), -b))
            group.append(best)
            left.discard(best)
        out.append(sorted(group))
    return out


def agreeing_pairs(fps: DataFrame, groups: list[list[int]]) -> list[float]:
    """How many pairs of the distinct fingerprints agree on all bits of each group; one row per group reaches the driver."""
    keys = [F.struct(F.lit(k).alias("k"), _masked(F.col("fp"), g).alias("v")) for k, g in enumerate(groups)]
    sizes = fps.select(F.explode(F.array(*keys)).alias("x")).groupBy("x.k", "x.v").agg(F.count("*").cast("double").alias("n"))
    found = {r.k: r.pairs for r in sizes.groupBy("k").agg(F.sum(F.expr("n * (n - 1) / 2")).alias("pairs")).collect()}
    return [found.get(k, 0.0) for k in range(len(groups))]


def estimated_cost(n: int, p: np.ndarray, bits: list[int], t: int, agreeing: float) -> float:
    """Keys written plus candidates within t bits in this partition, from the number of pairs that agree on it."""
    if t < 0:
        return 0.0
    near = np.zeros(t + 1)
    near[0] = 1.0
    for b in bits:
        d = 2 * p[b] * (1 - p[b])
        near = near * (1 - d) + np.concatenate([[0.0], near[:-1]]) * d
    expected = n * (n - 1) / 2 * near  # pairs at each distance if bits were independent
    farther = expected[1:].sum() * max(1.0, agreeing / max(expected[0], 1e-300)) if agreeing else expected[1:].sum()
    return n * sum(math.comb(len(bits), k) for k in range(t + 1)) + agreeing + min(farther, n * (n - 1) / 2)


def allocate(cost: list[dict[int, float]], total: int) -> tuple[float, list[int]]:
    """Thresholds per partition with the given sum and the least cost, by dynamic programming over partitions."""
    best: dict[int, tuple[float, list[int]]] = {0: (0.0, [])}
    for c in cost:
        after: dict[int, tuple[float, list[int]]] = {}
        for s, (v, ts) in best.items():
            for t, w in c.items():
                if s + t not in after or v + w < after[s + t][0]:
                    after[s + t] = (v + w, [*ts, t])
        best = after
    return best[total]


def plan(n: int, both: np.ndarray, pairs: Callable[[list[list[int]]], list[float]], bound: int = BOUND) -> list[tuple[list[int], int]]:
    """(bits, threshold) of the partitions to probe, for the number of partitions that costs least.

    ``pairs`` counts the pairs that agree on each group of bits; it is asked once, for all groups of all divisions.
    """
    p = np.diag(both) / max(n, 1)
    divisions = [partitions(n, both, m) for m in range(1, bound + 2) if -m <= bound - m + 1 <= m]
    counted = iter(pairs([g for groups in divisions for g in groups]))
    found = []
    for groups in divisions:
        cost = [{t: estimated_cost(n, p, g, t, k) for t in (-1, 0, 1)} for g, k in zip(groups, counted)]
        v, ts = allocate(cost, bound - len(groups) + 1)
        found.append((v, len(groups), [(g, t) for g, t in zip(groups, ts) if t >= 0]))
    return min(found, key=lambda x: x[:2])[2]


def _masked(fp: Column, bits: list[int]) -> Column:
    mask = sum(1 << b for b in bits)
    return fp.bitwiseAND(F.lit(mask - (1 << 64) if mask >> 63 else mask))


def _flip(v: Column, b: int) -> Column:
    return v.bitwiseXOR(F.lit(-(1 << 63) if b == 63 else 1 << b))


def links(fps: DataFrame, bound: int = BOUND, hot: int = HOT) -> DataFrame:
    """Distinct fingerprints (column fp) -> (src, dst) links whose components are those of all pairs within two bits."""
    if bound != 2:
        raise ValueError("the meeting points of large buckets serve a bound of two bits")
    n, both = bit_statistics(fps)
    keys = []
    for k, (bits, t) in enumerate(plan(n, both, lambda groups: agreeing_pairs(fps, groups), bound) if n else [([0], 0)]):
        v = _masked(F.col("fp"), bits)
        keys.append(F.struct(F.lit(k).alias("k"), v.alias("v")))
        keys += [F.struct(F.lit(k).alias("k"), _flip(v, b).alias("v")) for b in bits if t == 1]
    probes, _ = materialize(fps.select("fp", F.explode(F.array(*keys)).alias("x")).select("fp", "x.k", "x.v"), "probes")
    sizes = probes.groupBy("k", "v").agg(F.count("*").alias("n")).where("n > 1")
    small = probes.join(sizes.where(F.col("n") <= hot).select("k", "v"), ["k", "v"])
    groups = small.groupBy("k", "v").agg(F.sort_array(F.collect_list("fp")).alias("g"))  # no more than ``hot`` each
    at = groups.select("g", F.posexplode("g").alias("i", "src"))
    pair = at.select("src", F.explode(F.expr("slice(g, i + 2, size(g))")).alias("dst"))
    near = pair.where(F.bit_count(F.col("src").bitwiseXOR(F.col("dst"))) <= bound)
    large = probes.join(sizes.where(F.col("n") > hot).select("k", "v"), ["k", "v"], "left_semi").select("fp").distinct()
    points = large.select("fp", F.explode(F.array(F.col("fp"), *[_flip(F.col("fp"), b) for b in range(64)])).alias("z"))
    first = points.groupBy("z").agg(F.min("fp").alias("src"), F.max("fp").alias("last"))
    met = points.join(first.where("src < last").select("z", "src"), "z").where("src < fp").select("src", F.col("fp").alias("dst"))
    return near.union(met).distinct()


def components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", hot: int = HOT) -> DataFrame:
    """doc_id, fp, component_id (least doc_id reachable) of every row."""
    marked, _ = materialize(fingerprints(docs, id_col, text_col), "fps")
    reps = marked.groupBy("fp").agg(F.min("doc_id").alias("least"))
    labels = wcc(links(reps.select("fp"), hot=hot))
    by_fp = reps.join(labels.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", F.coalesce("component", "fp").alias("c"))
    roots = by_fp.groupBy("c").agg(F.min("least").alias("component_id"))
    return marked.join(by_fp.join(roots, "c").select("fp", "component_id"), "fp").select("doc_id", "fp", "component_id")


def one_of_each(docs: DataFrame, labelled: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that stay, given (doc_id, k1, k2, c) of every row: the least (doc_id, nulls last; text hashes) of each c.

    Rows are told apart by id and text, so neither null ids nor ids that several texts share lose a component.
    """
    i, a, b, c = (fresh(docs, x) for x in ("__id", "__k1", "__k2", "__copies"))
    rows = labelled.groupBy("c", "doc_id", "k1", "k2").agg(F.count("*").alias("n"))
    best = rows.groupBy("c").agg(F.min(F.struct(F.col("doc_id").isNull().alias("last"), "doc_id", "k1", "k2", "n")).alias("x"))
    keep, _ = materialize(best.select(F.col("x.doc_id").alias(i), F.col("x.k1").alias(a), F.col("x.k2").alias(b), F.col("x.n").alias(c)), "keep")
    names = [F.col(f"`{x}`") for x in docs.columns]
    k1, k2 = row_keys(F.col(f"`{text_col}`").cast("string"))
    mine = docs.select(*names, k1.alias(k := fresh(docs, "__t1")), k2.alias(m := fresh(docs, "__t2")))
    same = (F.col(k) == F.col(a)) & (F.col(m) == F.col(b)) & F.col(f"`{id_col}`").cast("long").eqNullSafe(F.col(i))
    out = mine.join(keep.hint("merge"), same)  # the same way at every size: ids grow with the documents
    if keep.where(F.col(c) > 1).isEmpty():
        return out.select(*names)
    once = out.where(F.col(c) == 1).select(*names)
    again = out.where(F.col(c) > 1).dropDuplicates([i, a, b]).select(*names)
    return once.unionByName(again)


def near_pairs(rows: DataFrame, nodes: DataFrame) -> DataFrame:
    """(a, b): texts (node, k1) whose fingerprints are equal or linked; ``rows`` (k1, text, ..) has their words."""
    by_text = fingerprints(rows).groupBy("k1").agg(F.min("fp").alias("fp"))
    fps, _ = materialize(nodes.join(by_text, "k1").select("node", "fp"), "node-fps")
    reps, _ = materialize(fps.groupBy("fp").agg(F.min("node").alias("rep")), "fp-reps")
    same = fps.join(reps, "fp").where("rep < node").select(F.col("rep").alias("a"), F.col("node").alias("b"))
    side = lambda k, v: reps.select(F.col("fp").alias(k), F.col("rep").alias(v))
    linked = links(reps.select("fp")).join(side("src", "a"), "src").join(side("dst", "b"), "dst")
    return same.unionByName(linked.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"))).distinct()


def deduplicated(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that stay: one of each component of near-equal texts, that with the least doc_id.

    Fingerprints are searched first and their links verified on the shingle sets; ``near_text`` then finds what lies beyond their bound.
    """
    text = F.col(f"`{text_col}`").cast("string")
    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), *row_keys(text), text.alias("text"))
    return one_of_each(docs, near_text.labelled(rows, known=lambda nodes: near_pairs(rows, nodes)), id_col, text_col)
