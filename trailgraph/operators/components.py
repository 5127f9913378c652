"""M11e: weakly connected components by alternating star contraction (aggregates and joins only).

``wcc_by`` thins the edges to forests in Python first and leaves what is left to one task where that is small; its results are the same.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trailgraph.functions.runtime import materialize, remove

LOCAL = 4_000_000  # edges of forests that one task ends, about 100 bytes each


def _nearest(pairs: DataFrame) -> DataFrame:
    return pairs.groupBy("u").agg(F.min("v").alias("m"))


def _large_star(edges: DataFrame) -> DataFrame:
    """Every node links its larger neighbours to the smallest node it knows."""
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    near = _nearest(both).select("u", F.least("m", "u").alias("m"))
    return both.where("v > u").join(near, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    """Every node links its smaller neighbours, and itself, to the smallest of them."""
    near = _nearest(edges)
    moved = edges.join(near, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(near.select("u", F.col("m").alias("v"))).distinct()


def _state(edges: DataFrame) -> tuple:
    row = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
    return tuple(row)


def _places(g: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of the distinct (g, x), in their order, and the number of each pair among them."""
    if not len(g) or g.min() == g.max():
        _, first, at = np.unique(x, return_index=True, return_inverse=True)
        return first, at
    order = np.lexsort((x, g))
    new = np.append(True, (np.diff(g[order]) != 0) | (np.diff(x[order]) != 0))
    at = np.empty(len(x), np.int64)
    at[order] = np.cumsum(new) - 1
    return order[new], at


def forest(g: np.ndarray, u: np.ndarray, v: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(g, node, smallest node it reaches) of the nodes of the graphs ``g`` that reach a smaller one."""
    gs, ids = np.concatenate([g, g]), np.concatenate([u, v])
    first, at = _places(gs, ids)
    a, b, label = at[: len(u)], at[len(u) :], np.arange(len(first))
    while len(a):
        np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
        while not np.array_equal(up := label[label], label):
            label = up
        a, b = label[a], label[b]
        a, b = a[a != b], b[a != b]
    low = np.flatnonzero(label != np.arange(len(first)))
    return gs[first[low]], ids[first[low]], ids[first[label[low]]]


def _thinned(batches: Iterator[pa.RecordBatch], group: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """The edges (g, u, v) of a task as forests; what is kept at a time is these and ``group`` edges."""
    kept, n = [(np.zeros(0, np.int64),) * 3], 0
    for b in batches:
        kept.append(tuple(b.column(k).to_numpy() for k in range(3)))
        n += b.num_rows
        if n >= group:
            kept, n = [forest(*map(np.concatenate, zip(*kept)))], 0
    out = forest(*map(np.concatenate, zip(*kept)))
    for i in range(0, len(out[0]), group):
        yield pa.RecordBatch.from_arrays([pa.array(x[i : i + group]) for x in out], names=["g", "u", "v"])


def wcc(edges: DataFrame, src: str = "src", dst: str = "dst", max_rounds: int = 60) -> DataFrame:
    """(node, component) of every node that has an edge; component = smallest node reachable.

    Nulls and loops are no edges. Each round costs two aggregates and two joins over the edges that
    are left and is written to the shared folder, so lineage stays flat. The driver sees two numbers.
    """
    a, b = F.col(src), F.col(dst)
    pairs = edges.where(a.isNotNull() & b.isNotNull() & (a != b)).select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v"))
    return _stars(*materialize(pairs.distinct(), "wcc"), max_rounds)


def wcc_by(edges: DataFrame, by: str, src: str = "src", dst: str = "dst", local: int = LOCAL) -> DataFrame:
    """(by, node, component): ``wcc`` of each graph ``by`` at once, where all three columns are longs.

    Every task thins its edges to forests. If no more than ``local`` edges are left one task ends the work, otherwise rounds do.
    """
    g, a, b = F.col(by), F.col(src), F.col(dst)
    pairs = edges.where(g.isNotNull() & a.isNotNull() & b.isNotNull() & (a != b)).select(g.alias("g"), F.greatest(a, b).alias("u"), F.least(a, b).alias("v"))
    kind = "g long, u long, v long"
    now, path = materialize(pairs.mapInArrow(_thinned, kind), "wcc")
    if now.count() <= local:
        out = materialize(now.coalesce(1).mapInArrow(_thinned, kind), "wcc")[0]
        out = out.select("g", F.col("u").alias("node"), F.col("v").alias("component")).unionByName(out.select("g", F.col("v").alias("node"), F.col("v").alias("component")).distinct())
    else:
        one = lambda c: F.struct("g", F.col(c).alias("id")).alias(c)
        out = _stars(*materialize(now.select(one("u"), one("v")).distinct(), "wcc"), 60).select("node.g", F.col("node.id").alias("node"), F.col("component.id").alias("component"))
    return out.withColumnRenamed("g", by)


def _stars(now: DataFrame, path: str, max_rounds: int) -> DataFrame:
    spark = now.sparkSession
    state = _state(now)
    for _ in range(max_rounds if state[0] else 0):
        after, new_path = materialize(_small_star(_large_star(now)), "wcc")
        new_state = _state(after)
        remove(spark, path)
        now, path = after, new_path
        if new_state == state:
            break
        state = new_state
    else:
        if state[0]:
            raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(now.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
