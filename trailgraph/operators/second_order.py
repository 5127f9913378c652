"""The pair graph, co-occurrence weights, and pruning of weak edges."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def pair_graph(edges: DataFrame, count_mode: str = "edges") -> DataFrame:
    """TEDGE -> SEDGE(a, b, c, n): how often a payment a to b was followed by one from b to c."""
    n = {"edges": F.count("*"), "distinct_src": F.countDistinct("src_id"), "distinct_dst": F.countDistinct("dst_id")}[count_mode]
    return edges.groupBy("a", "b", "c").agg(n.alias("n"))


def merge_pairs(*parts: DataFrame) -> DataFrame:
    """Counts are additive: batches add up (count_mode edges)."""
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out.groupBy("a", "b", "c").agg(F.sum("n").alias("n"))


def totals(s: DataFrame, how: str = "window") -> DataFrame:
    """SEDGE with n_out (all that follows a to b) and n_in (all that comes before b to c).

    ``join`` suits accounts with very many continuations: it doesn't sort a group and pre-aggregates.
    """
    if how == "window":
        return s.select("*", F.sum("n").over(Window.partitionBy("a", "b")).alias("n_out"), F.sum("n").over(Window.partitionBy("b", "c")).alias("n_in"))
    out = s.groupBy("a", "b").agg(F.sum("n").alias("n_out"))
    inn = s.groupBy("b", "c").agg(F.sum("n").alias("n_in"))
    return s.join(out, ["a", "b"]).join(inn, ["b", "c"]).select("a", "b", "c", "n", "n_out", "n_in")


def combined(p: Column, q: Column, combine: str = "max") -> Column:
    return {"max": F.greatest(p, q), "fwd": p, "bwd": q, "mean": (p + q) / 2, "product": p * q}[combine]


def weights(s: DataFrame, combine: str = "max", how: str = "window") -> DataFrame:
    """(a, b, c, n, p_fwd, p_bwd, w). The larger of both shares unless ``combine`` says otherwise."""
    x = totals(s, how).select("a", "b", "c", "n", (F.col("n") / F.col("n_out")).alias("p_fwd"), (F.col("n") / F.col("n_in")).alias("p_bwd"))
    return x.withColumn("w", combined(F.col("p_fwd"), F.col("p_bwd"), combine))


def forward_share(s: DataFrame) -> DataFrame:
    return weights(s).select("a", "b", "c", "n", "p_fwd")


def backward_share(s: DataFrame) -> DataFrame:
    return weights(s).select("a", "b", "c", "n", "p_bwd")


def attach(edges: DataFrame, w: DataFrame) -> DataFrame:
    """TEDGE with n, p_fwd, p_bwd, w of its pair of pairs."""
    return edges.join(w, ["a", "b", "c"])


def prune(edges: DataFrame, min_weight: float) -> DataFrame:
    return edges.where(F.col("w") >= F.lit(float(min_weight)))


def weigh_and_prune(edges: DataFrame, min_weight: float, combine: str = "max", count_mode: str = "edges") -> DataFrame:
    """Counts, weights, pruning of the pair graph first, and only then the join back to the edges."""
    return attach(edges, prune(weights(pair_graph(edges, count_mode), combine), min_weight))


def pair_labels(s: DataFrame) -> DataFrame:
    """The pair graph with node labels as text, for sinks."""
    arrow = lambda x, y: F.concat_ws("->", F.col(x).cast("string"), F.col(y).cast("string"))
    return s.select(arrow("a", "b").alias("src_pair"), arrow("b", "c").alias("dst_pair"), "n")


def nth_order(edges: DataFrame, order: int = 3) -> DataFrame:
    """Counts of walks of ``order`` payments by their accounts, as array ``path`` of order + 1 accounts."""
    cur = edges.select("dst_id", F.array("a", "b", "c").alias("path"))
    step = edges.select(F.col("src_id").alias("s"), F.col("dst_id").alias("d"), F.col("c").alias("x"))
    for _ in range(order - 2):
        cur = cur.join(step, F.col("dst_id") == F.col("s")).select(F.col("d").alias("dst_id"), F.concat("path", F.array("x")).alias("path"))
    return cur.groupBy("path").agg(F.count("*").alias("n"))
