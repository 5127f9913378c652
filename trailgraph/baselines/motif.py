"""The motif-join baseline and its multi-hop extension on the temporal graph.

A path of h hops is a chain of h payments. Layers say which accounts a motif fixes ("1") and which it
leaves open ("*"); a flow is one combination of the fixed accounts.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trailgraph.functions.runtime import materialize


def paths(edges: DataFrame, hops: int, simple: bool = False, first: DataFrame | None = None, last: DataFrame | None = None, max_paths: int | None = None) -> DataFrame:
    """(accts array of hops + 1, ids array of hops). ``first``/``last``: tables of allowed end accounts (column acct)."""
    if hops < 2:
        raise ValueError("a motif has two hops or more")
    e = edges.select("src_id", "dst_id", "a", "b", "c")
    cur = e.select(F.array("a", "b", "c").alias("accts"), F.array("src_id", "dst_id").alias("ids"), F.col("dst_id").alias("end"), F.col("a").alias("start"), F.col("c").alias("tip"))
    if first is not None:
        cur = cur.join(first.select(F.col("acct").alias("start")), "start", "left_semi")
    step = e.select(F.col("src_id").alias("s"), F.col("dst_id").alias("d"), F.col("c").alias("x"))
    for h in range(2, hops):
        cur = cur.join(step, F.col("end") == F.col("s")).select(F.concat("accts", F.array("x")).alias("accts"), F.concat("ids", F.array("d")).alias("ids"), F.col("d").alias("end"), "start", F.col("x").alias("tip"))
        if max_paths is not None and (n := cur.count()) > max_paths:
            raise RuntimeError(f"{n} paths at {h + 1} hops; the bound is {max_paths}")
    if simple:
        cur = cur.where(F.size(F.array_distinct("accts")) == F.size("accts"))
    if last is not None:
        cur = cur.join(last.select(F.col("acct").alias("tip")), "tip", "left_semi")
    return cur.select("accts", "ids")


def flows(edges: DataFrame, layers=("1", "*", "1"), min_intermediates: int = 1, **kw) -> DataFrame:
    """(key array, n_paths, n_txn_slots): motif groups by the accounts of the fixed layers.

    ``min_intermediates``: distinct accounts that each open layer must have in the group.
    """
    fixed = [i for i, x in enumerate(layers) if x == "1"]
    p = paths(edges, len(layers) - 1, **kw)
    x = p.groupBy(F.array(*[F.col("accts")[i] for i in fixed]).alias("key")).agg(F.count("*").alias("n_paths"), *[F.countDistinct(F.col("accts")[i]).alias(f"open{i}") for i, v in enumerate(layers) if v == "*"])
    for i, v in enumerate(layers):
        if v == "*":
            x = x.where(F.col(f"open{i}") >= min_intermediates)
    return x.select("key", "n_paths")


def _first_hop(edges: DataFrame, first: DataFrame | None = None) -> DataFrame:
    """(first_payer, end, tip, n) of the motifs of two hops."""
    cur = edges.select(F.col("a").alias("first_payer"), F.col("dst_id").alias("end"), F.col("c").alias("tip"))
    if first is not None:
        cur = cur.join(first.select(F.col("acct").alias("first_payer")), "first_payer", "left_semi")
    return cur.groupBy("first_payer", "end", "tip").agg(F.count("*").alias("n"))


def _next_hop(cur: DataFrame, edges: DataFrame) -> DataFrame:
    step = edges.select(F.col("src_id").alias("s"), F.col("dst_id").alias("d"), F.col("c").alias("x"))
    return cur.join(step, F.col("end") == F.col("s")).groupBy("first_payer", F.col("d").alias("end"), F.col("x").alias("tip")).agg(F.sum("n").alias("n"))


def _pairs(cur: DataFrame) -> DataFrame:
    return cur.groupBy("first_payer", F.col("tip").alias("last_payee")).agg(F.sum("n").alias("n_paths"))


def end_pairs(edges: DataFrame, hops: int, first: DataFrame | None = None, last: DataFrame | None = None) -> DataFrame:
    """Type 2 groups (first_payer, last_payee, n_paths) without making the paths: multiplicities are carried.

    State after each hop is (first payer, last payment, tip, count): the shuffle stays at payments times first payers.
    """
    cur = _first_hop(edges, first)
    for _ in range(hops - 2):
        cur = _next_hop(cur, edges)
    if last is not None:
        cur = cur.join(last.select(F.col("acct").alias("tip")), "tip", "left_semi")
    return _pairs(cur)


def growth(edges: DataFrame, hops=(2, 3, 4, 5, 6, 7)) -> DataFrame:
    """(hops, n_paths, n_flows) of the type 2 motif for each number of hops; one chain, written after each hop."""
    cur, out = _first_hop(edges), None
    for h in range(2, max(hops) + 1):
        cur, _ = materialize(cur if h == 2 else _next_hop(cur, edges), "motif-chain")
        if h in hops:
            row = _pairs(cur).agg(F.lit(h).alias("hops"), F.coalesce(F.sum("n_paths"), F.lit(0)).alias("n_paths"), F.count("*").alias("n_flows"))
            out = row if out is None else out.unionByName(row)
    return out


def members(edges: DataFrame, hops: int, **kw) -> DataFrame:
    """MEMBER of type 2 groups: (first_payer, last_payee, txn_id); a payment may be in many flows."""
    p = paths(edges, hops, **kw)
    return p.select(F.col("accts")[0].alias("first_payer"), F.element_at("accts", -1).alias("last_payee"), F.explode("ids").alias("txn_id")).distinct()


def aggressive_prefilter(txn: DataFrame, keep_fraction: float = 2e-5) -> DataFrame:
    """Keeps the top share of payments by amount (ties by id) - a stand-in for the published pre-filter, whose rule isn't known."""
    n = txn.count()
    return txn.orderBy(F.desc("amount"), "txn_id").limit(max(1, round(n * keep_fraction)))
