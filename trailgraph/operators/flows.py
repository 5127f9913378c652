"""Roles of accounts in a flow, flow summaries, export and search.

A flow is whatever ``keys`` name in MEMBER: (comm_id), (window_start, comm_id), or a motif's fixed ends.
"""

from __future__ import annotations

from collections import deque
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from trailgraph.sources.ledger import micros

KEYS = ("comm_id",)


def payments(member: DataFrame, txn: DataFrame, keys=KEYS) -> DataFrame:
    """The payments of each flow: keys, txn_id, us, payer, payee, amount, channel."""
    return member.select(*keys, "txn_id").join(txn.select("txn_id", micros().alias("us"), "payer", "payee", "amount", "channel"), "txn_id").select(*keys, "txn_id", "us", "payer", "payee", "amount", "channel")


def roles(pay: DataFrame, keys=KEYS, role_mode: str = "account", edges: DataFrame | None = None) -> DataFrame:
    """(keys, acct, role, paid, received): dispense pays and never receives, sink receives and never pays, else mid.

    ``role_mode="txn"``: an account is dispense (sink) if it pays (receives) a payment without an edge
    from (to) another of the flow; it may be both. Needs ``edges``.
    """
    side = lambda who, give, take: pay.select(*keys, F.col(who).alias("acct"), give.alias("paid"), take.alias("received"), "txn_id")
    no, amount = F.lit(None).cast("long"), F.col("amount")
    both = side("payer", amount, no).unionByName(side("payee", no, amount))
    per = both.groupBy(*keys, "acct").agg(F.coalesce(F.sum("paid"), F.lit(0)).alias("paid"), F.coalesce(F.sum("received"), F.lit(0)).alias("received"), F.count("paid").alias("n_paid"), F.count("received").alias("n_received"))
    if role_mode == "account":
        role = F.when(F.col("n_received") == 0, "dispense").when(F.col("n_paid") == 0, "sink").otherwise("mid")
        return per.select(*keys, "acct", role.alias("role"), "paid", "received")
    inner = edges.join(pay.select(*keys, F.col("txn_id").alias("src_id")), "src_id").join(pay.select(*keys, F.col("txn_id").alias("dst_id")), ["dst_id", *keys])
    begun = pay.join(inner.select(*keys, F.col("dst_id").alias("txn_id")), [*keys, "txn_id"], "left_anti").select(*keys, F.col("payer").alias("acct"), F.lit("dispense").alias("role"))
    ended = pay.join(inner.select(*keys, F.col("src_id").alias("txn_id")), [*keys, "txn_id"], "left_anti").select(*keys, F.col("payee").alias("acct"), F.lit("sink").alias("role"))
    ends = begun.unionByName(ended).distinct()
    return per.join(ends, [*keys, "acct"], "left").select(*keys, "acct", F.coalesce("role", F.lit("mid")).alias("role"), "paid", "received")


def summarize(pay: DataFrame, role: DataFrame, keys=KEYS) -> DataFrame:
    """One row per flow: counts, dispensed, sunk, sunk_pct, span."""
    t = pay.groupBy(*keys).agg(F.count("*").alias("n_txn"), F.sum("amount").alias("amount"), F.min("us").alias("first_us"), F.max("us").alias("last_us"))
    is_ = lambda r: F.col("role") == r
    a = role.groupBy(*keys).agg(
        F.count("*").alias("n_acct"), F.count_if(is_("dispense")).alias("n_dispense"), F.count_if(is_("sink")).alias("n_sink"), F.count_if(is_("mid")).alias("n_mid"),
        F.coalesce(F.sum(F.when(is_("dispense"), F.col("paid"))), F.lit(0)).alias("dispensed"), F.coalesce(F.sum(F.when(is_("sink"), F.col("received"))), F.lit(0)).alias("sunk"),
    )
    return t.join(a, list(keys)).withColumn("sunk_pct", F.try_divide((F.col("sunk") * 100).cast("double"), F.col("dispensed").cast("double")))


def _diameter(arcs: list) -> int:
    """Longest finite shortest directed path."""
    out: dict = {}
    for a, b in arcs:
        out.setdefault(a, set()).add(b)
    most = 0
    for start in out:
        seen, queue = {start: 0}, deque([start])
        while queue:
            x = queue.popleft()
            for y in out.get(x, ()):
                if y not in seen:
                    seen[y] = seen[x] + 1
                    queue.append(y)
        most = max(most, max(seen.values()))
    return most


def diameters(pay: DataFrame, keys=KEYS) -> DataFrame:
    """(keys, diameter) on the flow's account digraph."""
    packed = pay.groupBy(*keys).agg(F.collect_set(F.struct("payer", "payee")).alias("arcs"))
    kinds = dict(packed.dtypes)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            out = f[list(keys)].copy()
            out["diameter"] = [_diameter([(x["payer"], x["payee"]) for x in a]) for a in f["arcs"]]
            yield out

    return packed.mapInPandas(run, ", ".join(f"{k} {kinds[k]}" for k in keys) + ", diameter int")


def vectors(pay: DataFrame, summary: DataFrame, role: DataFrame, acct: DataFrame, wedges: DataFrame, keys=KEYS) -> DataFrame:
    """(keys, vector) - a fixed-length summary of each flow for anomaly models.

    Logs of counts and amounts, span in hours, sunk share, shares of banks crossed, edge density, mean
    weight, largest fan-out and fan-in, channel entropy.
    """
    log = lambda c: F.log1p(F.col(c).cast("double"))
    fan_out = pay.groupBy(*keys, "payer").agg(F.countDistinct("payee").alias("f")).groupBy(*keys).agg(F.max("f").alias("fan_out"))
    fan_in = pay.groupBy(*keys, "payee").agg(F.countDistinct("payer").alias("f")).groupBy(*keys).agg(F.max("f").alias("fan_in"))
    b = acct.select("acct", "bank")
    banks = pay.join(b.select(F.col("acct").alias("payer"), F.col("bank").alias("b1")), "payer", "left").join(b.select(F.col("acct").alias("payee"), F.col("bank").alias("b2")), "payee", "left")
    cross = banks.groupBy(*keys).agg(F.avg((F.col("b1") != F.col("b2")).cast("double")).alias("cross"), F.size(F.array_distinct(F.flatten(F.array(F.collect_set("b1"), F.collect_set("b2"))))).alias("n_banks"))
    per = pay.groupBy(*keys, "channel").agg(F.count("*").alias("n"))
    share = F.col("n") / F.sum("n").over(Window.partitionBy(*keys))
    mixed = per.withColumn("s", share).groupBy(*keys).agg((-F.sum(F.col("s") * F.log("s"))).alias("entropy"))
    inner = wedges.join(pay.select(*keys, F.col("txn_id").alias("src_id")), "src_id").join(pay.select(*keys, F.col("txn_id").alias("dst_id")), ["dst_id", *keys]).groupBy(*keys).agg(F.count("*").alias("n_edge"), F.avg("w").alias("mean_w"))
    x = summary
    for part in (fan_out, fan_in, cross, mixed, inner):
        x = x.join(part, list(keys), "left")
    cols = [
        log("n_txn"), log("n_acct"), log("n_dispense"), log("n_sink"), log("n_mid"), log("dispensed"), log("sunk"), (F.col("last_us") - F.col("first_us")) / F.lit(3.6e9),
        F.coalesce("sunk_pct", F.lit(0.0)), F.coalesce("cross", F.lit(0.0)), F.col("n_banks").cast("double"), F.coalesce(F.col("n_edge") / F.col("n_txn"), F.lit(0.0)),
        F.coalesce("mean_w", F.lit(0.0)), F.col("fan_out").cast("double"), F.col("fan_in").cast("double"), F.coalesce("entropy", F.lit(0.0)),
    ]
    return x.select(*keys, F.array(*cols).alias("vector"))


def export_graphs(pay: DataFrame, edges: DataFrame, keys=KEYS) -> DataFrame:
    """One row per flow with its payments and edges as arrays, for graph-level models."""
    inner = edges.join(pay.select(*keys, F.col("txn_id").alias("src_id")), "src_id").join(pay.select(*keys, F.col("txn_id").alias("dst_id")), ["dst_id", *keys])
    nodes = pay.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("txn_id", "us", "payer", "payee", "amount"))).alias("txns"))
    arcs = inner.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct("src_id", "dst_id"))).alias("edges"))
    return nodes.join(arcs, list(keys), "left")


def export_cases(cases: DataFrame, path: str) -> None:
    """One JSON document per flow."""
    cases.select(F.to_json(F.struct("*")).alias("value")).write.text(path)


def search(pay: DataFrame, acct: int, k: int, keys=KEYS) -> DataFrame:
    """The k flows in which an account moves most, and how much."""
    mine = pay.where((F.col("payer") == acct) | (F.col("payee") == acct))
    return mine.groupBy(*keys).agg(F.sum("amount").alias("moved"), F.count("*").alias("n")).orderBy(F.desc("moved"), *keys).limit(k)
