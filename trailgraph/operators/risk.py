"""Risk criteria on flows. One code path judges the flows of every method.

C1: dispense and sink accounts lie in given segments. C2: the share of the dispensed amount that is sunk lies in a
range. C3: the temporal maximum flow is over a threshold. Cheap ones first: C3 sees survivors only.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from trailgraph.operators import flows, maxflow_kernel
from trailgraph.operators.flows import KEYS

SEGMENTS = ("HOUSEHOLD", "MACHINERY", "FURNITURE")


def segment_ok(role: DataFrame, acct: DataFrame, segments=SEGMENTS, quantifier: str = "all", keys=KEYS) -> DataFrame:
    """(keys, c1). ``all``: every dispense and sink account qualifies, and there are both; ``any``: one of each."""
    ends = role.where("role <> 'mid'").join(acct.select("acct", "segment"), "acct", "left").withColumn("ok", F.coalesce(F.col("segment").isin(*segments), F.lit(False)))
    of = lambda r: F.col("role") == r
    if quantifier == "all":
        ok = F.bool_and("ok") & F.bool_or(of("dispense")) & F.bool_or(of("sink"))
    else:
        ok = F.bool_or(of("dispense") & F.col("ok")) & F.bool_or(of("sink") & F.col("ok"))
    found = ends.groupBy(*keys).agg(ok.alias("c1"))
    return role.select(*keys).distinct().join(found, list(keys), "left").select(*keys, F.coalesce("c1", F.lit(False)).alias("c1"))


def sunk_pct(summary: DataFrame, lo: float, hi: float, keys=KEYS) -> DataFrame:
    """(keys, sunk_pct, c2)."""
    return summary.select(*keys, "sunk_pct", F.coalesce(F.col("sunk_pct").between(lo, hi), F.lit(False)).alias("c2"))


def temporal_max_flow(pay: DataFrame, edges: DataFrame | None, hold: str = "window", keys=KEYS) -> DataFrame:
    """C3's amount: (keys, max_flow). A flow's payments and edges are packed into one row, bounded by the size of a flow."""
    packed = pay.groupBy(*keys).agg(F.array_sort(F.collect_list(F.array("txn_id", "us", "payer", "payee", "amount"))).alias("txns"))
    if hold == "window":
        own = lambda c: pay.select(*keys, F.col("txn_id").alias(c))
        inner = edges.select("src_id", "dst_id").join(own("src_id"), "src_id").join(own("dst_id"), ["dst_id", *keys]).groupBy(*keys).agg(F.collect_list(F.array("src_id", "dst_id")).alias("arcs"))
        packed = packed.join(inner, list(keys), "left")
    else:
        packed = packed.withColumn("arcs", F.lit(None).cast("array<array<bigint>>"))
    kinds = dict(packed.dtypes)

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            out = f[list(keys)].copy()
            found = []
            for txns, arcs in zip(f["txns"], f["arcs"]):
                rows = [tuple(int(v) for v in x) for x in txns]
                found.append(maxflow_kernel.windowed(rows, [tuple(map(int, e)) for e in (arcs if arcs is not None else ())]) if hold == "window" else maxflow_kernel.unbounded(rows))
            out["max_flow"] = found
            yield out

    return packed.mapInPandas(run, ", ".join(f"{k} {kinds[k]}" for k in keys) + ", max_flow long")


def temporal_max_flow_cogrouped(pay: DataFrame, edges: DataFrame, keys=KEYS) -> DataFrame:
    """The same amount with payments and edges as two cogrouped tables (J13, U2), for flows too large for one row."""
    kinds = dict(pay.dtypes)
    own = lambda c: pay.select(*keys, F.col("txn_id").alias(c))
    inner = edges.select("src_id", "dst_id").join(own("src_id"), "src_id").join(own("dst_id"), ["dst_id", *keys]).select(*[F.col(k).alias(k) for k in keys], "src_id", "dst_id")

    def solve(key: tuple, p: pd.DataFrame, e: pd.DataFrame) -> pd.DataFrame:
        txns = list(p[["txn_id", "us", "payer", "payee", "amount"]].itertuples(index=False, name=None))
        return pd.DataFrame([(*key, maxflow_kernel.windowed(txns, list(e[["src_id", "dst_id"]].itertuples(index=False, name=None))))], columns=[*keys, "max_flow"])

    schema = ", ".join(f"{k} {kinds[k]}" for k in keys) + ", max_flow long"
    return pay.groupBy(*keys).cogroup(inner.groupBy(*keys)).applyInPandas(solve, schema)


@dataclass(frozen=True)
class Criterion:
    """A named condition on the columns of a flow's summary."""

    name: str
    holds: Callable[[], Column]


def flag(pay: DataFrame, edges: DataFrame, acct: DataFrame, segments=SEGMENTS, quantifier: str = "all", lo: float = 50.0, hi: float = 150.0, threshold: int = 500_000, hold: str = "window", more: tuple[Criterion, ...] = (), keys=KEYS) -> DataFrame:
    """FLOW rows with c1, c2, max_flow, c3, suspicious; max_flow is null where C1 or C2 fails already."""
    role = flows.roles(pay, keys)
    x = flows.summarize(pay, role, keys).join(segment_ok(role, acct, segments, quantifier, keys), list(keys))
    x = x.withColumn("c2", F.coalesce(F.col("sunk_pct").between(lo, hi), F.lit(False)))
    extra = F.lit(True)
    for c in more:
        x = x.withColumn(c.name, F.coalesce(c.holds(), F.lit(False)))
        extra = extra & F.col(c.name)
    alive = x.where(F.col("c1") & F.col("c2") & extra).select(*keys)
    c3 = temporal_max_flow(pay.join(alive, list(keys), "left_semi"), edges, hold, keys)
    x = x.join(c3, list(keys), "left").withColumn("c3", F.coalesce(F.col("max_flow") > threshold, F.lit(False)))
    return x.withColumn("suspicious", F.col("c1") & F.col("c2") & F.col("c3") & extra)


def flagged_accounts(flagged: DataFrame, pay: DataFrame, method: str, keys=KEYS) -> DataFrame:
    """FLAGGED(method, flow_key, acct): every account of a suspicious flow."""
    bad = flagged.where("suspicious").select(*keys)
    return pay.join(bad, list(keys), "left_semi").select(F.lit(method).alias("method"), F.concat_ws("|", *[F.col(k).cast("string") for k in keys]).alias("flow_key"), F.explode(F.array("payer", "payee")).alias("acct")).distinct()


def features(pay: DataFrame, acct: DataFrame, cash: tuple[str, ...] = ("purchase",), high_risk: tuple[int, ...] = (), keys=KEYS) -> DataFrame:
    """(keys, cash_share, high_risk_share, max_turnover_z): other risks, per flow.

    The z-score of an account's turnover is taken inside its segment over all accounts of the given flows.
    """
    amount = F.col("amount")
    nation = acct.select("acct", "nation", "segment")
    x = pay.join(nation.select(F.col("acct").alias("payer"), F.col("nation").alias("n1")), "payer", "left").join(nation.select(F.col("acct").alias("payee"), F.col("nation").alias("n2")), "payee", "left")
    risky = F.coalesce(F.col("n1").isin(*high_risk), F.lit(False)) | F.coalesce(F.col("n2").isin(*high_risk), F.lit(False)) if high_risk else F.lit(False)
    per = x.groupBy(*keys).agg(
        (F.sum(F.when(F.col("channel").isin(*cash), amount).otherwise(0)).cast("double") / F.sum(amount).cast("double")).alias("cash_share"),
        (F.sum(F.when(risky, amount).otherwise(0)).cast("double") / F.sum(amount).cast("double")).alias("high_risk_share"),
    )
    turnover = pay.select("txn_id", "amount", F.explode(F.array("payer", "payee")).alias("acct")).distinct().groupBy("acct").agg(F.sum("amount").alias("turnover")).join(nation.select("acct", "segment"), "acct", "left")
    w = Window.partitionBy("segment")
    z = turnover.select("acct", F.try_divide(F.col("turnover") - F.avg("turnover").over(w), F.stddev_samp("turnover").over(w)).alias("z"))
    worst = pay.select(*keys, F.explode(F.array("payer", "payee")).alias("acct")).distinct().join(z, "acct").groupBy(*keys).agg(F.max("z").alias("max_turnover_z"))
    return per.join(worst, list(keys))
