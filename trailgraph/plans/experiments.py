"""The reference's experiments on the given tables, as tables of measurements."""

from __future__ import annotations

from datetime import timedelta

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trailgraph.baselines import motif
from trailgraph.functions.runtime import materialize
from trailgraph.operators import community, flows, risk, second_order, temporal
from trailgraph.plans.config import TrailConfig
from trailgraph.plans.metrics import StageTimer
from trailgraph.plans.pipeline import edges_of, ledger_of, wedges_of
from trailgraph.sources import ledger

DAY = 86_400_000_000


def batches(txn: DataFrame, days: int, delta_w: timedelta) -> DataFrame:
    """W4 without a clock: (batch, n_txn, n_new_edges) when batches of ``days`` days are appended in order."""
    lo, hi = txn.agg(F.min(ledger.micros()), F.max(ledger.micros())).first()
    first = lo // DAY * DAY
    out, n = None, 0
    while first + n * days * DAY <= hi:
        a, b = first + n * days * DAY, first + (n + 1) * days * DAY
        us = ledger.micros()
        new, old = txn.where((us >= a) & (us < b)), txn.where(us < a)
        row = new.agg(F.lit(n).alias("batch"), F.count("*").alias("n_txn")).crossJoin(temporal.append(old, new, delta_w).agg(F.count("*").alias("n_new_edges")))
        out = row if out is None else out.unionByName(row)
        n += 1
    return out


def batch_runtimes(spark: SparkSession, sf_dir: str, cfg: TrailConfig, days=(1, 3, 7, 15, 30)) -> DataFrame:
    """Seconds per stage for one batch of each length; feed it to ``metrics.linearity``."""
    txn, _ = materialize(ledger_of(spark, sf_dir, cfg), "txn")
    first = txn.agg(F.min(ledger.micros())).first()[0] // DAY * DAY
    timer = StageTimer(spark)
    for d in days:
        part = txn.where(ledger.micros() < first + d * DAY)
        facts = {"n_txn": part.count(), "batch": d}
        with timer.stage("edges", **facts):
            e, _ = materialize(edges_of(part, cfg), "edges")
        with timer.stage("weights and pruning", **facts):
            w, _ = materialize(wedges_of(e, cfg), "wedges")
        with timer.stage("communities", **facts):
            materialize(community.detect(w, cfg.weight, max_comm_size=cfg.max_comm_size), "member")
    return timer.report()


def detection_runtimes(spark: SparkSession, sf_dir: str, cfg: TrailConfig, hops=(2, 3, 4, 5, 6)) -> DataFrame:
    """Seconds of detection and of flagging for communities and for motifs of each number of hops."""
    txn, _ = materialize(ledger_of(spark, sf_dir, cfg), "txn")
    acct = ledger.accounts(spark, sf_dir)
    w, _ = materialize(wedges_of(edges_of(txn, cfg), cfg), "wedges")
    timer = StageTimer(spark)
    with timer.stage("communities: detection"):
        m, _ = materialize(community.detect(w, cfg.weight, max_comm_size=cfg.max_comm_size), "member")
    with timer.stage("communities: flagging"):
        materialize(risk.flag(flows.payments(m, txn), w, acct, threshold=cfg.flow_threshold), "flagged")
    ends, keys = acct.where(F.col("segment").isin(*cfg.segments)).select("acct"), ("first_payer", "last_payee")
    for h in hops:
        with timer.stage(f"motif {h}: detection", batch=h):
            m, _ = materialize(motif.members(w, h, first=ends, last=ends), "member")
        with timer.stage(f"motif {h}: flagging", batch=h):
            materialize(risk.flag(flows.payments(m, txn, keys), w, acct, threshold=cfg.flow_threshold, keys=keys), "flagged")
    return timer.report()


def sweep(txn: DataFrame, deltas: tuple[timedelta, ...], thetas: tuple[float, ...]) -> DataFrame:
    """How edges move with the look-ahead and the weight bound: (delta_hours, min_weight, n_edge)."""
    out = None
    for d in deltas:
        e = temporal.build(txn, d)
        w = second_order.attach(e, second_order.weights(second_order.pair_graph(e)))
        row = w.select(F.lit(d.total_seconds() / 3600).alias("delta_hours"), "w", F.explode(F.array(*[F.lit(t) for t in thetas])).alias("min_weight")).groupBy("delta_hours", "min_weight").agg(F.count_if(F.col("w") >= F.col("min_weight")).alias("n_edge"))
        out = row if out is None else out.unionByName(row)
    return out
