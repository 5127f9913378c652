"""The whole engine, ledger to cases, with a stage report; M17b variants by configuration."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trailgraph.functions.runtime import materialize
from trailgraph.operators import community, flows, prep, risk, second_order, temporal
from trailgraph.plans.config import TrailConfig
from trailgraph.plans.metrics import StageTimer
from trailgraph.sources import ledger, store


def ledger_of(spark: SparkSession, sf_dir: str, cfg: TrailConfig) -> DataFrame:
    """The cleaned ledger, without hubs where the configuration asks for that (``hubs=None``: by fraction)."""
    txn = ledger.load(spark, sf_dir, cfg.ledger)
    return txn if cfg.hubs == 0 else prep.drop_hubs(txn, cfg.top_fraction, cfg.hubs, cfg.degree_kind)


def edges_of(txn: DataFrame, cfg: TrailConfig) -> DataFrame:
    return temporal.build(txn, cfg.delta_w)


def wedges_of(edges: DataFrame, cfg: TrailConfig) -> DataFrame:
    """Weighted edges that survive pruning."""
    return second_order.weigh_and_prune(edges, 0.0 if cfg.skip_prune else cfg.min_weight, cfg.combine, cfg.count_mode)


def wedges_two_pass(txn: DataFrame, cfg: TrailConfig, path: str) -> DataFrame:
    """The same edges without ever storing the unpruned graph.

    Pass 1 adds up pair counts day by day; pass 2 joins again and keeps only edges whose pair survived.
    """
    from datetime import timedelta

    spark = txn.sparkSession
    t = txn.withColumn("__day", ledger.day(ledger.micros()))
    lo, hi = t.agg(F.min("__day"), F.max("__day")).first()
    if lo is None:
        return wedges_of(edges_of(txn, cfg), cfg)
    back = timedelta(days=-(-int(cfg.delta_w.total_seconds() * 1e6) // ledger.DAY))
    batch = 0
    while lo <= hi:
        near = t.where(F.col("__day").between(F.lit(lo - back), F.lit(lo)))
        store.write_pairs(second_order.pair_graph(temporal.bucketed(near, t.where(F.col("__day") == F.lit(lo)), cfg.delta_w), cfg.count_mode), path, batch)
        lo, batch = lo + timedelta(days=1), batch + 1
    w, _ = materialize(second_order.prune(second_order.weights(store.read_pairs(spark, path), cfg.combine), cfg.min_weight), "weights")
    return second_order.attach(edges_of(txn, cfg), w)


def run(spark: SparkSession, sf_dir: str, cfg: TrailConfig, method: str = "trail") -> dict[str, DataFrame]:
    """All stages: txn, wedges, member, pay, flagged, accounts, stages (name, seconds)."""
    timer = StageTimer(spark)
    with timer.stage("ledger"):
        txn, _ = materialize(ledger_of(spark, sf_dir, cfg), "txn")
        acct, _ = materialize(ledger.accounts(spark, sf_dir), "acct")
    with timer.stage("edges and weights"):
        w, _ = materialize(wedges_of(edges_of(txn, cfg), cfg), "wedges")
    keys = ("window_start", "comm_id") if cfg.window else ("comm_id",)
    with timer.stage("communities"):
        member, _ = materialize(community.detect(w, cfg.weight, cfg.quality, cfg.resolution, cfg.max_comm_size, cfg.window, cfg.assign, cfg.seed, cfg.engine, task_limit=cfg.task_limit), "member")
    pay = flows.payments(member, txn, keys)
    with timer.stage("flagging"):
        flagged, _ = materialize(risk.flag(pay, w, acct, cfg.segments, cfg.quantifier, cfg.sunk_lo, cfg.sunk_hi, cfg.flow_threshold, cfg.hold, keys=keys), "flagged")
    return {"txn": txn, "acct": acct, "wedges": w, "member": member, "pay": pay, "flagged": flagged, "accounts": risk.flagged_accounts(flagged, pay, method, keys), "stages": timer.report()}
