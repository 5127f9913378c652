"""Cost and accuracy measures."""

from __future__ import annotations

import time
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trailgraph.operators import temporal


def funnel(stages: list[tuple[str, DataFrame | None, DataFrame | None]]) -> DataFrame:
    """(step, name, n_txn, n_edge). A stage has a ledger (its payments count), or edges (payments that touch one)."""
    out = None
    for i, (name, txn, edges) in enumerate(stages):
        if edges is None:
            row = txn.agg(F.count("*").alias("n_txn")).select(F.lit(i).alias("step"), F.lit(name).alias("stage"), "n_txn", F.lit(None).cast("long").alias("n_edge"))
        else:
            n = temporal.live_ids(edges).agg(F.count("*").alias("n_txn"))
            row = n.crossJoin(edges.agg(F.count("*").alias("n_edge"))).select(F.lit(i).alias("step"), F.lit(name).alias("stage"), "n_txn", "n_edge")
        out = row if out is None else out.unionByName(row)
    return out


def prune_ratio(edges: DataFrame, kept: DataFrame) -> DataFrame:
    """Counts before and after pruning and their ratios."""
    f = funnel([("before", None, edges), ("after", None, kept)])
    at = lambda s, c: F.max(F.when(F.col("stage") == s, F.col(c)))
    x = f.agg(at("before", "n_txn").alias("txn_before"), at("before", "n_edge").alias("edges_before"), at("after", "n_txn").alias("txn_after"), at("after", "n_edge").alias("edges_after"))
    r = lambda a, b: F.round(F.try_divide(F.col(a), F.col(b)), 6)
    return x.select("*", r("edges_after", "edges_before").alias("edges_kept"), r("txn_after", "txn_before").alias("txn_kept"), r("edges_before", "txn_before").alias("per_txn_before"), r("edges_after", "txn_after").alias("per_txn_after"))


def retention(before: DataFrame, after: DataFrame) -> DataFrame:
    """Payments before and after a filter."""
    x = before.agg(F.count("*").alias("n_before")).crossJoin(after.agg(F.count("*").alias("n_after")))
    return x.select("*", F.round(F.try_divide("n_after", "n_before"), 6).alias("kept"))


def coverage(flagged: DataFrame) -> DataFrame:
    """(method, n_acct, n_union, coverage_pct) from FLAGGED."""
    union = flagged.agg(F.countDistinct("acct").alias("n_union"))
    per = flagged.groupBy("method").agg(F.countDistinct("acct").alias("n_acct"))
    return per.crossJoin(F.broadcast(union)).select("method", "n_acct", "n_union", (F.col("n_acct") * 100 / F.col("n_union")).alias("coverage_pct"))


def cases(flagged: DataFrame) -> DataFrame:
    """Flagged flows of each method."""
    return flagged.groupBy("method").agg(F.countDistinct("flow_key").alias("n_cases"))


def overlap(member: DataFrame, item: str = "txn_id") -> DataFrame:
    """(n_items, n_shared, mean_flows) for payments or accounts in flows."""
    per = member.groupBy(item).agg(F.count("*").alias("n"))
    return per.agg(F.count("*").alias("n_items"), F.count_if(F.col("n") > 1).alias("n_shared"), F.round(F.avg("n"), 6).alias("mean_flows"))


def topology_hist(summary: DataFrame, measures=("diameter", "n_dispense", "n_sink"), flag: str = "suspicious") -> DataFrame:
    """(measure, value, n_in_scope, n_suspicious)."""
    long = summary.select(F.col(flag).alias("bad"), F.explode(F.map_from_arrays(F.array(*[F.lit(m) for m in measures]), F.array(*[F.col(m).cast("long") for m in measures]))).alias("measure", "value"))
    return long.groupBy("measure", "value").agg(F.count("*").alias("n_in_scope"), F.count_if("bad").alias("n_suspicious"))


def linearity(rows: DataFrame, x: str = "n_txn", y: str = "seconds") -> DataFrame:
    """Slope and r squared per stage."""
    return rows.groupBy("stage").agg(F.regr_slope(F.col(y), F.col(x)).alias("slope"), F.regr_r2(F.col(y), F.col(x)).alias("r2"), F.count("*").alias("n"))


class StageTimer:
    """Seconds per stage on the driver's clock."""

    def __init__(self, spark: SparkSession):
        self.spark, self.rows = spark, []

    @contextmanager
    def stage(self, name: str, **facts):
        began = time.perf_counter()
        yield
        self.rows.append((name, time.perf_counter() - began, int(facts.get("n_txn", 0)), int(facts.get("batch", 0))))

    def report(self) -> DataFrame:
        return self.spark.createDataFrame(self.rows, "stage string, seconds double, n_txn long, batch long")
