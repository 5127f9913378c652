"""M3d, T1-T11, S6: Structured Streaming forms. All take a streaming TXN with ``ts`` as TIMESTAMP."""

from __future__ import annotations

from collections.abc import Iterator
from datetime import timedelta

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from trailgraph.operators import second_order
from trailgraph.sources import ledger, store


def events(spark: SparkSession, path: str, per_trigger: int | None = None) -> DataFrame:
    """A folder of event files as a stream of TXN."""
    schema = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"
    r = spark.readStream.schema(schema)
    if per_trigger:
        r = r.option("maxFilesPerTrigger", per_trigger)
    e = r.parquet(path)
    return ledger.clean(ledger.from_events(e))


def temporal_edges(stream: DataFrame, delta_w: timedelta, lateness: str = "1 hour") -> DataFrame:
    """T5: stream-stream interval join. State holds payments of delta_w plus the lateness."""
    us = delta_w // timedelta(microseconds=1)
    s = stream.select(F.col("txn_id").alias("src_id"), F.col("payer").alias("a"), F.col("payee").alias("b"), F.col("ts").alias("t_src")).withWatermark("t_src", lateness)
    t = stream.select(F.col("txn_id").alias("dst_id"), F.col("payer").alias("b2"), F.col("payee").alias("c"), F.col("ts").alias("t_dst")).withWatermark("t_dst", lateness)
    on = (F.col("b") == F.col("b2")) & (F.col("t_dst") > F.col("t_src")) & (F.col("t_dst") < F.col("t_src") + F.expr(f"make_dt_interval(0, 0, 0, {us / 1e6:.6f})"))
    return s.join(t, on).select("src_id", "dst_id", "a", "b", "c", "t_src", "t_dst")


def tumbling(stream: DataFrame, width: str = "1 day", lateness: str = "1 hour") -> DataFrame:
    """Turnover of each payer per window."""
    return stream.withWatermark("ts", lateness).groupBy(F.window("ts", width), "payer").agg(F.sum("amount").alias("paid"), F.count("*").alias("n")).select(F.unix_micros("window.start").alias("start_us"), "payer", "paid", "n")


def sliding(stream: DataFrame, width: str = "7 days", step: str = "1 day", lateness: str = "1 hour") -> DataFrame:
    """T3."""
    return stream.withWatermark("ts", lateness).groupBy(F.window("ts", width, step), "payer").agg(F.sum("amount").alias("paid"), F.count("*").alias("n")).select(F.unix_micros("window.start").alias("start_us"), "payer", "paid", "n")


def sessions(stream: DataFrame, gap: str = "6 hours", lateness: str = "1 hour") -> DataFrame:
    """T4: spells of activity of each payer."""
    return stream.withWatermark("ts", lateness).groupBy(F.session_window("ts", gap), "payer").agg(F.sum("amount").alias("paid"), F.count("*").alias("n")).select(F.unix_micros("session_window.start").alias("start_us"), "payer", "paid", "n")


def enriched(stream: DataFrame, acct: DataFrame) -> DataFrame:
    """Stream-static join with the payer's segment and bank."""
    return stream.join(acct.select(F.col("acct").alias("payer"), "segment", "bank"), "payer", "left")


def deduplicated(stream: DataFrame, lateness: str = "1 day") -> DataFrame:
    """T8."""
    return stream.withWatermark("ts", lateness).dropDuplicatesWithinWatermark(["txn_id"])


def balances(stream: DataFrame) -> DataFrame:
    """Running balance of each account, as a custom stateful operator (update mode)."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    moves = stream.select(F.explode(F.array(F.struct(F.col("payer").alias("acct"), (-F.col("amount")).alias("m")), F.struct(F.col("payee").alias("acct"), F.col("amount").alias("m")))).alias("x")).select("x.acct", "x.m")

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0)
        for f in frames:
            n, total = n + len(f), total + int(f["m"].sum())
        state.update((n, total))
        yield pd.DataFrame({"acct": [key[0]], "n": [n], "balance": [total]})

    return moves.groupBy("acct").applyInPandasWithState(step, "acct long, n long, balance long", "n long, balance long", "update", GroupStateTimeout.NoTimeout)


def pair_counts(stream_edges: DataFrame, path: str, checkpoint: str):
    """Pair counts of each micro-batch under its batch id; a batch that runs twice counts once."""
    def add(batch: DataFrame, batch_id: int) -> None:
        store.write_pairs(second_order.pair_graph(batch), path, batch_id)

    return stream_edges.writeStream.foreachBatch(add).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def drain(stream: DataFrame, path: str, checkpoint: str, mode: str = "append") -> None:
    """Run over all that is there, to Parquet; a second run goes on from the checkpoint."""
    q = stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()


def collect_final(stream: DataFrame, name: str, mode: str = "complete") -> DataFrame:
    """All output of a stream over what is there, in a memory table (for small results and tests)."""
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.table(name)
