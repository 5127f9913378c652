"""The date-partitioned edge store with time travel, and additive pair counts per batch."""

from __future__ import annotations

from datetime import date

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

EDGE_SCHEMA = "src_id long, dst_id long, a long, b long, c long, t_src timestamp, t_dst timestamp, src_date date, dst_date date, batch_id long"
TXN_SCHEMA = "txn_id long, ts timestamp, payer long, payee long, amount long, channel string, date date"
PAIR_SCHEMA = "a long, b long, c long, n long, batch_id long"


def write_edges(edges: DataFrame, path: str, batch_id: int = 0) -> None:
    """Edges of one batch under ``src_date``/``dst_date``/``batch_id``; writing a batch again replaces it.

    Rows are sorted by the shared account and time, so that row groups can be skipped by account.
    """
    x = edges.withColumn("batch_id", F.lit(batch_id).cast("long"))
    x = x.hint("rebalance", "src_date", "dst_date").sortWithinPartitions("src_date", "dst_date", "b", "t_src")  # large days are split, small ones share a task
    x.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("src_date", "dst_date", "batch_id").parquet(path)


def read_edges(spark: SparkSession, path: str, src_between: tuple[date, date] | None = None, dst_between: tuple[date, date] | None = None, as_of: date | None = None, moment: date | None = None) -> DataFrame:
    """Edges by dates; all conditions are on partition columns. ``as_of``: the graph as it stood at the end of a day;
    ``moment``: money in transit over a day."""
    e = spark.read.schema(EDGE_SCHEMA).parquet(path)
    day = lambda d: F.lit(d).cast("date")
    if src_between:
        e = e.where(F.col("src_date").between(day(src_between[0]), day(src_between[1])))
    if dst_between:
        e = e.where(F.col("dst_date").between(day(dst_between[0]), day(dst_between[1])))
    if as_of:
        e = e.where((F.col("dst_date") <= day(as_of)) & (F.col("src_date") <= day(as_of)))
    if moment:
        e = e.where((F.col("src_date") <= day(moment)) & (F.col("dst_date") >= day(moment)))
    return e


def write_txn(txn: DataFrame, path: str) -> None:
    """Payments by day."""
    from trailgraph.sources.ledger import day, micros

    txn.withColumn("date", day(micros())).hint("rebalance", "date").sortWithinPartitions("date", "payee", "ts").write.mode("append").partitionBy("date").parquet(path)


def read_txn(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(TXN_SCHEMA).parquet(path)


def write_pairs(pairs: DataFrame, path: str, batch_id: int) -> None:
    """The pair counts that one batch of edges adds; a batch that is written again replaces itself."""
    pairs.select("a", "b", "c", "n").withColumn("batch_id", F.lit(batch_id).cast("long")).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("batch_id").parquet(path)


def read_pairs(spark: SparkSession, path: str) -> DataFrame:
    """SEDGE over all batches."""
    return spark.read.schema(PAIR_SCHEMA).parquet(path).groupBy("a", "b", "c").agg(F.sum("n").alias("n"))
