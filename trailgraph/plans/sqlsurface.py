"""S8, SURVEY 3.6: the engine's tables as SQL views, and helpers for SQL text."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def register(spark: SparkSession, **tables: DataFrame) -> None:
    """Temp views (txn, acct, tedge, sedge, wedge, member, flow, flagged ...); plans inline, so filters reach the scans."""
    for name, df in tables.items():
        df.createOrReplaceTempView(name)


def save(df: DataFrame, name: str, buckets: int | None = None, by: str | None = None) -> None:
    """A catalog table; bucketed where later joins on ``by`` should find their partitioning."""
    w = df.write.mode("overwrite")
    if buckets and by:
        w = w.bucketBy(buckets, by).sortBy(by)
    w.saveAsTable(name)


def co_weight_sql(n: str, n_out: str, n_in: str) -> str:
    """The co-occurrence weight as SQL text."""
    return f"greatest({n} / {n_out}, {n} / {n_in})"
