"""Streams against their batch forms."""

from datetime import timedelta

from pyspark.sql import functions as F

from trailgraph.operators import temporal
from trailgraph.sources import ledger
from trailgraph.streaming import streams


def _files(spark, sf, tmp_path, n=3):
    path = str(tmp_path / "in")
    spark.read.parquet(f"{sf}/events.parquet").repartitionByRange(n, "ts").write.parquet(path)
    return path


def test_restart_goes_on(spark, sf, tmp_path):
    src, out, mark = _files(spark, sf, tmp_path), str(tmp_path / "out"), str(tmp_path / "mark")
    for _ in range(2):
        streams.drain(streams.temporal_edges(streams.events(spark, src), timedelta(days=1), "40 days"), out, mark)
    got = sorted((r.src_id, r.dst_id) for r in spark.read.parquet(out).select("src_id", "dst_id").collect())
    want = sorted((r.src_id, r.dst_id) for r in temporal.build(ledger.load(spark, sf), timedelta(days=1)).select("src_id", "dst_id").collect())
    assert got == want


def test_late_rows_are_dropped(spark, sf, tmp_path):
    first, late = str(tmp_path / "in"), str(tmp_path / "late")
    e = spark.read.parquet(f"{sf}/events.parquet")
    e.where("ts >= timestamp_ntz'2024-01-20'").coalesce(1).write.parquet(first)
    out, mark = str(tmp_path / "out"), str(tmp_path / "mark")
    run = lambda: streams.drain(streams.tumbling(streams.events(spark, first), lateness="1 hour"), out, mark)
    run()
    e.where("ts < timestamp_ntz'2024-01-02'").coalesce(1).write.mode("append").parquet(first)
    run()
    assert spark.read.parquet(out).where(F.col("start_us") < 1_705_000_000_000_000).count() == 0
    assert late
