"""Hand fixtures F1-F4 and F7 as tables, and their answers (FIXTURES.md; time in days)."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

A, B, C, D, E, G, Z, K, X, Y, P, Q, R = range(1, 14)
#: Fixed values: (flow, id, day, payer, payee, amount).
PAYMENTS = [
    (1, 1, 1.0, A, B, 100), (1, 2, 2.0, B, C, 60), (1, 3, 2.0, B, D, 40), (1, 4, 4.0, C, E, 55), (1, 5, 4.0, D, E, 35), (1, 10, 1.5, G, B, 5),
    (2, 21, 1.0, A, B, 100), (2, 22, 2.0, B, C, 50), (2, 23, 2.0, B, D, 50), (2, 24, 3.0, D, C, 50),
    (3, 31, 1.0, A, B, 300), (3, 32, 2.0, B, Z, 100), (3, 33, 2.0, B, C, 30), (3, 34, 3.0, C, Z, 30), (3, 35, 2.0, B, D, 90), (3, 36, 3.0, D, E, 90), (3, 37, 4.0, E, Z, 90), (3, 38, 2.0, B, K, 30), (3, 39, 3.0, K, Z, 30),
    (4, 44, 1.0, P, Q, 9), (4, 45, 2.0, Q, R, 9), (4, 46, 3.0, R, P, 9),
]
MAXFLOW_ANSWERS = [(1, 90), (2, 100), (3, 250), (4, 0)]
SWEEP_ANSWERS = [(2, 3, 2, 3, 50, False), (2, 4, 3, 4, 50, False), (3, 3, 2, 3, 100, True), (3, 4, 5, 5, 60, False), (3, 5, 4, 5, 90, True)]
LOSS_ANSWERS = [(2, 100, True, 2, 0, 4), (3, 250, True, 3, 2, 2)]
FLAGGED = {"m1": "ABCD", "m2": "BCE", "m3": "A"}


def payments(spark: SparkSession) -> DataFrame:
    """TXN with the column ``flow``; each flow has accounts of its own."""
    rows = [(f, i, int(1_704_067_200 + d * 86_400), 100 * f + a, 100 * f + b, m) for f, i, d, a, b, m in PAYMENTS]
    x = spark.createDataFrame(rows, "flow long, txn_id long, s long, payer long, payee long, amount long")
    return x.select("flow", "txn_id", F.timestamp_seconds("s").alias("ts"), "payer", "payee", "amount", F.lit(None).cast("string").alias("channel"))


def flagged(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(m, f"{m}-1", ord(a)) for m, v in FLAGGED.items() for a in v], "method string, flow_key string, acct long")


def flagged_sql() -> str:
    rows = ", ".join(f"('{m}', '{m}-1', {ord(a)})" for m, v in FLAGGED.items() for a in v)
    return f"SELECT * FROM (VALUES {rows}) t(method, flow_key, acct)"


def values_sql(rows: list[tuple], columns: str) -> str:
    names = [c.split() for c in columns.split(", ")]
    cells = ", ".join("(" + ", ".join(str(v).lower() if isinstance(v, bool) else str(v) for v in r) + ")" for r in rows)
    return "SELECT " + ", ".join(f"CAST({n} AS {t}) AS {n}" for n, t in names) + f" FROM (VALUES {cells}) t({', '.join(n for n, _ in names)})"
