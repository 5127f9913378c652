"""M2: pre-processing - removal of the most connected accounts."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Most accounts that hub removal may name; more than that is no pre-processing any more, and no broadcast.
MAX_HUBS = 100_000


def degrees(txn: DataFrame, degree_kind: str = "txn") -> DataFrame:
    """(acct, degree): payments in and out, or distinct counterparties."""
    both = txn.select(F.col("payer").alias("acct"), F.col("payee").alias("other")).unionAll(txn.select(F.col("payee").alias("acct"), F.col("payer").alias("other")))
    how = {"txn": F.count("*"), "counterparty": F.countDistinct("other"), "counterparty_approx": F.approx_count_distinct("other", 0.02)}[degree_kind]
    return both.groupBy("acct").agg(how.alias("degree"))


def hubs(txn: DataFrame, top_fraction: float = 1e-6, k: int | None = None, degree_kind: str = "txn") -> DataFrame:
    """The top accounts by degree, ties by account id."""
    d = degrees(txn, degree_kind)
    if k is None:
        k = math.ceil(top_fraction * d.count())
    if k > MAX_HUBS:
        raise ValueError(f"{k} hubs; at most {MAX_HUBS} are broadcast")
    return d.orderBy(F.desc("degree"), "acct").limit(k)


def drop_hubs(txn: DataFrame, top_fraction: float = 1e-6, k: int | None = None, degree_kind: str = "txn") -> DataFrame:
    """The ledger without payments from or to a hub."""
    h = F.broadcast(hubs(txn, top_fraction, k, degree_kind).select(F.col("acct").alias("hub")))
    return txn.join(h, F.col("payer") == F.col("hub"), "left_anti").join(h, F.col("payee") == F.col("hub"), "left_anti")
