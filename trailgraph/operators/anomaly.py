"""Traditional anomaly scores on vectors (id, array of numbers)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

MAX_REFERENCE = 1 << 22  # numbers of the query block that kNN broadcasts at a time


def moments(v: DataFrame, col: str = "vector") -> DataFrame:
    """(dim, mean, sd) over all vectors."""
    return v.select(F.posexplode(col).alias("dim", "x")).groupBy("dim").agg(F.avg(F.col("x").cast("double")).alias("mean"), F.stddev_pop(F.col("x").cast("double")).alias("sd"))


def _scaled(v: DataFrame, id_col: str, col: str) -> DataFrame:
    m = F.broadcast(moments(v, col).agg(F.array_sort(F.collect_list(F.struct("dim", "mean", "sd"))).alias("m")))  # one row per dimension
    return v.select(id_col, col).join(m).select(id_col, F.zip_with(col, "m", lambda x, y: F.coalesce(F.try_divide(x.cast("double") - y["mean"], y["sd"]), F.lit(0.0))).alias("z"))


def zscore(v: DataFrame, id_col: str, col: str = "vector") -> DataFrame:
    """(id, score): largest absolute z of any dimension."""
    return _scaled(v, id_col, col).select(id_col, F.array_max(F.transform("z", lambda x: F.abs(x))).alias("score"))


def mahalanobis_diag(v: DataFrame, id_col: str, col: str = "vector") -> DataFrame:
    """(id, score): Mahalanobis distance with a diagonal covariance."""
    return _scaled(v, id_col, col).select(id_col, F.sqrt(F.aggregate("z", F.lit(0.0), lambda s, x: s + x * x)).alias("score"))


def iqr(v: DataFrame, id_col: str, value: str, k: float = 1.5) -> DataFrame:
    """(id, value, outlier) by the interquartile range of one column."""
    q = F.broadcast(v.agg(F.percentile(value, [0.25, 0.75]).alias("q")))
    span = F.col("q")[1] - F.col("q")[0]
    return v.join(q).select(id_col, value, ((F.col(value) < F.col("q")[0] - k * span) | (F.col(value) > F.col("q")[1] + k * span)).alias("outlier"))


def knn_distance(v: DataFrame, id_col: str, col: str = "vector", k: int = 5, every: int = 50) -> DataFrame:
    """(id, score): distance to the k-th nearest other vector, for every row whose id is divisible by ``every``.

    The queries are broadcast in blocks of bounded size; all vectors pass each block once and only the
    k best per task go on.
    """
    spark = v.sparkSession
    queries = v.where(F.pmod(F.col(id_col), F.lit(every)) == 0).select(id_col, F.col(col).cast("array<float>").alias("x"))
    parts, ids, rows, size = [], [], [], 0

    def part() -> DataFrame:
        block = spark.sparkContext.broadcast((np.array(ids), np.array(rows, np.float64)))

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            qi, q = block.value
            for f in frames:
                if not len(f):
                    continue
                x = np.stack(f["x"].to_numpy()).astype(np.float64)
                d = np.sqrt(np.maximum((q * q).sum(1)[:, None] + (x * x).sum(1)[None] - 2 * q @ x.T, 0))
                d[qi[:, None] == f[id_col].to_numpy()[None]] = np.inf
                n = min(k, d.shape[1])
                best = np.sort(np.partition(d, n - 1, axis=1)[:, :n], axis=1)
                yield pd.DataFrame({id_col: np.repeat(qi, n), "d": best.ravel()})

        return v.select(id_col, F.col(col).cast("array<float>").alias("x")).mapInPandas(run, f"{id_col} long, d double")

    for r in queries.toLocalIterator():
        ids.append(r[0])
        rows.append(r[1])
        size += len(r[1])
        if size >= MAX_REFERENCE:
            parts.append(part())
            ids, rows, size = [], [], 0
    if ids or not parts:
        parts.append(part() if ids else v.select(id_col, F.lit(0.0).alias("d")).limit(0))
    near = parts[0]
    for p in parts[1:]:
        near = near.unionByName(p)
    best = near.where("d < double('infinity')").groupBy(id_col).agg(F.slice(F.sort_array(F.collect_list("d")), 1, k).alias("d"))
    return best.select(id_col, F.element_at("d", -1).alias("score"))
