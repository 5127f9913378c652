"""M3: the temporal graph of sequential transactions.

An edge goes from a payment to every later payment that its receiver makes within the look-ahead:
shared account, and t_src < t_dst < t_src + delta_w, both strictly. All methods give the same edges.
"""

from __future__ import annotations

from datetime import timedelta

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trailgraph.functions.runtime import scratch_path
from trailgraph.sources.ledger import DAY, day, micros

EDGE = ["src_id", "dst_id", "a", "b", "c", "t_src", "t_dst", "src_date", "dst_date"]


def _us(delta: timedelta) -> int:
    return delta // timedelta(microseconds=1)


def _source_side(txn: DataFrame) -> DataFrame:
    return txn.select(F.col("txn_id").alias("src_id"), F.col("payer").alias("a"), F.col("payee").alias("b"), F.col("ts").alias("t_src"), micros().alias("us"))


def _target_side(txn: DataFrame) -> DataFrame:
    return txn.select(F.col("txn_id").alias("dst_id"), F.col("payer").alias("b2"), F.col("payee").alias("c"), F.col("ts").alias("t_dst"), micros().alias("ud"))


def _in_window(width: int):
    return (F.col("us") < F.col("ud")) & (F.col("ud") < F.col("us") + F.lit(width))


def _edges(joined: DataFrame) -> DataFrame:
    return joined.select("src_id", "dst_id", "a", "b", "c", "t_src", "t_dst", day(F.col("us")).alias("src_date"), day(F.col("ud")).alias("dst_date"))


def interval(sources: DataFrame, targets: DataFrame, delta_w: timedelta) -> DataFrame:
    """Plain form: equi join on the account, time bounds as a residual."""
    s, t = _source_side(sources), _target_side(targets)
    return _edges(s.join(t, (F.col("b") == F.col("b2")) & _in_window(_us(delta_w))))


def bucketed(sources: DataFrame, targets: DataFrame, delta_w: timedelta, bucket: timedelta | None = None, salts: int = 1) -> DataFrame:
    """Keys (account, time bucket): a source goes to the buckets it reaches, a target lies in one.

    A hub is so cut by time; ``salts`` cuts its buckets further (targets dealt out, sources copied).
    """
    width, b = _us(delta_w), _us(bucket or delta_w)
    slots = F.explode(F.sequence(F.floor((F.col("us") + 1) / b), F.floor((F.col("us") + width - 1) / b)))
    s = _source_side(sources).where(F.lit(width > 1)).withColumn("slot", slots)
    t = _target_side(targets).withColumn("slot2", F.floor(F.col("ud") / b))
    on = (F.col("b") == F.col("b2")) & (F.col("slot") == F.col("slot2"))
    if salts > 1:
        s = s.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
        t = t.withColumn("salt2", F.pmod(F.xxhash64("dst_id"), F.lit(salts)).cast("int"))
        on = on & (F.col("salt") == F.col("salt2"))
    return _edges(s.join(t, on & _in_window(width)))


def theta_join(s: DataFrame, t: DataFrame, width: int, accounts: int = 16) -> DataFrame:
    """Sources (b, us) and targets (b2, ud) by inequalities alone: b and b2 less than 1 apart, us < ud < us + width.

    Both sides are cut into blocks of ``accounts`` neighbouring account numbers and one ``width`` of time. A nested loop holds the
    bounds of all blocks against each other; the rows of two blocks that can meet are compared one by one.
    """

    def blocks(x: DataFrame, acct: str, us: str, k: str) -> tuple[DataFrame, DataFrame]:
        x = x.withColumn(f"{k}a", F.floor(F.col(acct) / accounts)).withColumn(f"{k}u", F.floor(F.col(us) / width))
        ends = [f(c).alias(f"{k}_{n}") for f, c, n in ((F.min, acct, "lo"), (F.max, acct, "hi"), (F.min, us, "from"), (F.max, us, "to"))]
        return x, x.groupBy(f"{k}a", f"{k}u").agg(*ends)

    (s, p), (t, q) = blocks(s, "b", "us", "s"), blocks(t, "b2", "ud", "t")
    can = (F.col("s_lo") - F.col("t_hi") < 1) & (F.col("t_lo") - F.col("s_hi") < 1) & (F.col("s_from") < F.col("t_to")) & (F.col("t_from") < F.col("s_to") + width)
    met = p.hint("broadcast").join(q, can).select("sa", "su", "ta", "tu")
    near = (F.abs(F.col("b") - F.col("b2")) < 1) & (F.col("us") < F.col("ud")) & (F.col("ud") < F.col("us") + width)
    return s.join(met.join(t, ["ta", "tu"]), ["sa", "su"]).where(near)


def candidates(txn: DataFrame, delta_w: timedelta) -> DataFrame:
    """Pairs each (account, bucket) will compare: tells skew before the join."""
    width = _us(delta_w)
    s = _source_side(txn).withColumn("slot", F.explode(F.sequence(F.floor((F.col("us") + 1) / width), F.floor((F.col("us") + width - 1) / width)))).groupBy("b", "slot").agg(F.count("*").alias("n_src"))
    t = _target_side(txn).groupBy(F.col("b2").alias("b"), F.floor(F.col("ud") / width).alias("slot")).agg(F.count("*").alias("n_dst"))
    return s.join(t, ["b", "slot"]).select("b", "slot", (F.col("n_src") * F.col("n_dst")).alias("pairs"))


def daily(txn: DataFrame, delta_w: timedelta, path: str | None = None) -> DataFrame:
    """One destination day at a time, each appended to a date-partitioned store; restartable by day."""
    spark = txn.sparkSession
    path = path or scratch_path(spark, "daily-edges")
    lo, hi = txn.agg(F.min(day(micros())), F.max(day(micros()))).first()
    if lo is None:
        return bucketed(txn, txn, delta_w)
    stored = scratch_path(spark, "daily-ledger")
    txn.withColumn("__day", day(micros())).hint("rebalance", "__day").write.partitionBy("__day").parquet(stored)  # so that a step reads its days only
    t = spark.read.schema(txn.select("*", day(micros()).alias("__day")).schema).parquet(stored)
    back = timedelta(days=-(-_us(delta_w) // DAY))
    while lo <= hi:
        near = t.where(F.col("__day").between(F.lit(lo - back), F.lit(lo)))
        bucketed(near, t.where(F.col("__day") == F.lit(lo)), delta_w).hint("rebalance", "src_date", "dst_date").write.mode("append").partitionBy("src_date", "dst_date").parquet(path)
        lo += timedelta(days=1)
    schema = bucketed(txn, txn, delta_w).schema
    return spark.read.schema(schema).parquet(path).select(EDGE)


def build(txn: DataFrame, delta_w: timedelta, method: str = "bucketed", **kw) -> DataFrame:
    """TXN -> TEDGE by ``bucketed`` (default), ``interval`` or ``daily``."""
    if method == "daily":
        return daily(txn, delta_w, **kw)
    return {"bucketed": bucketed, "interval": interval}[method](txn, txn, delta_w, **kw)


def append(stored: DataFrame, new: DataFrame, delta_w: timedelta) -> DataFrame:
    """The edges that a batch adds: new to all, and old to new. Payments already stored are passed over.

    Only stored payments within delta_w of the batch take part; on a date-partitioned ledger that prunes.
    """
    new = new.join(stored.select("txn_id"), "txn_id", "left_anti")
    span = new.agg(F.min(micros()), F.max(micros())).first()
    if span[0] is None:
        return bucketed(new, new, delta_w)
    width = _us(delta_w)
    old = stored.where(F.col("ts").between(F.timestamp_micros(F.lit(span[0] - width)), F.timestamp_micros(F.lit(span[1] + width))))
    return bucketed(new, old.unionByName(new), delta_w).unionByName(bucketed(old, new, delta_w))


def latest_receipt(txn: DataFrame) -> DataFrame:
    """As-of join - each payment with the latest strictly earlier receipt of its payer (lean form of the graph)."""
    from pyspark.sql import Window

    inn = txn.select(F.col("payee").alias("acct"), micros().alias("u"), F.lit(1).alias("kind"), F.struct(micros().alias("u"), "txn_id").alias("r"), F.lit(None).cast("long").alias("txn_id"))
    out = txn.select(F.col("payer").alias("acct"), micros().alias("u"), F.lit(0).alias("kind"), F.lit(None).cast("struct<u:bigint,txn_id:bigint>").alias("r"), "txn_id")
    w = Window.partitionBy("acct").orderBy("u", "kind").rowsBetween(Window.unboundedPreceding, 0)  # a payment sorts before receipts of its own instant
    both = inn.unionByName(out).withColumn("prev", F.max("r").over(w))
    return both.where("kind = 0").select("txn_id", F.col("prev.txn_id").alias("receipt_id"), (F.col("u") - F.col("prev.u")).alias("held_us"))


def live_ids(edges: DataFrame) -> DataFrame:
    """Ids of payments that touch an edge."""
    return edges.select(F.explode(F.array("src_id", "dst_id")).alias("txn_id")).distinct()


def isolated(txn: DataFrame, edges: DataFrame) -> DataFrame:
    return txn.join(live_ids(edges), "txn_id", "left_anti")
