"""Ledgers as TXN(txn_id, ts, payer, payee, amount, channel) and the account dimension.

Money is BIGINT in 1e-4 units; ``ts`` is an instant (TIMESTAMP). Wall-clock columns without a zone are read as UTC
whatever the session's zone is.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

TXN = T.StructType(
    [
        T.StructField("txn_id", T.LongType()), T.StructField("ts", T.TimestampType()), T.StructField("payer", T.LongType()),
        T.StructField("payee", T.LongType()), T.StructField("amount", T.LongType()), T.StructField("channel", T.StringType()),
    ]
)
DAY = 86_400_000_000


def instant(c: Column) -> Column:
    """A zone-less wall clock, taken as UTC."""
    return F.convert_timezone(F.lit("UTC"), F.current_timezone(), c).cast("timestamp")


def micros(ts: str | Column = "ts") -> Column:
    return F.unix_micros(F.col(ts) if isinstance(ts, str) else ts)


def day(us: Column) -> Column:
    """UTC date of epoch microseconds."""
    return F.date_add(F.lit("1970-01-01").cast("date"), F.floor(us / F.lit(DAY)).cast("int"))


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ledger E without checks: fine timestamps, few forwarding accounts."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    return from_events(e)


def from_events(e: DataFrame) -> DataFrame:
    ts = F.col("ts") if dict(e.dtypes)["ts"] == "timestamp" else instant(F.col("ts"))
    return e.select(
        F.col("event_id").alias("txn_id"), ts.alias("ts"), (F.col("user_id") * 2).alias("payer"),
        (F.get_json_object("props", "$.k").cast("long") * 2).alias("payee"),
        (F.round(F.col("value") * 100).cast("long") * 100).alias("amount"), F.col("event_type").alias("channel"),
    )


def trade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ledger R: purchases at the order date and, for returned lines, refunds at the ship date."""
    o = spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_orderkey", "o_custkey", "o_orderdate")
    l = spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    rn = F.row_number().over(Window.partitionBy("l_orderkey").orderBy(*l.columns))
    amount = F.round(F.col("l_extendedprice") * 100).cast("long") * (F.lit(100).cast("long") - F.round(F.col("l_discount") * 100).cast("long"))
    lines = l.withColumn("rn", rn).select("l_orderkey", "l_suppkey", "l_returnflag", "l_shipdate", amount.alias("amount"), ((F.col("l_orderkey") * 100 + F.col("rn")) * 2).alias("id"))
    j = lines.join(o, lines["l_orderkey"] == o["o_orderkey"])
    buyer, seller = F.col("o_custkey") * 2, F.col("l_suppkey") * 2 + 1
    none = F.lit(None).cast("string")
    both = F.array(
        F.struct(F.col("id").alias("txn_id"), instant(F.col("o_orderdate")).alias("ts"), buyer.alias("payer"), seller.alias("payee"), F.lit("purchase").alias("channel")),
        F.when(F.col("l_returnflag") == "R", F.struct((F.col("id") + 1).alias("txn_id"), instant(F.col("l_shipdate")).alias("ts"), seller.alias("payer"), buyer.alias("payee"), F.lit("refund").alias("channel"))),
    )
    rows = j.select("amount", F.explode(both).alias("x")).where("x is not null")
    return rows.select("x.txn_id", "x.ts", "x.payer", "x.payee", "amount", "x.channel")


def clean(txn: DataFrame, drop_self: bool = True) -> DataFrame:
    """Rows that a ledger may hold: keys and time there, a positive amount, payer other than payee."""
    ok = F.col("txn_id").isNotNull() & F.col("ts").isNotNull() & F.col("payer").isNotNull() & F.col("payee").isNotNull() & (F.col("amount") > 0)
    return txn.where(ok & (F.col("payer") != F.col("payee")) if drop_self else ok)


def load(spark: SparkSession, sf_dir: str, kind: str = "events", drop_self: bool = True) -> DataFrame:
    return clean({"events": events, "trade": trade}[kind](spark, sf_dir), drop_self)


def duplicate_ids(txn: DataFrame) -> DataFrame:
    """txn_ids that occur twice or more; a valid ledger has none."""
    return txn.groupBy("txn_id").agg(F.count("*").alias("n")).where("n > 1")


def validate(txn: DataFrame) -> DataFrame:
    """The ledger itself, or ValueError if an id is not unique."""
    bad = duplicate_ids(txn).limit(1).collect()
    if bad:
        raise ValueError(f"txn_id {bad[0]['txn_id']} occurs {bad[0]['n']} times")
    return txn


def accounts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """ACCT(acct, kind, segment, nation, bank): customers and suppliers; the bank is the region."""
    n = spark.read.parquet(f"{sf_dir}/nation.parquet").select("n_nationkey", "n_regionkey")
    c = spark.read.parquet(f"{sf_dir}/customer.parquet").select((F.col("c_custkey") * 2).alias("acct"), F.lit("customer").alias("kind"), F.col("c_mktsegment").alias("segment"), F.col("c_nationkey").alias("nation"))
    s = spark.read.parquet(f"{sf_dir}/supplier.parquet").select((F.col("s_suppkey") * 2 + 1).alias("acct"), F.lit("supplier").alias("kind"), F.lit("SUPPLIER").alias("segment"), F.col("s_nationkey").alias("nation"))
    both = c.unionByName(s)
    return both.join(F.broadcast(n), both["nation"] == n["n_nationkey"]).select("acct", "kind", "segment", F.col("nation").cast("int"), F.col("n_regionkey").cast("int").alias("bank"))


_UNITS = {"seconds": lambda c: F.timestamp_seconds(c), "millis": lambda c: F.timestamp_millis(c), "micros": lambda c: F.timestamp_micros(c), "iso": lambda c: instant(F.to_timestamp_ntz(c)), "ntz": instant, "timestamp": lambda c: c}


def from_columns(df: DataFrame, mapping: dict[str, str], time_unit: str = "seconds", scale: int = 10_000, drop_self: bool = True) -> DataFrame:
    """Any table as TXN. ``mapping``: our name -> its column; amounts are multiplied by ``scale``."""
    at = {k: F.col(f"`{v}`") for k, v in mapping.items()}
    return clean(
        df.select(
            at["txn_id"].cast("long").alias("txn_id"), _UNITS[time_unit](at["ts"]).alias("ts"), at["payer"].cast("long").alias("payer"), at["payee"].cast("long").alias("payee"),
            F.round(at["amount"].cast("decimal(28,6)") * scale).cast("long").alias("amount"), at.get("channel", F.lit(None)).cast("string").alias("channel"),
        ),
        drop_self,
    )


def read(spark: SparkSession, fmt: str, path: str, schema: str, mapping: dict[str, str], time_unit: str = "seconds", **kw) -> DataFrame:
    """A CSV, JSON, ORC or Parquet ledger with an explicit schema."""
    options = {"header": "true"} if fmt == "csv" else {}
    return from_columns(spark.read.schema(schema).options(**options).format(fmt).load(path), mapping, time_unit, **kw)


def synth(spark: SparkSession, n: int, seed: int = 7, n_accounts: int = 1000, days: int = 30, patterns: tuple = ("chain", "smurf", "ring", "mixed", "hub")) -> DataFrame:
    """N hash-random payments and planted flows; the same rows under any partitioning.

    Planted accounts are 10,000,000 and up (100 per pattern), their payments an hour apart.
    """
    u = lambda k: F.pmod(F.xxhash64(F.lit(seed), F.lit(k), F.col("id")), F.lit(1 << 40))
    noise = spark.range(n).select(
        F.col("id").alias("txn_id"), F.timestamp_micros(F.lit(1_704_067_200_000_000) + u(1) % F.lit(days * DAY)).alias("ts"),
        (u(2) % n_accounts).alias("payer"), (u(3) % n_accounts).alias("payee"), (u(4) % F.lit(5_000_000) + 10_000).alias("amount"), F.lit("noise").alias("channel"),
    )
    rows, base = [], 10_000_000
    plan = {
        "chain": [(0, 1, 2, 900), (1, 2, 3, 880), (2, 3, 4, 860), (3, 4, 5, 850)],
        "smurf": [(0, 1, 10 + i, 200) for i in range(5)] + [(1, 10 + i, 9, 195) for i in range(5)],
        "ring": [(0, 1, 2, 500), (1, 2, 3, 490), (2, 3, 1, 480)],
        "mixed": [(0, 1, 2, 300), (1, 2, 9, 100), (1, 2, 3, 30), (2, 3, 9, 30), (1, 2, 4, 90), (2, 4, 5, 90), (3, 5, 9, 90), (1, 2, 6, 30), (2, 6, 9, 30)],
    }
    for k, name in enumerate(patterns):
        for i, (hour, a, b, money) in enumerate(plan.get(name, [])):
            rows.append((1_000_000_000 + 1000 * k + i, 1_704_067_200 + 86_400 * (k + 1) + 3600 * hour, base + 100 * k + a, base + 100 * k + b, money * 10_000, name))
    planted = spark.createDataFrame(rows, "txn_id long, s long, payer long, payee long, amount long, channel string").select("txn_id", F.timestamp_seconds("s").alias("ts"), "payer", "payee", "amount", "channel") if rows else noise.limit(0)
    out = noise.unionByName(planted)
    if "hub" in patterns:
        hub = spark.range(max(1, n // 10)).select(
            (F.col("id") + 2_000_000_000).alias("txn_id"), F.timestamp_micros(F.lit(1_704_067_200_000_000) + u(5) % F.lit(days * DAY)).alias("ts"),
            F.lit(9_999_999).cast("long").alias("payer"), (u(6) % n_accounts).alias("payee"), (u(7) % F.lit(5_000_000) + 10_000).alias("amount"), F.lit("hub").alias("channel"),
        )
        out = out.unionByName(hub)
    return out
