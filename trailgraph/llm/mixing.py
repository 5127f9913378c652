"""Operator 9 [native]: mixing sources to target weights.

Every source gets a target number of words (weights over a total, capped at ``max_epochs`` times its
size, the excess reshared by weight). Its documents are put in the order of hash-random keys; whole
epochs take all of them, and the rest is cut where the running sum of words meets the budget.
The running sum has two levels - key ranges within a source, then rows within a range - so a source
with a third of all rows is spread over many tasks.

Defined cases: a null text has 0 words; null source is a source of its own, last in order; rows that
are repeated count as often as they occur; sources without words get target 0. Empty input: no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from trailgraph.functions.runtime import fresh, materialize, plan_bytes, row_hashes
from trailgraph.llm.sharding import HASH_BITS, hash_bits

WORD = r"[^\x20\x09-\x0D]+"
WEIGHTS = (5, 2, 1)


def word_count(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def targets(sources: DataFrame, share: float = 1.5, max_epochs: float = 2.0, weights: tuple[int, ...] = WEIGHTS) -> DataFrame:
    """sources(source, source_size) -> with ``target``: water filling in closed form.

    Sorted by cap over weight, the first k sources are full and the others get weight times one level;
    k is the first for which that level stays below the next source's ratio.
    """
    order = Window.orderBy(F.col("source").asc_nulls_last())
    w = F.element_at(F.array(*map(F.lit, weights)), (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int"))
    x = sources.withColumn("w", w.cast("double")).withColumn("cap", F.col("source_size") * F.lit(float(max_epochs)))
    upto = Window.orderBy(F.col("cap") / F.col("w"), F.col("source").asc_nulls_last())
    every = Window.partitionBy(F.lit(0))
    x = x.select(
        "*", (F.sum("cap").over(upto) - F.col("cap")).alias("full"), (F.sum("w").over(upto) - F.col("w")).alias("gone"),
        F.sum("w").over(every).alias("all_w"), (F.sum("source_size").over(every) * F.lit(float(share))).alias("total"),
    )
    level = (F.col("total") - F.col("full")) / (F.col("all_w") - F.col("gone"))
    x = x.withColumn("level", level).withColumn("lowest", F.min(F.when(F.col("level") <= F.col("cap") / F.col("w"), F.struct(F.col("cap") / F.col("w"), F.col("level").alias("level")))).over(every)["level"])
    return x.select("source", "source_size", F.coalesce(F.least("cap", F.col("w") * F.col("lowest")), F.col("cap")).alias("target"))


def takes(sized: DataFrame, share: float = 1.5, max_epochs: float = 2.0, weights: tuple[int, ...] = WEIGHTS, seed: int = 9, rows_each: int = 20_000, bytes_hint: int = 0) -> DataFrame:
    """sized(doc_id, source, size) -> doc_id, source, size, source_size, target, taken (words, repeats counted).

    Further columns of ``sized`` are kept at the end and order rows of the same id and size.
    """
    more = [c for c in sized.columns if c not in ("doc_id", "source", "size")]
    ranges = max(64, min(1 << 20, bytes_hint // (rows_each * 500)))
    keyed = sized.withColumn("key", hash_bits(F.concat_ws(":", F.lit(seed), F.col("doc_id").cast("string"))))
    keyed = keyed.withColumn("range", F.shiftright(F.shiftright("key", HASH_BITS - 20) * ranges, 20).cast("int"))
    per_range = keyed.groupBy("source", "range").agg(F.sum("size").alias("s"))
    by_source = Window.partitionBy("source")
    per_range = per_range.select(
        "source", "range", (F.sum("s").over(by_source.orderBy("range")) - F.col("s")).alias("before"), F.sum("s").over(by_source).alias("source_size"),
    )
    goals = targets(per_range.select("source", "source_size").distinct(), share, max_epochs, weights)
    offsets = per_range.join(goals.select(F.col("source").alias("gs"), "target"), F.col("source").eqNullSafe(F.col("gs"))).select(F.col("source").alias("os"), F.col("range").alias("orange"), "before", "source_size", "target")
    inner = Window.partitionBy("source", "range").orderBy("key", "doc_id", "size", *more).rowsBetween(Window.unboundedPreceding, -1)
    run = keyed.withColumn("run", F.coalesce(F.sum("size").over(inner), F.lit(0)))
    x = run.join(offsets, F.col("source").eqNullSafe(F.col("os")) & (F.col("range") == F.col("orange")))
    epochs = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0).cast("long")
    rest = F.floor(F.col("target")).cast("long") - epochs * F.col("source_size")
    cut = F.least(F.col("size"), F.greatest(F.lit(0).cast("long"), rest - F.col("before") - F.col("run")))
    return x.select("doc_id", "source", "size", "source_size", "target", (epochs * F.col("size") + cut).cast("long").alias("taken"), *more)


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **kw) -> DataFrame:
    """The budget of every row of ``docs``: doc_id, source, size, source_size, target, taken."""
    sized = docs.select(F.col(f"`{id_col}`").alias("doc_id"), F.col(f"`{source_col}`").alias("source"), word_count(F.col(f"`{text_col}`")).alias("size"))
    return takes(sized, bytes_hint=plan_bytes(docs), **kw)


def mixed_rows(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", **kw) -> DataFrame:
    """The mix itself, with the columns of ``docs``: a row per epoch that takes it whole or, at the cut, by half or more.

    Whole documents only: the cut is moved to the nearer end of the document it falls in, so a
    source is off its target by half a document at most. Rows are told apart by all their columns, so an id that several
    texts share is taken text by text.
    """
    a, b, n, t = (fresh(docs, x) for x in ("__row", "__other", "__rows", "__times"))
    names = [F.col(f"`{c}`") for c in docs.columns]
    k1, k2 = row_hashes(docs)
    sized = docs.select(F.col(f"`{id_col}`").alias("doc_id"), F.col(f"`{source_col}`").alias("source"), word_count(F.col(f"`{text_col}`")).alias("size"), k1.alias("k1"), k2.alias("k2"))
    plan = takes(sized, bytes_hint=plan_bytes(docs), **kw)
    whole = F.floor(F.try_divide(F.col("taken") * 2 + F.col("size"), F.col("size") * 2))
    times = plan.groupBy(F.col("k1").alias(a), F.col("k2").alias(b)).agg(F.count("*").alias(n), F.sum(whole).cast("int").alias(t)).where(F.col(t) > 0)
    times, _ = materialize(times, "mix-times")
    mine = docs.select(*names, k1.alias(c := fresh(docs, "__k1")), k2.alias(d := fresh(docs, "__k2")))
    joined = mine.join(times.hint("merge"), (F.col(c) == F.col(a)) & (F.col(d) == F.col(b)))
    many = lambda rows: rows.select(*names, F.explode(F.sequence(F.lit(1), F.col(t))).alias(a)).select(*names)
    if times.where(F.col(n) > 1).isEmpty():
        return many(joined)
    once = many(joined.where(F.col(n) == 1))
    return once.unionByName(many(joined.where(F.col(n) > 1).dropDuplicates([a, b])))  # equal rows: one stands for all their times
