"""Operator 1: sharding by extendible hashing.

A row's hash bits are those of md5(id). The directory starts with one bucket (depth 0); a bucket over
the byte limit splits on its next bit, others stay. The whole directory is worked out from one
histogram of bytes per fine prefix, so the data are hashed once and never moved to find it.

Defined cases: null text weighs 0 bytes; null id hashes as the empty string; rows with the same id
share all their bits, so a bucket that is over the limit at the finest depth is cut into overflow
pages by running byte sums; a single row over the limit gets a page of its own; columns may have any names. Empty input: no rows.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from trailgraph.functions.runtime import fresh, materialize, row_hashes

HASH_BITS = 60  # 15 hexadecimal digits of md5, a positive long
PARTS = 64  # parts, at least, of an overflowing key whose page offsets are summed apart


def hash_bits(key: Column) -> Column:
    """60 well-mixed bits, the same in any engine that has md5."""
    return F.conv(F.substring(F.md5(F.coalesce(key.cast("string"), F.lit(""))), 1, 15), 16, 10).cast("long")


def _fine_depth(total: int, limit: int) -> int:
    return min(HASH_BITS, max(8, math.ceil(math.log2(max(1, total / limit))) + 8))


def directory(hist: DataFrame, limit: int, depth: int, above: int = -1) -> DataFrame:
    """hist(prefix at ``depth``, bytes) -> (prefix, local_depth, shard_bytes): the shallowest bucket of each prefix that fits.

    Buckets at depth ``above`` or less are known not to fit.
    """
    levels = hist.select("prefix", "bytes", F.explode(F.sequence(F.lit(above + 1), F.lit(depth))).alias("d"))
    at = F.expr(f"shiftright(prefix, {depth} - d)").alias("bucket")
    sums = levels.groupBy("d", at).agg(F.sum("bytes").alias("shard_bytes"))
    fits = sums.where((F.col("shard_bytes") <= limit) | (F.col("d") == depth))
    return (
        levels.select("prefix", "d", at).join(fits, ["d", "bucket"])
        .groupBy("prefix").agg(F.min(F.struct(F.col("d").alias("local_depth"), "shard_bytes")).alias("x")).select("prefix", "x.*")
    )


def _directories(sizes: DataFrame, limit: int, depth: int) -> list[tuple[int, DataFrame]]:
    """(depth, directory) of sizes(h, n): one for all prefixes, then ones for what is below prefixes that are still too large."""
    out, above, left = [], -1, sizes
    while True:
        hist = left.groupBy(F.shiftright("h", HASH_BITS - depth).alias("prefix")).agg(F.sum("n").alias("bytes"))
        dirs, _ = materialize(directory(hist, limit, depth, above), "directory")
        out.append((depth, dirs))
        over = dirs.where(F.col("shard_bytes") > limit).select(F.col("prefix").alias("p"))
        if depth == HASH_BITS or over.isEmpty():
            return out
        below = left.join(over, F.shiftright("h", HASH_BITS - depth) == F.col("p"), "left_semi")
        spread = below.groupBy(F.shiftright("h", HASH_BITS - depth).alias("p")).agg(F.min("h").alias("lo"), F.max("h").alias("hi")).where("lo < hi")
        if spread.isEmpty():
            return out
        left, above, depth = below, depth, min(HASH_BITS, depth + 8)


def text_bytes(text: Column) -> Column:
    return F.coalesce(F.octet_length(text), F.lit(0)).cast("long")


def assign(docs: DataFrame, limit: int, id_col: str = "doc_id", text_col: str = "text", size: Column | None = None) -> DataFrame:
    """The rows of ``docs`` with a struct column ``shard`` (name, bits, local_depth, page, bytes) added at the end.

    ``bits``: the prefix as a string of 0 and 1; ``name``: bits, and the page where one is needed.
    ``size``: a row's bytes, if not those of its text; so the texts can stay where they are.
    Where ``docs`` has a column ``shard`` itself, the new one gets underscores until its name is free.
    """
    size = text_bytes(F.col(f"`{text_col}`")) if size is None else size
    if limit < 1:
        raise ValueError("limit must be positive")
    h, n, x = (fresh(docs, c) for c in ("__hash", "__bytes", "__dir"))
    rows = docs.withColumns({h: hash_bits(F.col(f"`{id_col}`")), n: size})
    total = docs.agg(F.sum(size)).first()[0] or 0
    levels = _directories(rows.select(F.col(h).alias("h"), F.col(n).alias("n")), limit, _fine_depth(total, limit))
    placed = rows
    for k, (depth, dirs) in enumerate(levels):  # a row's deepest entry holds; those above it are over the limit
        p, y = fresh(docs, f"__prefix{k}"), fresh(docs, f"__dir{k}")
        bits = F.when(F.col("local_depth") == 0, F.lit("")).otherwise(F.substring(F.lpad(F.bin("prefix"), depth, "0"), F.lit(1), F.col("local_depth")))
        d = dirs.select(F.col("prefix").alias(p), F.struct(bits.alias("bits"), "local_depth", "shard_bytes").alias(y))
        placed = placed.join(d, F.shiftright(F.col(h), HASH_BITS - depth) == F.col(p), "left" if k else "inner").drop(p)
        placed = placed.withColumn(x, F.coalesce(F.col(y), F.col(x)) if k else F.col(y)).drop(y)
    out = [F.col(f"`{c}`") for c in docs.columns]
    shard = lambda page, size: F.struct(
        F.concat(F.lit("s"), F.col(x)["bits"], F.when(page > 0, F.concat(F.lit("-"), page.cast("string"))).otherwise(F.lit(""))).alias("name"),
        F.col(x)["bits"].alias("bits"), F.col(x)["local_depth"].alias("local_depth"), page.alias("page"), size.cast("long").alias("bytes"),
    ).alias(fresh(docs, "shard"))
    if levels[-1][1].where(F.col("shard_bytes") > limit).isEmpty():
        return placed.select(*out, shard(F.lit(0).cast("long"), F.col(x)["shard_bytes"]))
    fits = placed.where(F.col(x)["shard_bytes"] <= limit).select(*out, shard(F.lit(0).cast("long"), F.col(x)["shard_bytes"]))
    return fits.unionByName(_paged(placed.where(F.col(x)["shard_bytes"] > limit), docs, limit, max(PARTS, total // limit + 1), x, n, out, shard))


def _paged(rows: DataFrame, docs: DataFrame, limit: int, parts: int, x: str, n: str, out: list, shard) -> DataFrame:
    """Overflow pages: rows of a bucket in the order of their hashes, pages filled by running byte sums.

    A row's part follows from its hash, and ``parts`` grows with the bytes, so a bucket with most of them is about one
    limit a part. Equal rows are counted by the task that wrote them: which of them goes to which page
    makes no difference, so a rerun gives the same shards. A page starts at a multiple of the limit less the largest
    row, so none passes the limit unless one row does.
    """
    key, hashed, part, task = (fresh(rows, c) for c in ("__bucket", "__row", "__part", "__task"))
    rows = rows.withColumns({key: F.col(x)["bits"], hashed: row_hashes(docs)[0], task: F.spark_partition_id()})
    rows, _ = materialize(rows.withColumn(part, F.pmod(F.xxhash64(F.col(hashed)), F.lit(parts))), "pages")
    equal = rows.groupBy(key, part, hashed, task).agg(F.sum(n).alias("s"), F.max(n).alias("most"))
    within = Window.partitionBy(key, part).orderBy(hashed, task)
    equal = equal.select(key, part, hashed, task, (F.sum("s").over(within) - F.col("s")).alias("inside"), "s", "most")
    w = Window.partitionBy(key)
    sums = equal.groupBy(key, part).agg(F.sum("s").alias("s"), F.max("most").alias("most"))
    sums = sums.select(key, part, (F.sum("s").over(w.orderBy(part)) - F.col("s")).alias("before"), F.max("most").over(w).alias("most"))
    starts = equal.drop("s", "most").join(sums, [key, part]).select(key, hashed, task, F.struct((F.col("before") + F.col("inside")).alias("start"), "most").alias(at := fresh(rows, "__at")))
    same = Window.partitionBy(key, hashed, task).orderBy(n)
    joined = rows.withColumn(seq := fresh(rows, "__seq"), F.row_number().over(same) - 1).join(starts, [key, hashed, task])
    step = F.greatest(F.lit(1).cast("long"), F.lit(limit) - F.col(at)["most"] + 1)
    joined = joined.withColumn(g := fresh(rows, "__page"), (F.floor((F.col(at)["start"] + F.col(seq) * F.col(n)) / step) + 1).cast("long"))
    size = joined.groupBy(key, g).agg(F.sum(n).alias(z := fresh(rows, "__size")))
    return joined.join(size, [key, g]).select(*out, shard(F.col(g), F.col(z)))


def write_shards(docs: DataFrame, path: str, limit: int, **kw) -> None:
    """Write every shard as its own folder ``shard=<name>`` under ``path``."""
    placed = assign(docs, limit, **kw)
    name = fresh(docs, "shard_name")
    placed.select(*[F.col(f"`{c}`") for c in docs.columns], F.col(fresh(docs, "shard"))["name"].alias(name)).repartition(name).write.partitionBy(name).parquet(path)
