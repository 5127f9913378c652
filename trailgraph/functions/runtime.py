"""Session helpers shared by every part of the engine: materialised tables, size checks, safe names."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``.

    Where that is unset a session in one process gets a temporary folder; on a cluster this is an error, as executors
    would each write to their own disk.
    """
    where = spark.conf.get("spark.checkpoint.dir", None)
    if not where:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        where = "file://" + tempfile.mkdtemp(prefix="trailgraph-")
        spark.conf.set("spark.checkpoint.dir", where)
    return where.rstrip("/")


def scratch_path(spark: SparkSession, label: str) -> str:
    return f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"


def materialize(df: DataFrame, label: str) -> tuple[DataFrame, str]:
    """Cut the lineage: write ``df`` as Parquet to the shared folder and read it back.

    A lost executor costs nothing that was computed before this point.
    """
    spark, path = df.sparkSession, scratch_path(df.sparkSession, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def remove(spark: SparkSession, path: str) -> None:
    """Delete a scratch table through Hadoop's file system, whatever store it lies in."""
    jvm, conf = spark._jvm, spark._jsc.hadoopConfiguration()
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(conf).delete(target, True)


def let(value: Column, body) -> Column:
    """Evaluate ``value`` once per row and hand it to ``body``.

    A plain Column used inside a lambda would be evaluated again for every element.
    """
    return F.transform(F.array(value), body)[0]


def fresh(df: DataFrame, base: str) -> str:
    """A column name that ``df`` doesn't have, so that user columns can never clash with ours."""
    taken, name = {c.lower() for c in df.columns}, base
    while name.lower() in taken:
        name += "_"
    return name


def row_hashes(df: DataFrame) -> list[Column]:
    """Two independent 64-bit hashes of a whole row: rows that share both are taken as equal. Maps and variants don't take part."""
    plain = [F.col(f"`{c}`") for c, t in df.dtypes if not any(x in t for x in ("map<", "variant"))]
    return [F.xxhash64(F.lit(0), *plain), F.xxhash64(F.lit(1), *plain)]


def plan_bytes(df: DataFrame) -> int:
    """Bytes of ``df``: the optimizer's estimate, which for a scan is that of its files, so nothing is read.

    Where the optimizer doesn't know (it then says exabytes), the texts are added up.
    """
    said = int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    if said < 1 << 50:
        return said
    texts = [F.coalesce(F.octet_length(F.col(f"`{c}`")), F.lit(0)) for c, t in df.dtypes if t in ("string", "binary")]
    each = sum(texts, F.lit(16 * len(df.columns))).cast("long")
    return int(df.agg(F.sum(each)).first()[0] or 0)


def shuffle_width(df: DataFrame, bytes_each: int = 64 << 20, expansion: float = 4.0) -> int:
    """Partitions for a shuffle of ``df``: at least the session's, more where the input is large."""
    conf = int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return min(1_000_000, max(conf, int(plan_bytes(df) * expansion / bytes_each) + 1))
