"""The eleven queries against SQL or brute force, and the pipeline stage by stage."""

import collections

import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from tests.compare import database, expected, rows
from tests.llm.test_operators import _alike, _contaminated, _fingerprint, _groups
from trailgraph.llm import oracles, queries, quality


@pytest.mark.parametrize("name", sorted(oracles.ALL))
def test_sql(spark, sf, name):
    assert rows(queries.queries()[name](spark, sf)) == expected(database(sf), oracles.ALL[name])


def test_one_query_per_operator():
    numbers = sorted(int(n[2:].split("_")[0]) for n in queries.queries())
    assert numbers == list(range(1, 11))


def test_simhash_query(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").orderBy("doc_id").collect()
    fps = [_fingerprint(r.text) for r in docs]
    want = [(r.doc_id, f"{f:016x}", docs[c].doc_id) for r, f, c in zip(docs, fps, _groups(fps))]
    got = sorted(tuple(r) for r in queries.op5_pigeonhole_simhash(spark, sf).collect())
    assert got == want


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert len(names) == 5 and corpus_pipeline.ORACLE_SQL is None
    now = docs
    for i, (name, stage) in enumerate(corpus_pipeline.STAGES):
        out = stage(spark, now, sf).cache()
        before = {r.doc_id: r.text for r in now.select("doc_id", "text").collect()}
        if i < 4:
            assert out.columns == docs.columns
        after = collections.Counter(r.doc_id for r in out.select("doc_id").collect())
        if i == 0:
            ok = {r.doc_id for r in quality.with_verdict(now, name="q").where("q.kept").collect()}
            assert set(after) == ok
        elif i == 1:
            keys = sorted(before)
            groups = _alike([before[k] for k in keys])
            assert set(after) == {keys[g] for g in groups} and max(after.values()) == 1
        elif i == 2:
            bench = [tuple(r) for r in spark.read.parquet(f"{sf}/benchmark.parquet").select("item_id", "text").collect()]
            assert set(after) == {r[0] for r in _contaminated(list(before.items()), bench) if not r[-1]}
        elif i == 3:
            assert max(after.values()) <= 2 and set(after) <= set(before)
        else:
            assert out.count() == now.count()
            per = {r.shard: (r.n, r.b) for r in out.groupBy("shard").agg(F.sum("n_bytes").alias("n"), F.max("shard_bytes").alias("b")).collect()}
            assert all(n == b <= queries.SHARD_BYTES for n, b in per.values())
        now = out
    assert sorted(map(tuple, corpus_pipeline.run(spark, sf).collect())) == sorted(map(tuple, now.collect()))


def test_stages_on_empty_and_odd_tables(spark, sf, docs):
    from tests.llm.conftest import ODD

    for d in (docs(ODD), docs(ODD).limit(0)):
        for _, stage in corpus_pipeline.STAGES:
            out = stage(spark, d, sf)
            assert out.count() <= 2 * d.count()


def test_sharding_keeps_whole_rows(spark, docs):
    """What leaves the pipeline is the corpus: every row with its text and all other columns, and its shard."""
    from tests.llm.conftest import ODD

    d = docs(ODD, extra=True)
    out = corpus_pipeline.sharding_stage(spark, d, "")
    assert out.columns == [*d.columns, "n_bytes", "shard_", "local_depth", "shard_bytes"]
    assert collections.Counter(map(tuple, out.select(*[f"`{c}`" for c in d.columns]).collect())) == collections.Counter(map(tuple, d.collect()))
    assert all(r.n_bytes == len((r.text or "").encode()) and r["shard_"].startswith("s") for r in out.collect())
