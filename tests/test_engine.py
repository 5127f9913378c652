"""Invariants, equivalences and edge cases."""

import random
from datetime import date, timedelta

import numpy as np
import pytest
from pyspark.sql import functions as F

from trailgraph.operators import anomaly, community, components, prep, second_order, temporal
from trailgraph.operators.components import wcc
from trailgraph.plans import config, metrics, pipeline
from trailgraph.sources import ledger, store

DAY = timedelta(days=1)


@pytest.fixture(scope="module")
def txn(spark, sf):
    return ledger.load(spark, sf).cache()


@pytest.fixture(scope="module")
def edges(txn):
    return temporal.build(txn, DAY).cache()


def ids(e):
    return sorted((r.src_id, r.dst_id) for r in e.select("src_id", "dst_id").collect())


def test_golden_counts(spark, sf, edges):
    assert edges.count() == 306 and temporal.live_ids(edges).count() == 351
    assert second_order.pair_graph(edges).count() == 293
    assert second_order.weigh_and_prune(edges, 0.5).count() == 293
    assert temporal.build(ledger.load(spark, sf, "trade"), timedelta(days=7)).count() == 3072


def test_methods_agree(txn, edges):
    for e in (temporal.build(txn, DAY, "interval"), temporal.daily(txn, DAY), temporal.build(txn, DAY, salts=3), temporal.build(txn, DAY, bucket=timedelta(hours=5))):
        assert ids(e) == ids(edges)


def test_brute_force(spark):
    r = random.Random(3)
    rows = [(i, r.randrange(40), r.randrange(6), r.randrange(6)) for i in range(120)]
    t = spark.createDataFrame([(i, s, a, b, 1) for i, s, a, b in rows if a != b], "txn_id long, s long, payer long, payee long, amount long").select("txn_id", F.timestamp_micros("s").alias("ts"), "payer", "payee", "amount", F.lit("c").alias("channel"))
    for w in (1, 2, 7, 100):
        want = sorted((x[0], y[0]) for x in rows for y in rows if x[2] != x[3] and y[2] != y[3] and x[3] == y[2] and x[1] < y[1] < x[1] + w)
        for method in ("interval", "bucketed"):
            assert ids(temporal.build(t, timedelta(microseconds=w), method)) == want


def test_append_in_any_order(txn, edges):
    cut = F.pmod(F.xxhash64("txn_id"), F.lit(3))
    stored, out = txn.limit(0), None
    for b in (1, 0, 1, 2):
        new = txn.where(cut == b)
        got = temporal.append(stored, new, DAY)
        out = got if out is None else out.unionByName(got)
        stored = stored.unionByName(new.join(stored.select("txn_id"), "txn_id", "left_anti"))
    assert ids(out) == ids(edges)


def test_time_rises_and_shares_add_up(edges):
    assert edges.where("t_dst <= t_src").count() == 0
    w = second_order.weights(second_order.pair_graph(edges)).cache()
    assert w.where("w <= 0 or w > 1 or w < p_fwd or w < p_bwd").count() == 0
    assert w.groupBy("a", "b").agg(F.sum("p_fwd").alias("s")).where("abs(s - 1) > 1e-9").count() == 0
    assert w.groupBy("b", "c").agg(F.sum("p_bwd").alias("s")).where("abs(s - 1) > 1e-9").count() == 0
    assert [second_order.weigh_and_prune(edges, t).count() for t in (0.0, 0.3, 0.6, 1.0)] == sorted([second_order.weigh_and_prune(edges, t).count() for t in (0.0, 0.3, 0.6, 1.0)], reverse=True)
    a = {tuple(r) for r in second_order.weights(second_order.pair_graph(edges), how="join").select(w.columns).collect()}
    assert a == {tuple(r) for r in w.collect()}


def test_two_pass_gives_the_same(spark, txn, edges, tmp_path):
    e = pipeline.wedges_two_pass(txn, config.E1d, str(tmp_path / "pairs"))
    assert ids(e) == ids(second_order.weigh_and_prune(edges, 0.5))


def test_store_time_travel_prunes(spark, edges, tmp_path):
    path = str(tmp_path / "edges")
    store.write_edges(edges, path)
    store.write_edges(edges, path)  # the same batch again
    assert store.read_edges(spark, path).count() == edges.count()
    got = store.read_edges(spark, path, as_of=date(2024, 1, 10))
    assert got.count() == edges.where("dst_date <= '2024-01-10'").count()
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "PartitionFilters: [" in plan and "dst_date" in plan.split("PartitionFilters")[1]


def test_scan_reads_only_what_it_needs(spark, sf):
    other = sf.replace("sf0.001", "sf0.01")  # Spark would answer from the cached ledger of the fixture
    plan = ledger.load(spark, other).select("txn_id", "payer")._jdf.queryExecution().executedPlan().toString()
    scan = plan[plan.index("FileScan"):]
    assert "event_type" not in scan[scan.index("ReadSchema"):]
    assert "IsNotNull(user_id)" in scan[scan.index("PushedFilters"):]


def test_theta_join_compares_only_blocks_that_can_meet(spark):
    s = spark.range(400).selectExpr("id as src_id", "id % 40 as b", "id * 7 as us")
    t = spark.range(400).selectExpr("id as dst_id", "id % 36 as b2", "id * 7 + 3 as ud")
    got = temporal.theta_join(s, t, 100, 4)
    plain = s.join(t, (F.abs(F.col("b") - F.col("b2")) < 1) & (F.col("us") < F.col("ud")) & (F.col("ud") < F.col("us") + 100))
    ids = lambda x: sorted(map(tuple, x.select("src_id", "dst_id").collect()))
    assert ids(got) == ids(plain) and len(ids(plain)) > 100
    names = got._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastNestedLoopJoin" in names and names.count("HashAggregate") >= 4  # over blocks, not over rows


def test_recurring_accounts_count_pairs_between_classes(spark):
    from pyspark.sql import types as T

    rows = [(w * 1000 + i, w, 7) for w in (1, 2) for i in range(120)]
    m = spark.createDataFrame(rows, "txn_id long, window_start long, comm_id long")
    ledger = T.StructType([T.StructField("txn_id", T.LongType()), T.StructField("payer", T.LongType()), T.StructField("payee", T.LongType())])
    t = spark.createDataFrame([(w * 1000 + i, i, 500 + (i if w == 1 else 0)) for w in (1, 2) for i in range(120)], ledger)
    spark.catalog.clearCache()
    pairs = community.recurring_accounts(m, t, 2, max_pairs_flow=9)
    got = sorted(map(tuple, pairs.collect()))
    both = [*range(120), 500]  # in both windows; the other payees are in one
    assert got == sorted((a, b, 2) for i, a in enumerate(both) for b in both[i + 1 :])
    scan = pairs._jdf.queryExecution().optimizedPlan().toString()
    assert "account-classes" in scan or pairs._jdf.queryExecution().executedPlan().toString().count("account-classes") > 0


def test_communities_do_not_depend_on_partitions(spark, edges):
    w = second_order.weigh_and_prune(edges, 0.5)
    a = {tuple(r) for r in community.detect(w).select("comm_id", "txn_id").collect()}
    b = {tuple(r) for r in community.detect(w.repartition(13)).select("comm_id", "txn_id").collect()}
    assert a == b and len({x[1] for x in a}) == len(a) == temporal.live_ids(w).count()


def test_distributed_engine(spark):
    rows = [(1, 2, 1.0), (2, 3, 1.0), (1, 3, 1.0), (4, 5, 1.0), (5, 6, 1.0), (4, 6, 1.0), (3, 4, 0.1)]
    e = spark.createDataFrame(rows, "src_id long, dst_id long, w double")
    got: dict = {}
    for r in community.detect(e, engine="distributed").collect():
        got.setdefault(r.comm_id, []).append(r.txn_id)
    assert {tuple(sorted(v)) for v in got.values()} == {(1, 2, 3), (4, 5, 6)}
    for kw in (dict(quality="cpm", resolution=0.3), dict(directed=False)):
        groups = lambda engine: sorted(tuple(sorted(r.t)) for r in community.detect(e, engine=engine, **kw).groupBy("comm_id").agg(F.collect_list("txn_id").alias("t")).collect())  # noqa: B023, E731
        assert groups("distributed") == groups("kernel") == [(1, 2, 3), (4, 5, 6)]
    capped = community.detect(e, engine="distributed", max_comm_size=2).groupBy("comm_id").count().agg(F.max("count")).first()[0]
    assert capped <= 2


def test_distributed_engine_ends_in_few_jobs_with_the_kernels_quality(spark, monkeypatch):
    monkeypatch.setattr(community, "PACK", 300)  # packs far smaller than the component
    rows = [(6 * c + i, 6 * c + j, 1.0) for c in range(120) for i in range(6) for j in range(i + 1, 6)]
    rows += [(6 * c, (6 * c + 6 * k) % 720, 0.2) for c in range(120) for k in (1, 7, 31)]
    e = spark.createDataFrame(rows, "src_id long, dst_id long, w double").cache()
    spark.sparkContext.setJobGroup("levels", "levels")
    large = community.detect(e, task_limit=600).cache()
    assert large.count() == 720 == large.select("txn_id").distinct().count()
    spark.sparkContext.setJobGroup("", "")
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("levels")) < 300
    worth = lambda m: community.modularity(e, m).first()[0]
    assert worth(large) > 0.99 * worth(community.detect(e, engine="kernel"))


def test_components_by_forests_equal_the_rounds(spark):
    rng = random.Random(5)
    rows = [(g, rng.randrange(60) - 20, rng.randrange(60) - 20) for g in (-1, 3, 7) for _ in range(45)] + [(3, None, 4), (3, 5, None), (7, 900, 900)]
    e = spark.createDataFrame(rows, "u long, a long, b long").repartition(5).cache()
    want = {(g, r.node, r.component) for g in (-1, 3, 7) for r in wcc(e.where(F.col("u") == g), "a", "b").collect()}
    for local in (1000, 0):  # in one task, and by rounds
        assert sorted(map(tuple, components.wcc_by(e, "u", "a", "b", local=local).collect())) == sorted(want)
    got = [np.array(x, np.int64) for x in zip(*rows[:45])]
    assert {tuple(map(int, x)) for x in zip(*components.forest(*got))} == {x for x in want if x[0] == -1 and x[1] != x[2]}


def test_a_long_chain_is_labelled_in_few_jobs(spark):
    e = spark.range(3000).select(F.col("id").alias("src_id"), (F.col("id") + 1).alias("dst_id"), F.lit(1.0).alias("w"))
    spark.sparkContext.setJobGroup("chain", "chain")
    assert community.detect(e).count() == 3001
    spark.sparkContext.setJobGroup("", "")
    assert len(spark.sparkContext.statusTracker().getJobIdsForGroup("chain")) < 60


def test_visiting_orders_in_tasks_of_their_own_give_the_kernels_communities(spark, monkeypatch):
    rng = random.Random(9)
    rows = [(100 * c + rng.randrange(40), 100 * c + rng.randrange(40), rng.random() + 0.1) for c in range(3) for _ in range(90)]
    e = spark.createDataFrame(rows, "src_id long, dst_id long, w double").coalesce(1).cache()
    found = lambda: sorted(map(tuple, community.detect(e, max_comm_size=12).select("comm_id", "txn_id").collect()))
    whole = found()
    monkeypatch.setattr(community, "_APART", 5)
    assert found() == whole


def test_window_mass_counts_for_every_component(spark):
    tri = [(1, 2), (2, 3), (1, 3), (4, 5), (5, 6), (4, 6), (3, 4)]
    rows = [(a + k, b + k, 1.0) for k in (0, 10) for a, b in tri]
    e = spark.createDataFrame(rows, "src_id long, dst_id long, w double")
    for scope, n in (("window", 4), ("component", 4)):
        assert community.detect(e, m_scope=scope).select("comm_id").distinct().count() == n


def test_hubs(spark, txn):
    top = prep.hubs(txn, k=1).first()
    lean = prep.drop_hubs(txn, k=1)
    assert lean.where((F.col("payer") == top.acct) | (F.col("payee") == top.acct)).count() == 0
    assert prep.hubs(txn).count() == 1
    with pytest.raises(ValueError):
        prep.hubs(txn, k=prep.MAX_HUBS + 1)


def test_broken_input(spark):
    t0 = "2024-01-01 00:00:00"
    rows = [(1, t0, 1, 2, 5), (1, t0, 1, 3, 5), (2, t0, None, 2, 5), (3, t0, 1, 2, 0), (4, t0, 2, 2, 5), (5, None, 1, 2, 5)]
    t = spark.createDataFrame(rows, "txn_id long, t string, payer long, payee long, amount long").select("txn_id", F.col("t").cast("timestamp").alias("ts"), "payer", "payee", "amount", F.lit(None).cast("string").alias("channel"))
    assert [r.txn_id for r in ledger.clean(t).collect()] == [1, 1]
    with pytest.raises(ValueError):
        ledger.validate(ledger.clean(t))
    empty = t.limit(0)
    assert temporal.build(empty, DAY).count() == 0 and temporal.daily(empty, DAY).count() == 0
    assert community.detect(second_order.weigh_and_prune(temporal.build(empty, DAY), 0.5)).count() == 0
    assert temporal.append(empty, empty, DAY).count() == 0


@pytest.mark.parametrize("fmt", ["csv", "json", "orc", "parquet"])
def test_formats_round_trip(spark, tmp_path, fmt):
    df = spark.createDataFrame([(1, 1704067200, 7, 8, 12.5), (2, 1704067260, 8, 9, 0.0001)], "i long, t long, f long, g long, m double")
    path = str(tmp_path / fmt)
    (df.write.option("header", "true") if fmt == "csv" else df.write).format(fmt).save(path)
    got = ledger.read(spark, fmt, path, "i long, t long, f long, g long, m double", {"txn_id": "i", "ts": "t", "payer": "f", "payee": "g", "amount": "m"})
    assert {(r.txn_id, r.ts.isoformat(), r.amount) for r in got.collect()} == {(1, "2024-01-01T00:00:00", 125000), (2, "2024-01-01T00:01:00", 1)}


def test_synthetic_ledger(spark):
    a = ledger.synth(spark, 500)
    assert sorted(map(tuple, a.collect())) == sorted(map(tuple, a.repartition(7).collect()))
    assert prep.hubs(a, k=1).first().acct == 9_999_999
    t = prep.drop_hubs(ledger.clean(a), k=1)
    m = community.detect(second_order.weigh_and_prune(temporal.build(t, DAY), 0.5))
    chain = t.where("channel = 'chain'").join(m, "txn_id")
    assert chain.count() == 4 and chain.select("comm_id").distinct().count() == 1


def test_scores(spark):
    v = spark.createDataFrame([(i, [float(i % 3), 1.0]) for i in range(30)] + [(100, [50.0, 1.0])], "id long, vector array<double>")
    assert anomaly.zscore(v, "id").orderBy(F.desc("score")).first().id == 100
    assert anomaly.mahalanobis_diag(v, "id").orderBy(F.desc("score")).first().id == 100
    near = {r.id: r.score for r in anomaly.knn_distance(v, "id", k=2, every=100).collect()}
    assert near[0] == 0.0 and near[100] == 48.0
    x = spark.createDataFrame([(i, float(i)) for i in range(10)] + [(99, 100.0)], "id long, x double")
    assert [r.id for r in anomaly.iqr(x, "id", "x").where("outlier").collect()] == [99]


def test_recurring_accounts_of_large_flows(spark):
    t = spark.createDataFrame([(w * 100 + i, f"a{i}", f"a{i + 1}") for w in range(2) for i in range(29)], "txn_id long, payer string, payee string")
    m = t.selectExpr("CAST(txn_id DIV 100 AS BIGINT) AS window_start", "1L AS comm_id", "txn_id")
    got = sorted(map(tuple, community.recurring_accounts(m, t, 2, max_pairs_flow=7).collect()))
    names = sorted(f"a{i}" for i in range(30))
    assert got == [(a, b, 2) for i, a in enumerate(names) for b in names[i + 1 :]]


def test_recurring_and_linearity(spark):
    m = spark.createDataFrame([(w, 1, w * 10 + i) for w in (1, 2) for i in (1, 2)], "window_start long, comm_id long, txn_id long")
    t = spark.createDataFrame([(w * 10 + i, 5, 5 + i) for w in (1, 2) for i in (1, 2)], "txn_id long, payer long, payee long")
    pairs = community.recurring_accounts(m, t, 2)
    assert {(r.acct, r.acct2) for r in pairs.collect()} == {(5, 6), (5, 7), (6, 7)}
    assert community.recurring_communities(pairs).select("comm_id").distinct().count() == 1
    rows = spark.createDataFrame([("s", 10, 1.0), ("s", 20, 2.0), ("s", 30, 3.0)], "stage string, n_txn long, seconds double")
    r = metrics.linearity(rows).first()
    assert abs(r.slope - 0.1) < 1e-12 and abs(r.r2 - 1) < 1e-12


def test_udf_surface(spark):
    from trailgraph.functions import columns

    df = spark.createDataFrame([("1", 12345, 3), ("1", 777, 5)], "k string, a long, g long")
    assert df.groupBy("k").agg(columns.median_hold("g").alias("m")).first().m == 4.0
    assert df.select(columns.mask_account(F.col("a").cast("string")).alias("x")).first().x == "***45"
    spark.udtf.register("reach", columns.Reach)
    assert [tuple(r) for r in spark.sql("SELECT * FROM reach(1, '1:2,3;3:4', 2) ORDER BY depth, node").collect()] == [(1, 2), (1, 3), (2, 4)]


def test_pipeline_report(spark, sf):
    out = pipeline.run(spark, sf, config.E6h)
    assert {r.stage for r in out["stages"].collect()} == {"ledger", "edges and weights", "communities", "flagging"}
    assert out["flagged"].where("suspicious and not (c1 and c2 and c3)").count() == 0


def test_method_comparison_plans(spark, sf, monkeypatch):
    """No table that the query writes runs a search for communities more than once."""
    from trailgraph.queries import trail

    searches, write = [], trail.materialize

    def watched(df, label):
        searches.append(str(df._jdf.queryExecution().optimizedPlan()).count("FlatMapGroupsInPandas"))
        return write(df, label)

    monkeypatch.setattr(trail, "materialize", watched)
    trail.clear_memo()
    out = trail.queries()["method_comparison"](spark, sf)
    assert {r.method for r in out.collect()} <= {"trail", "trail-unweighted", "motif-join+"}
    assert max(searches) <= 2 and "FlatMapGroupsInPandas" not in str(out._jdf.queryExecution().optimizedPlan())
