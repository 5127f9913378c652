"""Hand fixtures of FIXTURES.md."""

from datetime import timedelta

import pytest
from pyspark.sql import functions as F

from trailgraph.baselines import layered, motif
from trailgraph.operators import community, flows, leiden_kernel, maxflow_kernel, risk, second_order, temporal
from trailgraph.operators.components import wcc
from trailgraph.plans import metrics

W = timedelta(days=5)
TXN = "txn_id long, ts timestamp, payer long, payee long, amount long, channel string"
N = {c: i for i, c in enumerate("ABCDEGPQRXYZ", 1)}


def table(spark, rows):
    data = [(i, int(1_704_067_200 + d * 86_400), N[a], N[b], m) for i, d, a, b, m in rows]
    return spark.createDataFrame(data, "txn_id long, s long, payer long, payee long, amount long").select("txn_id", F.timestamp_seconds("s").alias("ts"), "payer", "payee", "amount", F.lit("x").alias("channel"))


F1 = [(1, 1, "A", "B", 100), (2, 2, "B", "C", 60), (3, 2, "B", "D", 40), (4, 4, "C", "E", 55), (5, 4, "D", "E", 35), (6, 10, "A", "B", 80), (7, 11, "B", "C", 80), (8, 16, "C", "E", 70), (9, 3, "E", "A", 10), (10, 1.5, "G", "B", 5)]


def ids(edges):
    return {(r.src_id, r.dst_id) for r in edges.select("src_id", "dst_id").collect()}


@pytest.mark.parametrize("method", ["interval", "bucketed", "daily"])
def test_edges_of_f1(spark, method):
    assert ids(temporal.build(table(spark, F1), W, method)) == {(1, 2), (1, 3), (2, 4), (3, 5), (6, 7), (10, 2), (10, 3)}


def test_isolated_and_as_of(spark):
    t = table(spark, F1)
    assert {r.txn_id for r in temporal.isolated(t, temporal.build(t, W)).collect()} == {8, 9}
    held = {r.txn_id: r.receipt_id for r in temporal.latest_receipt(t).collect()}
    assert held[2] == 10 and held[4] == 2 and held[1] is None and held[6] == 9


def test_weights_of_f1(spark):
    e = temporal.build(table(spark, F1), W)
    w = {(r.a, r.b, r.c): (r.n, r.p_fwd, r.p_bwd, r.w) for r in second_order.weights(second_order.pair_graph(e)).collect()}
    k = lambda s: tuple(N[x] for x in s)
    assert w[k("ABC")] == (2, 2 / 3, 2 / 3, 2 / 3)
    assert w[k("ABD")] == (1, 1 / 3, 1 / 2, 1 / 2)
    assert w[k("GBC")] == (1, 1 / 2, 1 / 3, 1 / 2)
    assert w[k("BCE")] == (1, 1, 1, 1)
    assert len(w) == 6


@pytest.mark.parametrize("theta, parts", [(0.6, {(1, 2, 4), (3, 5), (6, 7)}), (0.5, {(1, 2, 3, 4, 5, 10), (6, 7)})])
def test_components_of_f1(spark, theta, parts):
    e = second_order.weigh_and_prune(temporal.build(table(spark, F1), W), theta)
    got: dict = {}
    for r in wcc(e, "src_id", "dst_id").collect():
        got.setdefault(r.component, []).append(r.node)
    assert {tuple(sorted(v)) for v in got.values()} == parts


def test_flow_of_f1(spark):
    t = table(spark, F1)
    e = second_order.weigh_and_prune(temporal.build(t, W), 0.5)
    m = wcc(e, "src_id", "dst_id").select(F.col("node").alias("txn_id"), F.col("component").alias("comm_id"))
    p = flows.payments(m, t)
    s = {r.comm_id: r for r in flows.summarize(p, flows.roles(p)).collect()}
    assert (s[1].dispensed, s[1].sunk, round(s[1].sunk_pct, 4), s[1].n_dispense, s[1].n_sink) == (105, 90, 85.7143, 2, 1)
    assert s[6].sunk_pct == 100
    assert {r.comm_id: r.max_flow for r in risk.temporal_max_flow(p, e).collect()} == {1: 90, 6: 80}
    assert {r.comm_id: r.diameter for r in flows.diameters(p).collect()} == {1: 3, 6: 2}


def test_motifs_of_f1(spark):
    e = temporal.build(table(spark, F1), W)
    g = {r.hops: (r.n_paths, r.n_flows) for r in motif.growth(e, (2, 3, 4)).collect()}
    assert g == {2: (7, 5), 3: (4, 2), 4: (0, 0)}
    assert motif.paths(e, 3).count() == 4


def test_cycles_of_f4(spark):
    t = table(spark, [(41, 3, "X", "Y", 9), (42, 2, "Y", "Z", 9), (43, 1, "Z", "X", 9), (44, 1, "P", "Q", 9), (45, 2, "Q", "R", 9), (46, 3, "R", "P", 9)])
    e = temporal.build(t, W)
    assert ids(e) == {(43, 41), (44, 45), (45, 46)}
    p = t.where("txn_id >= 44").select(F.lit(44).cast("long").alias("comm_id"), "txn_id", F.unix_micros("ts").alias("us"), "payer", "payee", "amount", "channel")
    acct = spark.createDataFrame([(N[x], "HOUSEHOLD") for x in "PQR"], "acct long, segment string")
    f = risk.flag(p, e, acct, threshold=0).first()
    assert not f.c1 and f.sunk_pct is None and not f.suspicious
    assert risk.temporal_max_flow(p, e).first().max_flow == 0
    ends = {(r.acct, r.role) for r in flows.roles(p, role_mode="txn", edges=e).collect()}
    assert (N["P"], "dispense") in ends and (N["P"], "sink") in ends


TRI = ([1, 2, 1, 4, 5, 4, 3], [2, 3, 3, 5, 6, 6, 4])


@pytest.mark.parametrize("bridge, quality", [(0.1, 0.48374093), (1.0, 0.36734694)])
def test_two_triangles(bridge, quality):
    w = [1.0] * 6 + [bridge]
    lab = leiden_kernel.run(*TRI, w)
    assert {tuple(sorted(k for k in lab if lab[k] == c)) for c in lab.values()} == {(1, 2, 3), (4, 5, 6)}
    assert abs(leiden_kernel.modularity(*TRI, w, lab) - quality) < 1e-8


def test_cap_and_weights():
    lab = leiden_kernel.run(*TRI, [1.0] * 6 + [0.1], max_comm_size=2)
    assert max(sum(v == c for v in lab.values()) for c in lab.values()) <= 2
    path = ([1, 2, 3, 4, 5], [2, 3, 4, 5, 6])
    part = lambda w: {tuple(sorted(k for k in lab if lab[k] == c)) for lab in [leiden_kernel.run(*path, w)] for c in lab.values()}
    assert part([1, 0.5, 1, 0.5, 1]) == {(1, 2), (3, 4), (5, 6)}
    assert part([1.0] * 5) == {(1, 2, 3), (4, 5, 6)}


def _partitions(xs):
    if not xs:
        yield []
        return
    for p in _partitions(xs[1:]):
        yield [[xs[0]], *p]
        for i in range(len(p)):
            yield [*p[:i], [xs[0], *p[i]], *p[i + 1 :]]


@pytest.mark.parametrize("seed", range(6))
def test_leiden_is_near_the_best_partition(seed):
    import random

    r = random.Random(seed)
    src, dst = zip(*[tuple(r.sample(range(7), 2)) for _ in range(12)])
    w = [r.choice([0.25, 0.5, 1.0]) for _ in src]
    best = max(leiden_kernel.modularity(src, dst, w, {x: i for i, b in enumerate(p) for x in b}) for p in _partitions(sorted({*src, *dst})))
    got = leiden_kernel.modularity(src, dst, w, leiden_kernel.run(list(src), list(dst), w))
    assert best - 0.06 <= got <= best + 1e-12


@pytest.mark.parametrize("seed", range(8))
def test_max_flow_equals_min_cut(seed):
    import itertools
    import random

    r = random.Random(seed)
    txns = [(i, r.randrange(8), r.randrange(4), 4 + r.randrange(3) if r.random() < 0.4 else r.randrange(4), r.randrange(1, 9)) for i in range(8)]
    txns = [t for t in txns if t[2] != t[3]]
    edges = [(s[0], d[0]) for s in txns for d in txns if s[3] == d[2] and s[1] < d[1] < s[1] + 4]
    first, last = maxflow_kernel.roles(txns)
    best = None
    for k in range(len(txns) + 1):
        for cut in itertools.combinations([t[0] for t in txns], k):
            live = {t[0]: t for t in txns if t[0] not in cut}
            seen = [i for i, t in live.items() if t[2] in first]
            todo = set(seen)
            while seen:
                x = seen.pop()
                for s, d in edges:
                    if s == x and d in live and d not in todo:
                        todo.add(d)
                        seen.append(d)
            if not any(live[i][3] in last for i in todo):
                cost = sum(t[4] for t in txns if t[0] in cut)
                best = cost if best is None else min(best, cost)
    assert maxflow_kernel.windowed(txns, edges) == best
    assert maxflow_kernel.unbounded(txns) >= best


def test_coverage_and_overlap(spark):
    from trailgraph.queries import fixtures

    assert {r.method: r.coverage_pct for r in metrics.coverage(fixtures.flagged(spark)).collect()} == {"m1": 80.0, "m2": 60.0, "m3": 20.0}
    m = spark.createDataFrame([(1, "A"), (1, "B"), (2, "B"), (2, "C")], "flow int, acct string")
    assert tuple(metrics.overlap(m, "acct").first()) == (3, 1, 1.333333)


def test_bank_subsets(spark):
    got = layered.bank_subsets(spark.range(5).withColumnRenamed("id", "bank")).collect()
    sizes = [r.n_banks for r in got]
    assert len(got) == 31 and [sizes.count(k) for k in range(1, 6)] == [5, 10, 10, 5, 1]
    assert all(sum(r["mask"] >> b & 1 for r in got) == 16 for b in range(5))


def test_too_many_banks_are_refused(spark):
    with pytest.raises(ValueError):
        layered.bank_subsets(spark.range(31).withColumnRenamed("id", "bank"))
    assert layered.bank_subsets(spark.range(0).withColumnRenamed("id", "bank")).count() == 0


def _hand(spark, which=(1, 2, 3, 4)):
    from datetime import timedelta

    from trailgraph.operators import flows, temporal
    from trailgraph.queries import fixtures

    t = fixtures.payments(spark).where(F.col("flow").isin(*which))
    e = temporal.build(t.drop("flow"), timedelta(days=5))
    return flows.payments(t.select("flow", "txn_id"), t.drop("flow"), ("flow",)), e


def test_max_flow_of_the_hand_flows(spark):
    from trailgraph.operators import risk
    from trailgraph.queries import fixtures

    p, e = _hand(spark)
    for got in (risk.temporal_max_flow(p, e, keys=("flow",)), risk.temporal_max_flow_cogrouped(p, e, ("flow",))):
        assert sorted(map(tuple, got.collect())) == fixtures.MAXFLOW_ANSWERS


def test_sweep_and_loss_of_the_case_studies(spark):
    from trailgraph.queries import fixtures

    p, e = _hand(spark, (2, 3))
    assert sorted(map(tuple, layered.sweep(p, e, (3, 4, 5), 80, ("flow",)).collect())) == fixtures.SWEEP_ANSWERS
    assert sorted(map(tuple, layered.split_loss(p, e, (3, 4, 5), 80, ("flow",)).collect())) == fixtures.LOSS_ANSWERS


@pytest.mark.parametrize("seed", range(6))
def test_peeling_against_a_plain_greedy(spark, seed):
    """The account of least score goes, ties to the least account; the densest state seen is kept."""
    import random

    r = random.Random(seed)
    arcs = [(*r.sample(range(8), 2), r.randrange(1, 40)) for _ in range(14)]

    def score(v, live):
        i = sum(m for a, b, m in arcs if b == v and a in live)
        o = sum(m for a, b, m in arcs if a == v and b in live)
        return min(i, o) - 0.8 * abs(i - o)

    live = {v for a, b, _ in arcs for v in (a, b)}
    best, keep = None, None
    while live:
        density = sum(score(v, live) for v in live) / len(live)
        if best is None or density > best + 1e-9:
            best, keep = density, set(live)
        live.remove(min(live, key=lambda v: (round(score(v, live), 9), v)))
    got = layered._peel([(a, b, m) for a, b, m in arcs], 0.8)
    assert {v for v, _ in got} == keep and all(abs(d - best) < 1e-6 for _, d in got)
