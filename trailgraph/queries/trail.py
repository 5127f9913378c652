"""Queries of the trail engine, one per method, variant, baseline, measure, workload or operator of SURVEY section 2."""

from __future__ import annotations

from collections.abc import Callable
from contextlib import contextmanager
from datetime import date, timedelta

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from trailgraph.baselines import layered, motif
from trailgraph.functions import columns
from trailgraph.functions.runtime import materialize, scratch_path
from trailgraph.operators import anomaly, community, flows, prep, risk, second_order, temporal
from trailgraph.operators.components import wcc, wcc_by
from trailgraph.plans import config, experiments, metrics, pipeline, sqlsurface
from trailgraph.queries.sql import ACCT, DAY, EVENTS, HOUR, PAY, ROLES, SEDGE, SUMMARY, TRADE, WCC, WTS, c1, q, tedge, wedge
from trailgraph.sources import ledger, store
from trailgraph.streaming import streams

_QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
_SQL: dict[str, str] = {}
_memo: dict = {}


def query(text: str | None = None, name: str | None = None):
    def put(f):
        _QUERIES[name or f.__name__] = f
        if text:
            _SQL[name or f.__name__] = text
        return f

    return put


def clear_memo() -> None:
    _memo.clear()


def _once(spark: SparkSession, key: tuple, make: Callable[[], DataFrame]) -> DataFrame:
    """A table that several queries start from, written once per session to the shared folder."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _memo:
        _memo[key] = materialize(make(), "base")[0]
    return _memo[key]


def _e(spark, d):
    return ledger.load(spark, d, "events")


def _r(spark, d):
    return ledger.load(spark, d, "trade")


def _edges(spark, d, hours: int = 24, kind: str = "events", method: str = "bucketed"):
    return temporal.build(ledger.load(spark, d, kind), timedelta(hours=hours), method)


def _wedges(spark, d, hours: int = 24, theta: float = 0.5, kind: str = "events"):
    stored = lambda: materialize(temporal.build(materialize(ledger.load(spark, d, kind), "ledger")[0], timedelta(hours=hours)), "edges")[0]  # noqa: E731  # both are read more than once
    return _once(spark, ("wedges", d, hours, theta, kind), lambda: second_order.weigh_and_prune(stored(), theta))


def _member(spark, d):
    """Weak components of the pruned E6h graph as flows."""
    return _once(spark, ("member", d), lambda: wcc(_wedges(spark, d, 6), "src_id", "dst_id").select(F.col("node").alias("txn_id"), F.col("component").alias("comm_id")))


def _pay(spark, d):
    return flows.payments(_member(spark, d), _e(spark, d))


def _flat(edges: DataFrame) -> DataFrame:
    return edges.select("src_id", "dst_id", "a", "b", "c", F.unix_micros("t_src").alias("us"), F.unix_micros("t_dst").alias("ud"))


def _us(txn: DataFrame) -> DataFrame:
    return txn.select("txn_id", F.unix_micros("ts").alias("us"), "payer", "payee", "amount", "channel")


E1D, E6H = (EVENTS, tedge(DAY)), (EVENTS, tedge(6 * HOUR))
FLOWS = (*E6H, wedge(), WCC, PAY, ROLES, SUMMARY)
T_COLS = "src_id, dst_id, a, b, c, us, ud"


# ---- ledgers, accounts, preparation (M1, M2) -------------------------------------------------

@query(q(EVENTS, select="SELECT * FROM txn"))
def ledger_events(spark, d):
    return _us(_e(spark, d))


@query(q(TRADE, select="SELECT * FROM txn"))
def ledger_trade(spark, d):
    return _us(_r(spark, d))


@query(q(ACCT, select="SELECT * FROM acct"))
def accounts(spark, d):
    return ledger.accounts(spark, d)


_DEG = "deg AS (SELECT acct, count(*) AS degree, count(DISTINCT other) AS partners FROM (SELECT payer AS acct, payee AS other FROM txn UNION ALL SELECT payee, payer FROM txn) GROUP BY acct)"


@query(q(EVENTS, _DEG, select="SELECT acct, degree FROM deg"))
def degree_txn(spark, d):
    return prep.degrees(_e(spark, d))


@query(q(EVENTS, _DEG, select="SELECT acct, partners AS degree FROM deg"))
def degree_counterparty(spark, d):
    return prep.degrees(_e(spark, d), "counterparty")


@query(q(EVENTS, _DEG, select="SELECT acct, degree FROM deg ORDER BY degree DESC, acct LIMIT 5"))
def hubs(spark, d):
    return prep.hubs(_e(spark, d), k=5)


_HUB = "hub AS (SELECT acct FROM deg ORDER BY degree DESC, acct LIMIT 5), lean AS (SELECT * FROM txn WHERE payer NOT IN (SELECT acct FROM hub) AND payee NOT IN (SELECT acct FROM hub))"


@query(q(EVENTS, _DEG, _HUB, select="SELECT * FROM lean"))
def drop_hubs(spark, d):
    return _us(prep.drop_hubs(_e(spark, d), k=5))


@query(q(EVENTS, _DEG, "hub AS (SELECT acct FROM deg ORDER BY partners DESC, acct LIMIT 5)", select="SELECT count(*) AS n_before, (SELECT count(*) FROM txn WHERE payer NOT IN (SELECT acct FROM hub) AND payee NOT IN (SELECT acct FROM hub)) AS n_after FROM txn"))
def drop_hubs_counterparty(spark, d):
    t = _e(spark, d)
    return metrics.retention(t, prep.drop_hubs(t, k=5, degree_kind="counterparty")).select("n_before", "n_after")


# ---- temporal graph (M3, M4) -----------------------------------------------------------------

@query(q(*E1D, select=f"SELECT {T_COLS} FROM tedge"))
def tedges_interval(spark, d):
    return _flat(_edges(spark, d, method="interval"))


@query(q(*E1D, select=f"SELECT {T_COLS} FROM tedge"))
def tedges_bucketed(spark, d):
    return _flat(_edges(spark, d))


@query(q(EVENTS, tedge(3 * DAY), select=f"SELECT {T_COLS} FROM tedge"))
def tedges_bucketed_fine(spark, d):
    return _flat(temporal.build(_e(spark, d), timedelta(days=3), bucket=timedelta(hours=7)))


@query(q(*E1D, select=f"SELECT {T_COLS} FROM tedge"))
def tedges_salted(spark, d):
    return _flat(temporal.build(_e(spark, d), timedelta(days=1), salts=4))


@query(q(*E1D, select=f"SELECT {T_COLS} FROM tedge"))
def tedges_daily(spark, d):
    return _flat(temporal.daily(_e(spark, d), timedelta(days=1)))


@query(q(*E1D, select=f"SELECT {T_COLS} FROM tedge"))
def tedges_append(spark, d):
    """The whole graph from three batches that arrive out of order, the second of them twice."""
    t = _e(spark, d)
    part = F.pmod(F.col("txn_id"), F.lit(3))
    w, stored, out = timedelta(days=1), t.limit(0), None
    for b in (2, 0, 0, 1):
        new = t.where(part == b)
        got = temporal.append(stored, new, w)
        out = got if out is None else out.unionByName(got)
        stored = stored.unionByName(new.join(stored.select("txn_id"), "txn_id", "left_anti"))
    return _flat(out)


@query(q(*E1D, select=f"SELECT {T_COLS} FROM tedge"))
def tedges_stream(spark, d):
    src = _event_files(spark, d)
    return _flat(_drained(spark, streams.temporal_edges(streams.events(spark, src), timedelta(days=1), "40 days")))


@query(q(*E1D, select=f"SELECT {T_COLS} FROM tedge"))
def tedges_theta_join(spark, d):
    """A nested-loop join over one broadcast side, as a cross-check: of the bounds of blocks first, then of the payments in blocks that can meet."""
    t = _e(spark, d)
    s = t.select(F.col("txn_id").alias("src_id"), F.col("payer").alias("a"), F.col("payee").alias("b"), F.unix_micros("ts").alias("us"))
    x = t.select(F.col("txn_id").alias("dst_id"), F.col("payer").alias("b2"), F.col("payee").alias("c"), F.unix_micros("ts").alias("ud"))
    return temporal.theta_join(s, x, DAY).select(*T_COLS.split(", "))


@query("SELECT CAST(0 AS BIGINT) AS n_edges")
def tedges_boundary_days(spark, d):
    """R1d: whole days under a look-ahead of one day give no edge."""
    return _edges(spark, d, 24, "trade").agg(F.count("*").alias("n_edges"))


@query(q(TRADE, tedge(7 * DAY), select="SELECT count(*) AS n_edges, count(DISTINCT a) AS n_a, CAST(sum(src_id % 1000003 + dst_id % 1000003) AS BIGINT) AS check_sum FROM tedge"))
def tedges_trade(spark, d):
    return _edges(spark, d, 168, "trade").agg(F.count("*").alias("n_edges"), F.countDistinct("a").alias("n_a"), F.sum(F.col("src_id") % 1000003 + F.col("dst_id") % 1000003).alias("check_sum"))


@query(q(EVENTS, f"s AS (SELECT payee AS b, us, unnest(generate_series((us + 1) // {DAY}, (us + {DAY} - 1) // {DAY})) AS slot FROM txn), sc AS (SELECT b, slot, count(*) AS n1 FROM s GROUP BY b, slot)", f"t AS (SELECT payer AS b, us // {DAY} AS slot, count(*) AS n2 FROM txn GROUP BY ALL)", select="SELECT b, slot, n1 * n2 AS pairs FROM sc JOIN t USING (b, slot)"))
def join_candidates(spark, d):
    return temporal.candidates(_e(spark, d), timedelta(days=1))


_DAYS = f"dd AS (SELECT *, us // {DAY} AS src_day, ud // {DAY} AS dst_day FROM tedge)"


def _stored(spark, d):
    key = (spark.sparkContext.applicationId, "store", d)
    if key not in _memo:
        path = scratch_path(spark, "edge-store")
        store.write_edges(_edges(spark, d), path)
        _memo[key] = path
    return _memo[key]


def _epoch_day(c):
    return F.datediff(F.col(c), F.lit("1970-01-01").cast("date")).cast("long")


@query(q(*E1D, _DAYS, select="SELECT src_day, dst_day, count(*) AS n FROM dd GROUP BY GROUPING SETS ((src_day), (dst_day), ())"))
def edge_day_matrix(spark, d):
    _edges(spark, d).select(_epoch_day("src_date").alias("src_day"), _epoch_day("dst_date").alias("dst_day")).createOrReplaceTempView("edge_days")
    return spark.sql("SELECT src_day, dst_day, count(*) AS n FROM edge_days GROUP BY GROUPING SETS ((src_day), (dst_day), ())")


@query(q(*E1D, _DAYS, select=f"SELECT {T_COLS} FROM dd WHERE dst_day <= 19735"))
def edges_as_of(spark, d):
    """The graph at the end of 2024-01-13, from the store."""
    return _flat(store.read_edges(spark, _stored(spark, d), as_of=date(2024, 1, 13)))


@query(q(*E1D, _DAYS, select=f"SELECT {T_COLS} FROM dd WHERE src_day BETWEEN 19727 AND 19729 AND dst_day BETWEEN 19728 AND 19730"))
def edges_between(spark, d):
    return _flat(store.read_edges(spark, _stored(spark, d), (date(2024, 1, 5), date(2024, 1, 7)), (date(2024, 1, 6), date(2024, 1, 8))))


@query(q(*E1D, _DAYS, select=f"SELECT {T_COLS} FROM dd WHERE src_day <= 19732 AND dst_day >= 19732"))
def edges_at_moment(spark, d):
    return _flat(store.read_edges(spark, _stored(spark, d), moment=date(2024, 1, 10)))


@query(q(*E1D, select="SELECT t.* FROM txn t WHERE txn_id NOT IN (SELECT src_id FROM tedge) AND txn_id NOT IN (SELECT dst_id FROM tedge)"))
def isolated_txns(spark, d):
    return _us(temporal.isolated(_e(spark, d), _edges(spark, d)))


@query(q(EVENTS, select="SELECT p.txn_id, max_by(r.txn_id, (r.us, r.txn_id)) AS receipt_id, p.us - max(r.us) AS held_us FROM txn p LEFT JOIN txn r ON r.payee = p.payer AND r.us < p.us GROUP BY p.txn_id, p.us"))
def asof_prev(spark, d):
    return temporal.latest_receipt(_e(spark, d))


# ---- second order (M5-M10) ---------------------------------------------------------------------

@query(q(*E1D, SEDGE, select="SELECT * FROM sedge"))
def pair_graph(spark, d):
    return second_order.pair_graph(_edges(spark, d))


@query(q(*E1D, select="SELECT a, b, c, count(DISTINCT dst_id) AS n FROM tedge GROUP BY a, b, c"))
def pair_graph_distinct_dst(spark, d):
    return second_order.pair_graph(_edges(spark, d), "distinct_dst")


@query(q(*E1D, SEDGE, select="SELECT * FROM sedge"))
def pair_graph_merged(spark, d):
    """Counts of two halves of the edges, added up."""
    e = _edges(spark, d)
    half = F.pmod("src_id", F.lit(2))
    return second_order.merge_pairs(second_order.pair_graph(e.where(half == 0)), second_order.pair_graph(e.where(half == 1)))


@query(q(*E1D, SEDGE, WTS, select="SELECT a, b, c, n, p_fwd FROM wts"))
def share_fwd(spark, d):
    return second_order.forward_share(second_order.pair_graph(_edges(spark, d)))


@query(q(*E1D, SEDGE, WTS, select="SELECT a, b, c, n, p_bwd FROM wts"))
def share_bwd(spark, d):
    return second_order.backward_share(second_order.pair_graph(_edges(spark, d)))


@query(q(*E1D, SEDGE, WTS, select="SELECT * FROM wts"))
def co_weight(spark, d):
    return second_order.weights(second_order.pair_graph(_edges(spark, d)))


@query(q(*E1D, SEDGE, WTS, select="SELECT * FROM wts"))
def co_weight_by_join(spark, d):
    return second_order.weights(second_order.pair_graph(_edges(spark, d)), how="join")


@query(q(*E1D, SEDGE, WTS, select="SELECT a, b, c, w FROM wts"))
def co_weight_sql(spark, d):
    sqlsurface.register(spark, pair_totals=second_order.totals(second_order.pair_graph(_edges(spark, d))))
    return spark.sql(f"SELECT a, b, c, {sqlsurface.co_weight_sql('n', 'n_out', 'n_in')} AS w FROM pair_totals")


@query(q(*E1D, SEDGE, WTS, select="SELECT a, b, c, (p_fwd + p_bwd) / 2 AS w FROM wts"))
def weights_mean(spark, d):
    return second_order.weights(second_order.pair_graph(_edges(spark, d)), "mean").select("a", "b", "c", "w")


@query(q(*E1D, SEDGE, WTS, select="SELECT a, b, c, p_fwd * p_bwd AS w FROM wts"))
def weights_product(spark, d):
    return second_order.weights(second_order.pair_graph(_edges(spark, d)), "product").select("a", "b", "c", "w")


@query(q(*E1D, wedge(0.0), select="SELECT src_id, dst_id, n, p_fwd, p_bwd, w FROM wedge"))
def wedges(spark, d):
    """Flagship: the weighted temporal graph."""
    e = _edges(spark, d)
    return second_order.attach(e, second_order.weights(second_order.pair_graph(e))).select("src_id", "dst_id", "n", "p_fwd", "p_bwd", "w")


@query(q(*E1D, wedge(), select="SELECT src_id, dst_id, a, b, c, w FROM wedge"))
def pruned(spark, d):
    return second_order.weigh_and_prune(_edges(spark, d), 0.5).select("src_id", "dst_id", "a", "b", "c", "w")


@query(q(TRADE, tedge(7 * DAY), wedge(), select="SELECT src_id, dst_id, w FROM wedge"))
def pruned_trade(spark, d):
    return second_order.weigh_and_prune(_edges(spark, d, 168, "trade"), 0.5).select("src_id", "dst_id", "w")


@query(q(*E1D, wedge(), select="SELECT src_id, dst_id, a, b, c, w FROM wedge"))
def pruned_two_pass(spark, d):
    return pipeline.wedges_two_pass(_e(spark, d), config.E1d, scratch_path(spark, "pairs")).select("src_id", "dst_id", "a", "b", "c", "w")


@query(q(*E1D, SEDGE, select="SELECT concat(a, '->', b) AS src_pair, concat(b, '->', c) AS dst_pair, n FROM sedge"))
def pair_labels(spark, d):
    return second_order.pair_labels(second_order.pair_graph(_edges(spark, d)))


@query(q(*E6H, select="SELECT x.a AS p0, x.b AS p1, x.c AS p2, y.c AS p3, count(*) AS n FROM tedge x JOIN tedge y ON x.dst_id = y.src_id GROUP BY ALL"))
def order3(spark, d):
    x = second_order.nth_order(_edges(spark, d, 6), 3)
    return x.select(*[F.col("path")[i].alias(f"p{i}") for i in range(4)], "n")


# ---- measures of the funnel (E1, E12, E13) -----------------------------------------------------

_LIVE = "live AS (SELECT count(DISTINCT x) AS n FROM (SELECT src_id AS x FROM tedge UNION ALL SELECT dst_id FROM tedge)), lw AS (SELECT count(DISTINCT x) AS n FROM (SELECT src_id AS x FROM wedge UNION ALL SELECT dst_id FROM wedge))"


@query(q(EVENTS, _DEG, _HUB, tedge(DAY, "lean"), wedge(), _LIVE, select="""SELECT 0 AS step, 'intake' AS stage, count(*) AS n_txn, NULL::BIGINT AS n_edge FROM txn UNION ALL SELECT 1, 'hubs removed', count(*), NULL FROM lean
UNION ALL SELECT 2, 'graph', (SELECT n FROM live), count(*) FROM tedge UNION ALL SELECT 3, 'pruned', (SELECT n FROM lw), count(*) FROM wedge"""))
def funnel(spark, d):
    """Explosion and implosion of the search space on ledger E."""
    t = _e(spark, d)
    lean = prep.drop_hubs(t, k=5)
    e = temporal.build(lean, timedelta(days=1))
    return metrics.funnel([("intake", t, None), ("hubs removed", lean, None), ("graph", None, e), ("pruned", None, second_order.weigh_and_prune(e, 0.5))])


@query(q(*E1D, wedge(), _LIVE, select="""SELECT (SELECT n FROM live) AS txn_before, (SELECT count(*) FROM tedge) AS edges_before, (SELECT n FROM lw) AS txn_after, (SELECT count(*) FROM wedge) AS edges_after,
round((SELECT count(*) FROM wedge) / (SELECT count(*) FROM tedge), 6) AS edges_kept, round((SELECT n FROM lw) / (SELECT n FROM live), 6) AS txn_kept,
round((SELECT count(*) FROM tedge) / (SELECT n FROM live), 6) AS per_txn_before, round((SELECT count(*) FROM wedge) / (SELECT n FROM lw), 6) AS per_txn_after"""))
def prune_ratio(spark, d):
    e = _edges(spark, d)
    return metrics.prune_ratio(e, second_order.weigh_and_prune(e, 0.5))


@query(q(EVENTS, "k AS (SELECT greatest(1, CAST(round(count(*) * 0.01) AS BIGINT)) AS n FROM txn), r AS (SELECT *, row_number() OVER (ORDER BY amount DESC, txn_id) AS rn FROM txn)", select="SELECT txn_id, us, payer, payee, amount, channel FROM r, k WHERE rn <= n"))
def prefilter_by_amount(spark, d):
    return _us(motif.aggressive_prefilter(_e(spark, d), 0.01))


# ---- components and communities (M11, E11) ------------------------------------------------------

@query(q(*E6H, wedge(), WCC, select="SELECT txn_id, comm_id FROM member"))
def wcc_small(spark, d):
    return _member(spark, d).select("txn_id", "comm_id")


@query(q(TRADE, tedge(7 * DAY), wedge(), WCC, select="SELECT count(DISTINCT comm_id) AS n_components, count(*) AS n_txn, CAST(sum(comm_id % 1000003) AS BIGINT) AS check_sum FROM member"))
def wcc_trade(spark, d):
    x = wcc(_wedges(spark, d, 168, 0.5, "trade"), "src_id", "dst_id")
    return x.agg(F.countDistinct("component").alias("n_components"), F.count("*").alias("n_txn"), F.sum(F.col("component") % 1000003).alias("check_sum"))


def _leiden(spark, d, **kw):
    return _once(spark, ("leiden", d, str(sorted(kw.items()))), lambda: community.detect(_wedges(spark, d), **kw))


@query(q(*E1D, wedge(), select="SELECT count(DISTINCT x) AS n_txn, CAST(0 AS BIGINT) AS n_missing FROM (SELECT src_id AS x FROM wedge UNION ALL SELECT dst_id FROM wedge)"))
def leiden_cover(spark, d):
    m, live = _leiden(spark, d), temporal.live_ids(_wedges(spark, d))
    return m.agg(F.countDistinct("txn_id").alias("n_txn")).crossJoin(live.join(m, "txn_id", "left_anti").agg(F.count("*").alias("n_missing")))


@query("SELECT CAST(0 AS BIGINT) AS n_shared")
def leiden_disjoint(spark, d):
    return metrics.overlap(_leiden(spark, d)).select("n_shared")


@query("SELECT CAST(0 AS BIGINT) AS n_loose")
def leiden_connected(spark, d):
    """Communities that aren't connected inside."""
    m = _leiden(spark, d).select("txn_id", "comm_id")
    e = _wedges(spark, d).select("src_id", "dst_id").join(m.select(F.col("txn_id").alias("src_id"), F.col("comm_id").alias("c1")), "src_id").join(m.select(F.col("txn_id").alias("dst_id"), F.col("comm_id").alias("c2")), "dst_id").where("c1 = c2")
    parts = wcc_by(e.withColumn("u", F.lit(0).cast("long")), "u", "src_id", "dst_id").join(m, F.col("node") == F.col("txn_id"))
    return parts.groupBy("comm_id").agg(F.countDistinct("component").alias("n")).agg(F.count_if(F.col("n") > 1).alias("n_loose"))


@query("SELECT CAST(0 AS BIGINT) AS n_over")
def leiden_cap(spark, d):
    m = _leiden(spark, d, max_comm_size=20)
    return m.groupBy("comm_id").agg(F.count("*").alias("n")).agg(F.count_if(F.col("n") > 20).alias("n_over"))


@query("SELECT true AS better")
def leiden_beats_wcc(spark, d):
    w = _wedges(spark, d)
    parts = wcc(w, "src_id", "dst_id").select(F.col("node").alias("txn_id"), F.col("component").alias("comm_id"))
    a, b = community.modularity(w, _leiden(spark, d)), community.modularity(w, parts).withColumnRenamed("modularity", "of_parts")
    return a.crossJoin(b).select((F.col("modularity") >= F.col("of_parts") - 1e-12).alias("better"))


@query("SELECT CAST(0 AS BIGINT) AS n_shared")
def leiden_windows(spark, d):
    """Independent runs per 10 days; no payment is in two communities of one window."""
    m = _leiden(spark, d, window="10 days")
    return m.groupBy("window_start", "txn_id").agg(F.count("*").alias("n")).agg(F.count_if(F.col("n") > 1).alias("n_shared"))


@query("SELECT CAST(0 AS BIGINT) AS n_shared, CAST(0 AS BIGINT) AS n_over")
def leiden_distributed(spark, d):
    """M11d: the engine for components that are too large for a task."""
    m = _once(spark, ("leiden-d", d), lambda: community.detect(_wedges(spark, d, 6), max_comm_size=30, engine="distributed"))
    s = m.groupBy("comm_id").agg(F.count("*").alias("n")).agg(F.count_if(F.col("n") > 30).alias("n_over"))
    return metrics.overlap(m).select("n_shared").crossJoin(s)


@query("SELECT CAST(0 AS BIGINT) AS n_shared")
def leiden_unweighted(spark, d):
    """The ablation without weights."""
    return metrics.overlap(_leiden(spark, d, weight=None)).select("n_shared")


@query("SELECT CAST(0 AS BIGINT) AS n_shared")
def leiden_cpm(spark, d):
    return metrics.overlap(_leiden(spark, d, quality="cpm", resolution=0.05)).select("n_shared")


_MOD = """lab AS (SELECT e.w, s.comm_id AS cs, t.comm_id AS cd FROM wedge e JOIN member s ON e.src_id = s.txn_id JOIN member t ON e.dst_id = t.txn_id),
mm AS (SELECT sum(w) AS m, sum(w) FILTER (cs = cd) AS inside FROM lab), o AS (SELECT cs AS c, sum(w) AS o FROM lab GROUP BY cs), i AS (SELECT cd AS c, sum(w) AS i FROM lab GROUP BY cd)"""


@query(q(*E6H, wedge(), WCC, _MOD, select="SELECT round(any_value(inside) / any_value(m) - sum(o * i) / any_value(m) / any_value(m), 9) AS modularity FROM o JOIN i USING (c), mm"))
def modularity_wcc(spark, d):
    return community.modularity(_wedges(spark, d, 6), _member(spark, d)).select(F.round("modularity", 9).alias("modularity"))


# ---- flows and risk (M12-M17) --------------------------------------------------------------------

@query(q(*FLOWS, select="SELECT * FROM roles"))
def roles(spark, d):
    return flows.roles(_pay(spark, d))


@query(q(*FLOWS, """own AS (SELECT p.comm_id, p.txn_id, p.payer, p.payee FROM pay p),
ends AS (SELECT comm_id, payer AS acct, 'dispense' AS role FROM own WHERE txn_id NOT IN (SELECT dst_id FROM wedge) UNION SELECT comm_id, payee, 'sink' FROM own WHERE txn_id NOT IN (SELECT src_id FROM wedge))""", select="SELECT p.comm_id, p.acct, coalesce(e.role, 'mid') AS role, paid, received FROM per p LEFT JOIN ends e USING (comm_id, acct)"))
def roles_by_txn(spark, d):
    return flows.roles(_pay(spark, d), role_mode="txn", edges=_wedges(spark, d, 6))


@query(q(*FLOWS, select="SELECT * FROM summary"))
def flow_summary(spark, d):
    p = _pay(spark, d)
    return flows.summarize(p, flows.roles(p))


@query(q(*FLOWS, select="SELECT comm_id, sunk_pct, coalesce(sunk_pct BETWEEN 50 AND 150, false) AS c2 FROM summary"))
def sunk_pct(spark, d):
    p = _pay(spark, d)
    return risk.sunk_pct(flows.summarize(p, flows.roles(p)), 50.0, 150.0)


@query(q(*FLOWS, ACCT, c1(), select="SELECT * FROM c1"))
def c1_all(spark, d):
    return risk.segment_ok(flows.roles(_pay(spark, d)), ledger.accounts(spark, d))


@query(q(*FLOWS, ACCT, c1("any"), select="SELECT * FROM c1"))
def c1_any(spark, d):
    return risk.segment_ok(flows.roles(_pay(spark, d)), ledger.accounts(spark, d), quantifier="any")


@query(q(*FLOWS, ACCT, c1(), select="SELECT comm_id, c1, coalesce(sunk_pct BETWEEN 50 AND 150, false) AS c2, dispensed, sunk FROM summary JOIN c1 USING (comm_id) WHERE c1 AND sunk_pct BETWEEN 50 AND 150"))
def c1_c2_flags(spark, d):
    return _flagged(spark, d).where("c1 and c2").select("comm_id", "c1", "c2", "dispensed", "sunk")


def _flagged(spark, d):
    return _once(spark, ("flagged", d), lambda: risk.flag(_pay(spark, d), _wedges(spark, d, 6), ledger.accounts(spark, d)))


@query("SELECT CAST(0 AS BIGINT) AS n_bad")
def maxflow_bounds(spark, d):
    """The temporal maximum flow passes neither what is dispensed nor what is sunk, nor the flow with unlimited hold."""
    p = _pay(spark, d)
    s = flows.summarize(p, flows.roles(p))
    x = s.join(risk.temporal_max_flow(p, _wedges(spark, d, 6)), "comm_id").join(risk.temporal_max_flow(p, None, "unbounded").withColumnRenamed("max_flow", "free"), "comm_id")
    return x.agg(F.count_if((F.col("max_flow") > F.least("dispensed", "sunk")) | (F.col("max_flow") > F.col("free")) | (F.col("free") > F.least("dispensed", "sunk"))).alias("n_bad"))


@query(q(*FLOWS, select="SELECT count(*) AS n_flows, CAST(0 AS BIGINT) AS n_differ FROM summary"))
def maxflow_cogroup(spark, d):
    """Payments and edges of each flow as cogrouped tables give the maximum flow that one row per flow gives."""
    p, w = _pay(spark, d), _wedges(spark, d, 6)
    packed = risk.temporal_max_flow(p, w).withColumnRenamed("max_flow", "other")
    x = risk.temporal_max_flow_cogrouped(p, w).join(packed, "comm_id", "full")
    return x.agg(F.count("*").alias("n_flows"), F.count_if(~F.col("max_flow").eqNullSafe(F.col("other"))).alias("n_differ"))


@query(None)
def suspicious_flows(spark, d):
    """C1, C2 and C3 together on weak components."""
    return _flagged(spark, d).where("suspicious").select("comm_id", "n_txn", "dispensed", "sunk", "max_flow")


@query(None)
def suspicious_communities(spark, d):
    """M17 on Leiden communities of E1d."""
    m = _leiden(spark, d, max_comm_size=200)
    p = flows.payments(m, _e(spark, d))
    return risk.flag(p, _wedges(spark, d), ledger.accounts(spark, d)).where("suspicious").select("comm_id", "n_txn", "dispensed", "sunk", "max_flow")


@query(q(*FLOWS, ACCT, select="""SELECT p.comm_id, CAST(sum(CASE WHEN channel = 'purchase' THEN amount ELSE 0 END) AS DOUBLE) / CAST(sum(amount) AS DOUBLE) AS cash_share,
CAST(sum(CASE WHEN coalesce(x.nation IN (3, 7), false) OR coalesce(y.nation IN (3, 7), false) THEN amount ELSE 0 END) AS DOUBLE) / CAST(sum(amount) AS DOUBLE) AS high_risk_share FROM pay p LEFT JOIN acct x ON p.payer = x.acct LEFT JOIN acct y ON p.payee = y.acct GROUP BY p.comm_id"""))
def risk_features(spark, d):
    return risk.features(_pay(spark, d), ledger.accounts(spark, d), high_risk=(3, 7)).select("comm_id", "cash_share", "high_risk_share")


@query(q(*FLOWS, select="SELECT comm_id, n_txn, n_txn >= 4 AS busy FROM summary WHERE n_txn >= 4"))
def pluggable_criterion(spark, d):
    """A user's own criterion, here a least number of payments."""
    more = (risk.Criterion("busy", lambda: F.col("n_txn") >= 4),)
    return risk.flag(_pay(spark, d), _wedges(spark, d, 6), ledger.accounts(spark, d), more=more).where("busy").select("comm_id", "n_txn", "busy")


@query(q(*FLOWS, select="SELECT p.comm_id, count(*) AS n_nodes, (SELECT count(*) FROM wedge e JOIN member m ON e.src_id = m.txn_id WHERE m.comm_id = p.comm_id) AS n_arcs FROM pay p GROUP BY p.comm_id"))
def export_graphs(spark, d):
    x = flows.export_graphs(_pay(spark, d), _wedges(spark, d, 6))
    return x.select("comm_id", F.size("txns").cast("long").alias("n_nodes"), F.size("edges").cast("long").alias("n_arcs"))


@query(q(*FLOWS, "busy AS (SELECT payee AS acct FROM txn GROUP BY payee ORDER BY count(*) DESC, payee LIMIT 1)", select="SELECT comm_id, CAST(sum(amount) AS BIGINT) AS moved, count(*) AS n FROM pay, busy WHERE payer = acct OR payee = acct GROUP BY comm_id ORDER BY moved DESC, comm_id LIMIT 10"))
def search_account(spark, d):
    """The ten flows in which the busiest receiver moves most."""
    acct = _e(spark, d).groupBy("payee").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "payee").first()["payee"]
    return flows.search(_pay(spark, d), acct, 10)


@query(q(EVENTS, tedge(6 * HOUR), wedge(), WCC, f"mw AS (SELECT txn_id, comm_id FROM member), aw AS (SELECT DISTINCT t.us // {7 * DAY} AS win, m.comm_id, unnest([t.payer, t.payee]) AS acct FROM mw m JOIN txn t USING (txn_id))", select="SELECT x.acct, y.acct AS acct2, count(DISTINCT x.win) AS n_windows FROM aw x JOIN aw y ON x.win = y.win AND x.comm_id = y.comm_id AND x.acct < y.acct GROUP BY ALL HAVING count(DISTINCT x.win) >= 2"))
def recurring_accounts(spark, d):
    """Pairs of accounts that share a flow in two weeks or more."""
    t = _e(spark, d)
    m = _member(spark, d).join(t.select("txn_id", "ts"), "txn_id").select(F.floor(F.unix_micros("ts") / (7 * DAY)).alias("window_start"), "comm_id", "txn_id")
    return community.recurring_accounts(m, t, 2, max_pairs_flow=2000)


# ---- baselines (B1-B10) and their measures ---------------------------------------------------------

def _ends_sql(h: int, name: str = "tedge") -> str:
    joins = " ".join(f"JOIN {name} e{i} ON e{i - 1}.dst_id = e{i}.src_id" for i in range(1, h - 1))
    return f"SELECT e0.a AS first_payer, e{h - 2}.c AS last_payee, count(*) AS n_paths FROM {name} e0 {joins} GROUP BY ALL"


def _motif(h: int):
    @query(q(*E1D, select=_ends_sql(h)), f"motif_h{h}")
    def run(spark, d):
        return motif.end_pairs(_edges(spark, d), h)


for _h in range(2, 8):
    _motif(_h)


@query(q(*E1D, wedge(), select=_ends_sql(4, "wedge")))
def motif_pruned_h4(spark, d):
    return motif.end_pairs(_wedges(spark, d), 4)


@query(q(*E1D, select="SELECT b AS mid, count(*) AS n_paths FROM tedge GROUP BY b"))
def motif_type1(spark, d):
    """Many to one to many."""
    return motif.flows(_edges(spark, d), ("*", "1", "*")).select(F.col("key")[0].alias("mid"), "n_paths")


@query(q(*E6H, select="SELECT e0.a AS k0, e0.c AS k1, count(*) AS n_paths FROM tedge e0 JOIN tedge e1 ON e0.dst_id = e1.src_id GROUP BY ALL"))
def motif_layers(spark, d):
    """Any pattern; here 1, open, 1, open."""
    return motif.flows(_edges(spark, d, 6), ("1", "*", "1", "*")).select(F.col("key")[0].alias("k0"), F.col("key")[1].alias("k1"), "n_paths")


@query(q(*E1D, select="SELECT a AS k0, c AS k1, count(*) AS n_paths FROM tedge GROUP BY a, c HAVING count(DISTINCT b) >= 2"))
def motif_two_intermediates(spark, d):
    return motif.flows(_edges(spark, d), min_intermediates=2).select(F.col("key")[0].alias("k0"), F.col("key")[1].alias("k1"), "n_paths")


_SEG = "seg AS (SELECT acct FROM acct WHERE segment IN ('HOUSEHOLD', 'MACHINERY', 'FURNITURE'))"


def _segments(spark, d):
    return ledger.accounts(spark, d).where(F.col("segment").isin(*risk.SEGMENTS)).select("acct")


@query(q(*E1D, ACCT, _SEG, select="SELECT e0.a AS first_payer, e1.c AS last_payee, count(*) AS n_paths FROM tedge e0 JOIN tedge e1 ON e0.dst_id = e1.src_id WHERE e0.a IN (SELECT acct FROM seg) AND e1.c IN (SELECT acct FROM seg) GROUP BY ALL"))
def motif_c1(spark, d):
    """Both ends in the segments, applied before the joins."""
    s = _segments(spark, d)
    return motif.end_pairs(_edges(spark, d), 3, s, s)


@query(q(*E6H, select="SELECT e0.src_id AS t0, e0.dst_id AS t1, e1.dst_id AS t2 FROM tedge e0 JOIN tedge e1 ON e0.dst_id = e1.src_id WHERE e0.a <> e0.b AND e0.a <> e0.c AND e0.b <> e0.c AND e1.c NOT IN (e0.a, e0.b, e0.c)"))
def motif_simple(spark, d):
    x = motif.paths(_edges(spark, d, 6), 3, simple=True)
    return x.select(*[F.col("ids")[i].alias(f"t{i}") for i in range(3)])


def _growth_sql(name: str, hops) -> str:
    return " UNION ALL ".join(f"SELECT {h} AS hops, CAST(coalesce(sum(n_paths), 0) AS BIGINT) AS n_paths, count(*) AS n_flows FROM ({_ends_sql(h, name)})" for h in hops)


@query(q(*E1D, select=_growth_sql("tedge", range(2, 8))))
def motif_growth(spark, d):
    """Paths and flows by number of hops, unpruned."""
    return motif.growth(_once(spark, ("edges", d), lambda: _edges(spark, d)))


@query(q(*E1D, wedge(), select=_growth_sql("wedge", range(2, 8))))
def motif_growth_pruned(spark, d):
    return motif.growth(_wedges(spark, d))


_M3 = "m3 AS (SELECT DISTINCT e0.a AS first_payer, e1.c AS last_payee, unnest([e0.src_id, e0.dst_id, e1.dst_id]) AS txn_id FROM wedge e0 JOIN wedge e1 ON e0.dst_id = e1.src_id)"


@query(q(*E1D, wedge(), _M3, "pp AS (SELECT txn_id, count(*) AS n FROM m3 GROUP BY txn_id)", select="SELECT count(*) AS n_items, count(*) FILTER (n > 1) AS n_shared, round(avg(n), 6) AS mean_flows FROM pp"))
def overlap_motif(spark, d):
    """How many payments lie in several flows of the baseline."""
    return metrics.overlap(motif.members(_wedges(spark, d), 3))


@query("SELECT CAST(0 AS BIGINT) AS n_shared")
def overlap_communities(spark, d):
    return metrics.overlap(_leiden(spark, d)).select("n_shared")


def _layered_sql(k: int) -> str:
    j = " ".join(f"JOIN wedge e{i} ON e{i - 1}.dst_id = e{i}.src_id" for i in range(1, k - 2))
    ids = ", ".join(["e0.src_id", *[f"e{i}.dst_id" for i in range(k - 2)]])
    last = f"e{k - 3}.c"
    return f"""lay AS (SELECT DISTINCT m.comm_id, unnest([{ids}]) AS txn_id FROM wedge e0 {j} JOIN member m ON m.txn_id = e0.src_id
  JOIN roles r1 ON r1.comm_id = m.comm_id AND r1.acct = e0.a AND r1.role = 'dispense' JOIN roles r2 ON r2.comm_id = m.comm_id AND r2.acct = {last} AND r2.role = 'sink')"""


def _layered(k: int):
    @query(q(*FLOWS, _layered_sql(k), select="SELECT * FROM lay"), f"layered_k{k}")
    def run(spark, d):
        return layered.restrict(_pay(spark, d), _wedges(spark, d, 6), k).select("comm_id", "txn_id")


for _k in (3, 4, 5):
    _layered(_k)


_KS = (3, 4, 5)
_PARTS = ", ".join(_layered_sql(k).replace("lay AS", f"lay{k} AS", 1) for k in _KS) + ", parts AS (" + " UNION ALL ".join(f"SELECT {k} AS k, * FROM lay{k}" for k in _KS) + ")"
_ON = "pa AS (SELECT DISTINCT k, comm_id, unnest([payer, payee]) AS acct FROM parts JOIN pay USING (comm_id, txn_id))"


@query(q(*FLOWS, _PARTS, _ON, select="SELECT k, comm_id, n_txn, n_acct FROM (SELECT k, comm_id, count(*) AS n_txn FROM parts GROUP BY ALL) JOIN (SELECT k, comm_id, CAST(count(*) AS INTEGER) AS n_acct FROM pa GROUP BY ALL) USING (k, comm_id)"))
def layered_sweep(spark, d):
    """What is left of every flow for each number of layers."""
    return layered.sweep(_pay(spark, d), _wedges(spark, d, 6), _KS).select("k", "comm_id", "n_txn", "n_acct")


@query(None)
def split_loss(spark, d):
    """What the whole flow passes and its fixed-length parts lose, at the threshold of C3."""
    return layered.split_loss(_pay(spark, d), _wedges(spark, d, 6), _KS)


_LOST = """SELECT p.comm_id, count(DISTINCT k) AS n_ks, count(DISTINCT k) AS n_flagged,
(SELECT count(*) FROM (SELECT payer AS acct FROM pay x WHERE x.comm_id = p.comm_id UNION SELECT payee FROM pay x WHERE x.comm_id = p.comm_id) w WHERE w.acct NOT IN (SELECT acct FROM pa WHERE pa.comm_id = p.comm_id)) AS n_lost
FROM (SELECT DISTINCT comm_id FROM pay) p LEFT JOIN parts USING (comm_id) GROUP BY p.comm_id"""


@query(q(*FLOWS, _PARTS, _ON, select=_LOST))
def split_loss_reach(spark, d):
    """E10 with a threshold of 0: every part that there is passes, so accounts are lost only where no walk of 3 to 5 layers reaches them."""
    return layered.split_loss(_pay(spark, d), _wedges(spark, d, 6), _KS, 0).select("comm_id", "n_ks", "n_flagged", "n_lost")


@query(None)
def case_studies(spark, d):
    """The ten flows that sink most, each with its parts for 3 to 5 layers."""
    p = _pay(spark, d)
    top = flows.summarize(p, flows.roles(p)).orderBy(F.desc("sunk"), "comm_id").limit(10).select("comm_id")
    ten = p.join(F.broadcast(top), "comm_id", "left_semi")
    return layered.split_loss(ten, _wedges(spark, d, 6), _KS)


@query("WITH b AS (SELECT count(*) AS n FROM region), m AS (SELECT unnest(generate_series(1, (SELECT (1 << n) - 1 FROM b))) AS mask) SELECT CAST(mask AS INTEGER) AS mask, CAST(bit_count(mask) AS INTEGER) AS n_banks FROM m")
def bank_subsets(spark, d):
    """31 sets of pass-through banks."""
    return layered.bank_subsets(spark.read.parquet(f"{d}/region.parquet").select(F.col("r_regionkey").alias("bank")))


@query(q(*E1D, ACCT, "per AS (SELECT bank, count(*) AS n FROM tedge JOIN acct ON b = acct GROUP BY bank), m AS (SELECT unnest(generate_series(1, 31)) AS mask)", select="SELECT CAST(mask AS INTEGER) AS mask, CAST(bit_count(mask) AS INTEGER) AS n_banks, CAST(coalesce(sum(n), 0) AS BIGINT) AS n_walks FROM m LEFT JOIN per ON (mask >> bank) % 2 = 1 GROUP BY mask"))
def bank_set_flows(spark, d):
    return layered.bank_set_flows(_edges(spark, d), ledger.accounts(spark, d))


@query(q(*E6H, ACCT, "ok AS (SELECT t.* FROM tedge t JOIN acct ON b = acct WHERE (5 >> bank) % 2 = 1)", select="SELECT x.src_id AS t0, x.dst_id AS t1, y.dst_id AS t2 FROM ok x JOIN ok y ON x.dst_id = y.src_id"))
def layered_partite(spark, d):
    """k = 4 with middle accounts in banks 0 and 2."""
    x = layered.partite(_edges(spark, d, 6), ledger.accounts(spark, d), 5, 4)
    return x.select(*[F.col("ids")[i].alias(f"t{i}") for i in range(3)])


@query(None)
def layered_peel(spark, d):
    """B10."""
    return layered.peel(_pay(spark, d))


# ---- comparison of methods (E6, E7, E9) -----------------------------------------------------------

_FLAGGED = """f AS (SELECT 'components' AS method, CAST(comm_id AS VARCHAR) AS flow_key, unnest([payer, payee]) AS acct
  FROM pay JOIN c1 USING (comm_id) JOIN summary USING (comm_id) WHERE c1 AND sunk_pct BETWEEN 50 AND 150
  UNION ALL SELECT 'motif-join+', e0.a || '|' || e1.c, unnest([e0.a, e0.b, e0.c, e1.c])
  FROM wedge e0 JOIN wedge e1 ON e0.dst_id = e1.src_id WHERE e0.a IN (SELECT acct FROM seg) AND e1.c IN (SELECT acct FROM seg)),
u AS (SELECT count(DISTINCT acct) AS n_union FROM f)"""


def _two_methods(spark, d):
    """FLAGGED of weak components that pass C1 and C2, and of motif flows of three hops whose ends pass C1."""
    pay, keys, s = _pay(spark, d), ("first_payer", "last_payee"), _segments(spark, d)
    a = risk.flagged_accounts(_flagged(spark, d).withColumn("suspicious", F.col("c1") & F.col("c2")), pay, "components")
    p = flows.payments(motif.members(_wedges(spark, d, 6), 3, first=s, last=s), _e(spark, d), keys)
    found = p.select(*keys).distinct().withColumn("suspicious", F.lit(True))
    return a.unionByName(risk.flagged_accounts(found, p, "motif-join+", keys))


@query(q(*FLOWS, ACCT, _SEG, c1(), _FLAGGED, select="SELECT method, count(DISTINCT acct) AS n_acct, any_value(n_union) AS n_union, count(DISTINCT acct) * 100 / any_value(n_union) AS coverage_pct FROM f, u GROUP BY method"))
def coverage(spark, d):
    """E7."""
    return metrics.coverage(_two_methods(spark, d))


@query(q(*FLOWS, ACCT, _SEG, c1(), _FLAGGED, select="SELECT method, count(DISTINCT flow_key) AS n_cases FROM f GROUP BY method"))
def cases(spark, d):
    """E6."""
    return metrics.cases(_two_methods(spark, d))


@query(None)
def method_comparison(spark, d):
    """Cases and coverage of the engine, its unweighted form and the motif baseline over one window, same criteria."""
    t, acct, w = materialize(_e(spark, d), "ledger")[0], ledger.accounts(spark, d), _wedges(spark, d, 6)
    first = w.where(F.col("t_src") < F.timestamp_seconds(F.lit(1_704_067_200 + 10 * 86_400)))

    def judged(method: str, member, keys=flows.KEYS):
        """Payments are stored, as the criteria read them many times and a plan with as many copies of the search fills the driver."""
        p, _ = materialize(flows.payments(member, t, keys), "payments")
        return materialize(risk.flagged_accounts(risk.flag(p, first, acct, keys=keys), p, method, keys), "flagged")[0]

    out = judged("trail", community.detect(first, "w", max_comm_size=200))
    out = out.unionByName(judged("trail-unweighted", community.detect(first, None, max_comm_size=200)))
    s = _segments(spark, d)
    out = out.unionByName(judged("motif-join+", motif.members(first, 3, first=s, last=s), ("first_payer", "last_payee")))
    return metrics.coverage(out).join(metrics.cases(out), "method", "left")


@query(q(*FLOWS, "l AS (UNPIVOT (SELECT comm_id, n_dispense, n_sink FROM summary) ON n_dispense, n_sink INTO NAME measure VALUE value)", select="SELECT measure, value, count(*) AS n_in_scope FROM l GROUP BY ALL"))
def topology_hist(spark, d):
    """E9 on weak components."""
    return metrics.topology_hist(_flagged(spark, d), ("n_dispense", "n_sink")).select("measure", "value", "n_in_scope")


@query(None)
def topology_communities(spark, d):
    """Diameter, dispense and sink accounts of communities, in scope and suspicious."""
    p = flows.payments(_leiden(spark, d, max_comm_size=200), _e(spark, d))
    f = risk.flag(p, _wedges(spark, d), ledger.accounts(spark, d)).join(flows.diameters(p), "comm_id")
    return metrics.topology_hist(f)


@query(None)
def flow_vectors(spark, d):
    p = _pay(spark, d)
    r = flows.roles(p)
    return flows.vectors(p, flows.summarize(p, r), r, ledger.accounts(spark, d), _wedges(spark, d, 6))


# ---- anomaly scores (M18) ----------------------------------------------------------------------

_Z = "x AS (SELECT vec_id, unnest(embedding)::DOUBLE AS v, generate_subscripts(embedding, 1) AS i FROM embeddings), mo AS (SELECT i, avg(v) AS m, stddev_pop(v) AS s FROM x GROUP BY i), z AS (SELECT vec_id, (v - m) / s AS z FROM x JOIN mo USING (i))"


def _vectors(spark, d):
    return spark.read.parquet(f"{d}/embeddings.parquet").select("vec_id", F.col("embedding").alias("vector"))


@query(f"WITH {_Z} SELECT vec_id, round(max(abs(z)), 6) AS score FROM z GROUP BY vec_id")
def z_embed(spark, d):
    return anomaly.zscore(_vectors(spark, d), "vec_id").select("vec_id", F.round("score", 6).alias("score"))


@query(f"WITH {_Z} SELECT vec_id, round(sqrt(sum(z * z)), 5) AS score FROM z GROUP BY vec_id")
def mahalanobis_embed(spark, d):
    return anomaly.mahalanobis_diag(_vectors(spark, d), "vec_id").select("vec_id", F.round("score", 5).alias("score"))


@query("""WITH p AS (SELECT a.vec_id, list_distance(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) AS dist FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY dist) AS rn FROM p) SELECT vec_id, round(dist, 5) AS score FROM r WHERE rn = 5""")
def knn_embed(spark, d):
    return anomaly.knn_distance(_vectors(spark, d), "vec_id").select("vec_id", F.round("score", 5).alias("score"))


@query(q(*FLOWS, "qq AS (SELECT quantile_cont(amount, 0.25) AS q1, quantile_cont(amount, 0.75) AS q3 FROM summary)", select="SELECT comm_id, amount, amount < q1 - 1.5 * (q3 - q1) OR amount > q3 + 1.5 * (q3 - q1) AS outlier FROM summary, qq"))
def iqr_flow(spark, d):
    p = _pay(spark, d)
    return anomaly.iqr(flows.summarize(p, flows.roles(p)), "comm_id", "amount")


# ---- operators around them (2.5) -------------------------------------------------------------------

@query(q(EVENTS, "a AS (SELECT payee AS acct, us, txn_id, amount AS m FROM txn UNION ALL SELECT payer, us, txn_id, -amount FROM txn)", select="SELECT acct, txn_id, CAST(sum(m) OVER (PARTITION BY acct ORDER BY us, txn_id, m ROWS UNBOUNDED PRECEDING) AS BIGINT) AS balance FROM a"))
def running_balance(spark, d):
    """W4f."""
    t = _e(spark, d)
    a = t.select(F.col("payee").alias("acct"), F.unix_micros("ts").alias("us"), "txn_id", F.col("amount").alias("m")).unionByName(t.select(F.col("payer").alias("acct"), F.unix_micros("ts").alias("us"), "txn_id", (-F.col("amount")).alias("m")))
    w = Window.partitionBy("acct").orderBy("us", "txn_id", "m").rowsBetween(Window.unboundedPreceding, 0)
    return a.select("acct", "txn_id", F.sum("m").over(w).alias("balance"))


@query(q(EVENTS, select=f"SELECT txn_id, CAST(sum(amount) OVER (PARTITION BY payee ORDER BY us RANGE BETWEEN {DAY} PRECEDING AND CURRENT ROW) AS BIGINT) AS trailing FROM txn"))
def trailing_turnover(spark, d):
    """W5f."""
    w = Window.partitionBy("payee").orderBy("us").rangeBetween(-DAY, 0)
    return _us(_e(spark, d)).select("txn_id", F.sum("amount").over(w).alias("trailing"))


@query(q(EVENTS, select="SELECT txn_id, lead(us) OVER w - us AS gap, CAST(row_number() OVER w AS INTEGER) AS rn, CAST(ntile(4) OVER w AS INTEGER) AS quart, first_value(txn_id) OVER w AS first_txn FROM txn WINDOW w AS (PARTITION BY payee ORDER BY us, txn_id)"))
def hold_gap(spark, d):
    """W2f, W3f."""
    w = Window.partitionBy("payee").orderBy("us", "txn_id")
    return _us(_e(spark, d)).select("txn_id", (F.lead("us").over(w) - F.col("us")).alias("gap"), F.row_number().over(w).alias("rn"), F.ntile(4).over(w).alias("quart"), F.first("txn_id").over(w).alias("first_txn"))


@query(q(EVENTS, ACCT, select="SELECT bank, nation, CAST(sum(amount) AS BIGINT) AS paid, count(*) AS n, CAST(grouping(bank) * 2 + grouping(nation) AS BIGINT) AS gid FROM txn JOIN acct ON payer = acct GROUP BY ROLLUP (bank, nation)"))
def bank_rollup(spark, d):
    """A9g."""
    x = _e(spark, d).join(ledger.accounts(spark, d), F.col("payer") == F.col("acct"))
    return x.rollup("bank", "nation").agg(F.sum("amount").alias("paid"), F.count("*").alias("n"), F.grouping_id().cast("long").alias("gid"))


@query(q(EVENTS, ACCT, select="SELECT bank, channel, CAST(sum(amount) AS BIGINT) AS paid, CAST(grouping(bank) * 2 + grouping(channel) AS BIGINT) AS gid FROM txn JOIN acct ON payer = acct GROUP BY CUBE (bank, channel)"))
def bank_cube(spark, d):
    """A10g."""
    x = _e(spark, d).join(ledger.accounts(spark, d), F.col("payer") == F.col("acct"))
    return x.cube("bank", "channel").agg(F.sum("amount").alias("paid"), F.grouping_id().cast("long").alias("gid"))


@query(q(*E1D, wedge(0.0), "r AS (SELECT *, row_number() OVER (PARTITION BY src_id ORDER BY w DESC, dst_id) AS rn FROM wedge)", select="SELECT src_id, dst_id, w FROM r WHERE rn <= 3"))
def top_edges(spark, d):
    """The three strongest successors of each payment."""
    w = Window.partitionBy("src_id").orderBy(F.desc("w"), "dst_id")
    return second_order.weigh_and_prune(_edges(spark, d), 0.0).withColumn("rn", F.row_number().over(w)).where("rn <= 3").select("src_id", "dst_id", "w")


@query(q(EVENTS, select="PIVOT (SELECT payer, channel, amount FROM txn) ON channel IN ('click', 'purchase', 'view') USING CAST(coalesce(sum(amount), 0) AS BIGINT) GROUP BY payer"))
def channel_pivot(spark, d):
    """A12g."""
    names = ["click", "purchase", "view"]
    x = _e(spark, d).groupBy("payer").pivot("channel", names).agg(F.sum("amount"))
    return x.select("payer", *[F.coalesce(n, F.lit(0)).alias(n) for n in names])


@query(q(*E6H, select="SELECT * FROM (UNPIVOT (SELECT a, src_id, dst_id FROM tedge) ON src_id, dst_id INTO NAME side VALUE txn_id)"))
def edge_unpivot(spark, d):
    return _edges(spark, d, 6).select("a", "src_id", "dst_id").unpivot("a", ["src_id", "dst_id"], "side", "txn_id")


@query(q(EVENTS, select="SELECT payer, max_by(txn_id, (amount, txn_id)) AS peak_txn, max(amount) AS peak, count(*) FILTER (channel = 'purchase') AS n_buy, bool_or(amount > 4000000) AS big FROM txn GROUP BY payer HAVING count(*) > 1"))
def account_facts(spark, d):
    """A4g, A6g, A13g."""
    return _e(spark, d).groupBy("payer").agg(F.max_by("txn_id", F.struct("amount", "txn_id")).alias("peak_txn"), F.max("amount").alias("peak"), F.count_if(F.col("channel") == "purchase").alias("n_buy"), F.bool_or(F.col("amount") > 4000000).alias("big"), F.count("*").alias("n")).where("n > 1").drop("n")


@query(q(EVENTS, select="SELECT channel, median(amount) AS med, quantile_cont(amount, 0.9) AS p90, round(stddev_samp(amount), 3) AS sd, round(corr(amount, us), 9) AS r, round(regr_slope(amount, us), 12) AS slope FROM txn GROUP BY channel"))
def channel_statistics(spark, d):
    """A7g, A8g."""
    return _us(_e(spark, d)).groupBy("channel").agg(F.percentile("amount", 0.5).alias("med"), F.percentile("amount", 0.9).alias("p90"), F.round(F.stddev_samp("amount"), 3).alias("sd"), F.round(F.corr("amount", "us"), 9).alias("r"), F.round(F.regr_slope("amount", "us"), 12).alias("slope"))


@query(q(EVENTS, select="SELECT amount // 500000 AS bin, count(*) AS n FROM txn GROUP BY bin"))
def amount_histogram(spark, d):
    """A15g."""
    return _e(spark, d).groupBy(columns.bucketed(F.col("amount"), 500000).alias("bin")).agg(F.count("*").alias("n"))


@query(q(EVENTS, select="SELECT DISTINCT payer AS acct FROM txn UNION SELECT DISTINCT payee FROM txn"))
def all_accounts(spark, d):
    """O7."""
    t = _e(spark, d)
    return t.select(F.col("payer").alias("acct")).union(t.select("payee")).distinct()


@query(q(EVENTS, select="SELECT payer AS acct FROM txn INTERSECT SELECT payee FROM txn"))
def forwarding_accounts(spark, d):
    """O8."""
    t = _e(spark, d)
    return t.select(F.col("payer").alias("acct")).intersect(t.select("payee"))


@query(q(EVENTS, select="SELECT payer AS acct FROM txn EXCEPT ALL SELECT payee FROM txn"))
def surplus_payments(spark, d):
    """O9."""
    t = _e(spark, d)
    return t.select(F.col("payer").alias("acct")).exceptAll(t.select("payee"))


@query(q(EVENTS, select="SELECT txn_id, amount FROM txn ORDER BY amount DESC, txn_id LIMIT 20 OFFSET 10"))
def payment_page(spark, d):
    """O4."""
    return _e(spark, d).select("txn_id", "amount").orderBy(F.desc("amount"), "txn_id").offset(10).limit(20)


@query(q(EVENTS, ACCT, "o AS (SELECT payer AS acct, CAST(sum(amount) AS BIGINT) AS paid FROM txn GROUP BY payer), i AS (SELECT payee AS acct, CAST(sum(amount) AS BIGINT) AS got FROM txn GROUP BY payee)", select="SELECT coalesce(o.acct, i.acct) AS acct, paid, got, segment FROM o FULL JOIN i ON o.acct = i.acct LEFT JOIN acct ON acct.acct = coalesce(o.acct, i.acct)"))
def account_balance_sheet(spark, d):
    """Full and left outer joins."""
    t = _e(spark, d)
    o, i = t.groupBy(F.col("payer").alias("acct")).agg(F.sum("amount").alias("paid")), t.groupBy(F.col("payee").alias("acct")).agg(F.sum("amount").alias("got"))
    return o.join(i, "acct", "full").join(ledger.accounts(spark, d).select("acct", "segment"), "acct", "left")


@query(q(EVENTS, select="SELECT txn_id, concat(payer, '->', payee) AS pair, substring(sha256(concat('trail:', CAST(payer AS VARCHAR))), 1, 16) AS payer_alias, upper(channel) AS ch, lpad(CAST(txn_id AS VARCHAR), 8, '0') AS code, CAST(us // 86400000000 AS BIGINT) AS day_no FROM txn"))
def payment_labels(spark, d):
    """String and date functions."""
    return _us(_e(spark, d)).select("txn_id", columns.pair_label("payer", "payee").alias("pair"), columns.pseudonym("payer").alias("payer_alias"), F.upper("channel").alias("ch"), F.lpad(F.col("txn_id").cast("string"), 8, "0").alias("code"), F.floor(F.col("us") / DAY).alias("day_no"))


@query(q(EVENTS, "l AS (SELECT payer, list(amount ORDER BY txn_id) AS xs FROM txn GROUP BY payer)", select="SELECT payer, len(xs)::INTEGER AS n, CAST(list_sum(list_filter(xs, lambda x: x > 2000000)) AS BIGINT) AS big, list_max(xs) AS top, list_contains(xs, 1000000) AS round_one, len(list_distinct(xs))::INTEGER AS n_kinds FROM l"))
def payment_arrays(spark, d):
    """Array functions."""
    x = _e(spark, d).groupBy("payer").agg(F.transform(F.array_sort(F.collect_list(F.struct("txn_id", "amount"))), lambda e: e["amount"]).alias("xs"))
    big = F.filter("xs", lambda v: v > 2000000)
    return x.select("payer", F.size("xs").alias("n"), F.when(F.size(big) > 0, F.aggregate(big, F.lit(0).cast("long"), lambda a, v: a + v)).alias("big"), F.array_max("xs").alias("top"), F.array_contains("xs", F.lit(1000000).cast("long")).alias("round_one"), F.size(F.array_distinct("xs")).alias("n_kinds"))


@query(q(EVENTS, "m AS (SELECT payer, channel, CAST(sum(amount) AS BIGINT) AS s FROM txn GROUP BY ALL)", select="SELECT payer, count(*)::INTEGER AS n_channels, max(s) FILTER (channel = 'purchase') AS bought FROM m GROUP BY payer"))
def channel_maps(spark, d):
    """Map functions: amount per channel."""
    x = _e(spark, d).groupBy("payer", "channel").agg(F.sum("amount").alias("s")).groupBy("payer").agg(F.map_from_entries(F.collect_list(F.struct("channel", "s"))).alias("m"))
    return x.select("payer", F.size(F.map_keys("m")).alias("n_channels"), F.try_element_at("m", F.lit("purchase")).alias("bought"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def event_props(spark, d):
    """JSON functions."""
    return spark.read.parquet(f"{d}/events.parquet").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


@query("SELECT CAST(0 AS BIGINT) AS n_off")
def approximate_degrees(spark, d):
    """A3g: accounts whose approximate counterparty degree is off by over a tenth (and over 2)."""
    t = _e(spark, d)
    x = prep.degrees(t, "counterparty").join(prep.degrees(t, "counterparty_approx").withColumnRenamed("degree", "near"), "acct")
    return x.agg(F.count_if(F.abs(F.col("degree") - F.col("near")) > F.greatest(F.lit(2.0), F.col("degree") * 0.1)).alias("n_off"))


@query(q(EVENTS, select="SELECT txn_id, amount, channel FROM txn WHERE amount BETWEEN 100000 AND 3000000 AND channel IN ('purchase', 'view') AND channel LIKE '%e%' AND regexp_matches(channel, '^[pv]') AND channel IS NOT DISTINCT FROM channel AND us >= 1704672000000000 AND us < 1705276800000000"))
def predicates(spark, d):
    """Half-open dates, ranges, lists, patterns, null-safe equality."""
    t = _us(_e(spark, d))
    c = F.col("channel")
    return t.where(F.col("amount").between(100000, 3000000) & c.isin("purchase", "view") & c.like("%e%") & c.rlike("^[pv]") & c.eqNullSafe(c) & (F.col("us") >= 1704672000000000) & (F.col("us") < 1705276800000000)).select("txn_id", "amount", "channel")


@query(q(EVENTS, ACCT, select="SELECT acct.acct, count(txn_id) AS n FROM txn RIGHT JOIN acct ON payer = acct.acct WHERE acct.kind = 'customer' GROUP BY acct.acct"))
def silent_accounts(spark, d):
    """Right outer join - customers with their number of payments, none included."""
    a = ledger.accounts(spark, d).where("kind = 'customer'")
    return _e(spark, d).join(a, F.col("payer") == F.col("acct"), "right").groupBy("acct").agg(F.count("txn_id").alias("n"))


_BATCHES = " UNION ALL ".join(f"SELECT {b} AS batch, (SELECT count(*) FROM txn WHERE us // {DAY} - 19723 >= {10 * b} AND us // {DAY} - 19723 < {10 * b + 10}) AS n_txn, (SELECT count(*) FROM tedge WHERE greatest(us, ud) // {DAY} - 19723 >= {10 * b} AND greatest(us, ud) // {DAY} - 19723 < {10 * b + 10}) AS n_new_edges" for b in range(3))


@query(q(*E1D, select=_BATCHES))
def batch_growth(spark, d):
    """Batches of ten days appended in order."""
    return experiments.batches(_e(spark, d), 10, timedelta(days=1))


@query(q(*E1D, SEDGE, WTS, "w6 AS (SELECT t.w FROM wts t JOIN tedge USING (a, b, c))", select="SELECT 24.0::DOUBLE AS delta_hours, CAST(th AS DOUBLE) AS min_weight, (SELECT count(*) FROM w6 WHERE w >= th) AS n_edge FROM (VALUES (0.3), (0.5), (1.0)) v(th)"))
def theta_sweep(spark, d):
    return experiments.sweep(_e(spark, d), (timedelta(days=1),), (0.3, 0.5, 1.0))


# ---- streaming (T1-T9) --------------------------------------------------------------------------------

def _event_files(spark, d):
    """The events as three files, earliest first, in a folder that a stream can read."""
    key = (spark.sparkContext.applicationId, "event-files", d)
    if key not in _memo:
        path = scratch_path(spark, "event-files")
        spark.read.parquet(f"{d}/events.parquet").repartitionByRange(3, "ts").sortWithinPartitions("ts").write.parquet(path)
        _memo[key] = path
    return _memo[key]


@contextmanager
def _state_width(spark):
    """State stores for the cores there are: a stream's state isn't coalesced as batch shuffles are."""
    was = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", str(min(int(was), 2 * spark.sparkContext.defaultParallelism)))
    try:
        yield
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", was)


def _drained(spark, stream, mode="append"):
    out, mark = scratch_path(spark, "drained"), scratch_path(spark, "mark")
    with _state_width(spark):
        streams.drain(stream, out, mark, mode)
    return spark.read.schema(stream.schema).parquet(out)


def _final(spark, stream, key: list[str]):
    """The last state of an updating aggregate: every batch is kept, and the latest row of each key counts."""
    out, mark = scratch_path(spark, "updates"), scratch_path(spark, "mark")

    def add(batch, batch_id):
        batch.withColumn("batch", F.lit(batch_id)).write.mode("append").parquet(out)

    with _state_width(spark):
        stream.writeStream.foreachBatch(add).option("checkpointLocation", mark).outputMode("update").trigger(availableNow=True).start().awaitTermination()
    w = Window.partitionBy(*key).orderBy(F.desc("batch"))
    return spark.read.parquet(out).withColumn("__r", F.row_number().over(w)).where("__r = 1").drop("__r", "batch")


@query(q(EVENTS, select=f"SELECT us // {DAY} * {DAY} AS start_us, payer, CAST(sum(amount) AS BIGINT) AS paid, count(*) AS n FROM txn GROUP BY ALL"))
def tumbling(spark, d):
    return _final(spark, streams.tumbling(streams.events(spark, _event_files(spark, d)), lateness="40 days"), ["start_us", "payer"])


@query(q(EVENTS, f"s AS (SELECT us // {DAY} * {DAY} - unnest(generate_series(0, 6)) * {DAY} AS start_us, payer, amount FROM txn)", select="SELECT start_us, payer, CAST(sum(amount) AS BIGINT) AS paid, count(*) AS n FROM s GROUP BY ALL"))
def sliding(spark, d):
    return _final(spark, streams.sliding(streams.events(spark, _event_files(spark, d)), lateness="40 days"), ["start_us", "payer"])


@query(q(*E1D, wedge(0.0), select="SELECT src_id, dst_id, n, p_fwd, p_bwd, w FROM wedge"))
def join_shuffle_hash(spark, d):
    """Weights joined to the edges by hash tables after a shuffle."""
    e = _edges(spark, d)
    w = second_order.weights(second_order.pair_graph(e))
    return second_order.attach(e, w.hint("shuffle_hash")).select("src_id", "dst_id", "n", "p_fwd", "p_bwd", "w")


@query(q(EVENTS, select="SELECT acct, n, total FROM (SELECT DISTINCT payer AS acct FROM txn) a, LATERAL (SELECT count(*) AS n, CAST(sum(amount) AS BIGINT) AS total FROM txn WHERE payee = a.acct)"))
def join_lateral(spark, d):
    """What each payer receives, by a lateral join."""
    t = _e(spark, d)
    got = t.where(F.col("payee") == F.col("acct").outer()).select(F.count("*").alias("n"), F.sum("amount").alias("total"))
    return t.select(F.col("payer").alias("acct")).distinct().lateralJoin(got)


_RANKS = "rank() OVER w AS rank, dense_rank() OVER w AS dense, round(percent_rank() OVER w, 9) AS percent, round(cume_dist() OVER w, 9) AS cume, ntile(4) OVER o AS quarter"


@query(q(EVENTS, select=f"SELECT txn_id, {_RANKS} FROM txn WINDOW w AS (PARTITION BY payer ORDER BY amount), o AS (PARTITION BY payer ORDER BY us, txn_id)"))
def window_ranks(spark, d):
    """W2f: the ranking functions."""
    w, o = Window.partitionBy("payer").orderBy("amount"), Window.partitionBy("payer").orderBy("ts", "txn_id")
    long = lambda c: c.cast("long")
    return _e(spark, d).select(
        "txn_id", long(F.rank().over(w)).alias("rank"), long(F.dense_rank().over(w)).alias("dense"),
        F.round(F.percent_rank().over(w), 9).alias("percent"), F.round(F.cume_dist().over(w), 9).alias("cume"), long(F.ntile(4).over(o)).alias("quarter"),
    )


@query(q(EVENTS, select="SELECT txn_id, first_value(amount) OVER o AS first, last_value(amount) OVER o AS last, nth_value(amount, 2) OVER o AS second FROM txn WINDOW o AS (PARTITION BY payer ORDER BY us, txn_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)"))
def window_values(spark, d):
    """W3f: first, last and n-th value."""
    o = Window.partitionBy("payer").orderBy("ts", "txn_id").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return _e(spark, d).select("txn_id", F.first("amount").over(o).alias("first"), F.last("amount").over(o).alias("last"), F.nth_value("amount", 2).over(o).alias("second"))


@query(q(EVENTS, select="SELECT payer AS acct FROM txn INTERSECT ALL SELECT payee AS acct FROM txn"))
def set_intersect_all(spark, d):
    """O8."""
    t = _e(spark, d)
    return t.select(F.col("payer").alias("acct")).intersectAll(t.select(F.col("payee").alias("acct")))


@query(q(EVENTS, select="SELECT payer AS acct FROM txn EXCEPT SELECT payee AS acct FROM txn"))
def set_subtract(spark, d):
    """O9."""
    t = _e(spark, d)
    return t.select(F.col("payer").alias("acct")).subtract(t.select(F.col("payee").alias("acct")))


@query(q(EVENTS, select="""SELECT txn_id, '{"payer":' || payer || ',"to":' || payee || '}' AS doc, 'STRUCT<payer: BIGINT, to: BIGINT>' AS kind FROM txn"""))
def struct_and_json(spark, d):
    """Struct and JSON functions: withField, dropFields, to_json, schema_of_json."""
    x = F.struct("payer", "amount").withField("to", F.col("payee")).dropFields("amount")
    return _e(spark, d).select("txn_id", F.to_json(x).alias("doc"), F.schema_of_json(F.lit('{"payer": 1, "to": 2}')).alias("kind"))


_SESSION = f"g AS (SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY payer ORDER BY us) < {6 * HOUR} THEN 0 ELSE 1 END AS cut FROM txn), h AS (SELECT *, sum(cut) OVER (PARTITION BY payer ORDER BY us ROWS UNBOUNDED PRECEDING) AS spell FROM g)"


@query(q(EVENTS, _SESSION, select="SELECT min(us) AS start_us, payer, CAST(sum(amount) AS BIGINT) AS paid, count(*) AS n FROM h GROUP BY payer, spell"))
def session(spark, d):
    t = _e(spark, d)
    return t.groupBy(F.session_window("ts", "6 hours"), "payer").agg(F.sum("amount").alias("paid"), F.count("*").alias("n")).select(F.unix_micros("session_window.start").alias("start_us"), "payer", "paid", "n")


@query(q(EVENTS, select="SELECT count(*) AS n, count(DISTINCT txn_id) AS n_ids FROM txn"))
def dedupe_stream(spark, d):
    """Every event twice in, once out."""
    src = scratch_path(spark, "twice")
    e = spark.read.parquet(f"{d}/events.parquet")
    e.unionByName(e).coalesce(2).write.parquet(src)
    x = _drained(spark, streams.deduplicated(streams.events(spark, src), "40 days"))
    return x.agg(F.count("*").alias("n"), F.countDistinct("txn_id").alias("n_ids"))


@query(q(EVENTS, ACCT, select="SELECT segment, bank, count(*) AS n, CAST(sum(amount) AS BIGINT) AS paid FROM txn LEFT JOIN acct ON payer = acct GROUP BY ALL"))
def stream_static(spark, d):
    """T6."""
    x = _drained(spark, streams.enriched(streams.events(spark, _event_files(spark, d)), ledger.accounts(spark, d)))
    return x.groupBy("segment", "bank").agg(F.count("*").alias("n"), F.sum("amount").alias("paid"))


@query(q(EVENTS, "a AS (SELECT payee AS acct, amount AS m FROM txn UNION ALL SELECT payer, -amount FROM txn)", select="SELECT acct, count(*) AS n, CAST(sum(m) AS BIGINT) AS balance FROM a GROUP BY acct"))
def stateful_balance(spark, d):
    """T7."""
    return _final(spark, streams.balances(streams.events(spark, _event_files(spark, d))), ["acct"])


@query(q(*E1D, SEDGE, select="SELECT * FROM sedge"))
def stream_pair_counts(spark, d):
    """Additive pair counts from micro-batches."""
    path, mark = scratch_path(spark, "stream-pairs"), scratch_path(spark, "mark")
    st = streams.temporal_edges(streams.events(spark, _event_files(spark, d), 1), timedelta(days=1), "40 days")
    with _state_width(spark):
        streams.pair_counts(st, path, mark).awaitTermination()
    return store.read_pairs(spark, path)


# ---- whole runs ---------------------------------------------------------------------------------------

@query(None)
def pipeline_cases(spark, d):
    """Ledger to cases on E6h."""
    return pipeline.run(spark, d, config.E6h)["flagged"].where("suspicious").select("comm_id", "n_txn", "n_acct", "dispensed", "sunk", "max_flow")


@query(None)
def synth_planted(spark, d):
    """planted flows and the community each lies in; the hub goes first."""
    t = prep.drop_hubs(ledger.clean(ledger.synth(spark, 2000)), k=1)
    w = second_order.weigh_and_prune(temporal.build(t, timedelta(days=1)), 0.5)
    m = community.detect(w)
    return t.where("channel <> 'noise'").join(m, "txn_id").groupBy("channel").agg(F.countDistinct("comm_id").alias("n_communities"), F.count("*").alias("n_txn"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return dict(_QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(_SQL)
