"""The layered-flow baseline - flows of a fixed number of layers k (k - 1 hops)."""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from trailgraph.functions.runtime import materialize
from trailgraph.operators import flows, risk
from trailgraph.operators.flows import KEYS


MOST_BANKS = 30


def _inner(pay: DataFrame, edges: DataFrame, keys) -> DataFrame:
    own = lambda c: pay.select(*keys, F.col("txn_id").alias(c))
    return edges.select("src_id", "dst_id").join(own("src_id"), "src_id").join(own("dst_id"), ["dst_id", *keys]).select(*keys, "src_id", "dst_id")


def _levels(start: DataFrame, inner: DataFrame, most: int, keys, frm: str, to: str, name: str) -> DataFrame:
    """(keys, txn_id, level): level i = i-th payment of some walk that begins in ``start``; each level is written once."""
    cur, _ = materialize(start.select(*keys, "txn_id").distinct(), "level")
    out = cur.withColumn(name, F.lit(1))
    for i in range(2, most + 1):
        step = cur.select(*keys, F.col("txn_id").alias(frm)).join(inner, [*keys, frm]).select(*keys, F.col(to).alias("txn_id")).distinct()
        cur, _ = materialize(step, "level")
        out = out.unionByName(cur.withColumn(name, F.lit(i)))
    return out


def parts(pay: DataFrame, edges: DataFrame, ks=(3, 4, 5), keys=KEYS) -> DataFrame:
    """B7 for several numbers of layers at once: the payments with ``k``, for each k that has a walk of k - 1 payments over them."""
    pay, _ = materialize(pay, "layered-pay")
    inner, _ = materialize(_inner(pay, edges, keys), "layered-edges")
    role, _ = materialize(flows.roles(pay, keys).select(*keys, "acct", "role"), "layered-roles")
    end = lambda side, r: pay.join(role.where(F.col("role") == r).select(*keys, F.col("acct").alias(side)), [*keys, side], "left_semi")
    fwd = _levels(end("payer", "dispense"), inner, max(ks) - 1, keys, "src_id", "dst_id", "i")
    bwd = _levels(end("payee", "sink"), inner, max(ks) - 1, keys, "dst_id", "src_id", "j")
    on = fwd.join(bwd, [*keys, "txn_id"]).select(*keys, "txn_id", (F.col("i") + F.col("j")).alias("k")).where(F.col("k").isin(*ks)).distinct()
    return materialize(pay.join(on, [*keys, "txn_id"]), "layered-parts")[0]


def restrict(pay: DataFrame, edges: DataFrame, k: int, keys=KEYS) -> DataFrame:
    """Payments of each flow on a walk of exactly k - 1 payments from a dispense to a sink account."""
    return parts(pay, edges, (k,), keys).select(*pay.columns)


def _swept(found: DataFrame, edges: DataFrame, threshold: int, keys) -> DataFrame:
    by = (*keys, "k")
    n = found.groupBy(*by).agg(F.countDistinct("txn_id").alias("n_txn"), F.size(F.array_union(F.collect_set("payer"), F.collect_set("payee"))).alias("n_acct"))
    return n.join(risk.temporal_max_flow(found, edges, keys=by), list(by)).select(*by, "n_txn", "n_acct", "max_flow", (F.col("max_flow") > threshold).alias("c3"))


def sweep(pay: DataFrame, edges: DataFrame, ks=(3, 4, 5), threshold: int = 500_000, keys=KEYS) -> DataFrame:
    """(keys, k, n_txn, n_acct, max_flow, c3) of each flow's part for each k; flows without such a part are left out."""
    return _swept(parts(pay, edges, ks, keys), edges, threshold, keys)


def split_loss(pay: DataFrame, edges: DataFrame, ks=(3, 4, 5), threshold: int = 500_000, keys=KEYS) -> DataFrame:
    """Per flow, C3 of the whole, numbers of ks that have a part and that pass, and accounts in no passing part."""
    whole = risk.temporal_max_flow(pay, edges, keys=keys).withColumn("c3_whole", F.col("max_flow") > threshold)
    acct = lambda p: p.select(*keys, F.explode(F.array("payer", "payee")).alias("acct")).distinct()
    found = parts(pay, edges, ks, keys)
    swept, _ = materialize(_swept(found, edges, threshold, keys), "layered-sweep")
    kept = acct(found.join(swept.where("c3").select(*keys, "k"), [*keys, "k"], "left_semi"))
    lost = acct(pay).join(kept, [*keys, "acct"], "left_anti").groupBy(*keys).agg(F.count("*").alias("n_lost"))
    per = swept.groupBy(*keys).agg(F.count("*").alias("n_ks"), F.count_if("c3").alias("n_flagged"))
    out = whole.join(per, list(keys), "left").join(lost, list(keys), "left")
    return out.select(*keys, "max_flow", "c3_whole", *[F.coalesce(n, F.lit(0)).alias(n) for n in ("n_ks", "n_flagged", "n_lost")])


def bank_subsets(banks: DataFrame) -> DataFrame:
    """(mask, n_banks) for every non-empty set of banks (column bank: 0, 1, ...).

    There are 2^n - 1 sets, so more than ``MOST_BANKS`` banks are refused rather than cut.
    """
    n = (banks.agg(F.max("bank")).first()[0] if banks.columns else None) or 0
    if n >= MOST_BANKS:
        raise ValueError(f"{n + 1} banks have more sets than can be listed; {MOST_BANKS} are the most")
    top = banks.agg(F.coalesce(F.max("bank") + 1, F.lit(0)).cast("int").alias("n")).where("n > 0")
    masks = top.select(F.explode(F.sequence(F.lit(1), F.expr("cast(shiftleft(1L, n) - 1 as int)"))).alias("mask"))
    return masks.select("mask", F.bit_count("mask").alias("n_banks"))


def partite(edges: DataFrame, acct: DataFrame, mask: int, k: int = 3) -> DataFrame:
    """Walks of k - 1 payments whose middle accounts all lie in the bank set; as arrays of payment ids."""
    inside = acct.where(F.col("bank").isNotNull() & (F.expr(f"shiftright({mask}, bank)") % 2 == 1)).select(F.col("acct").alias("b"))
    e = edges.join(inside, "b", "left_semi").select("src_id", "dst_id")
    cur = e.select(F.array("src_id", "dst_id").alias("ids"), F.col("dst_id").alias("end"))
    for _ in range(k - 3):
        cur = cur.join(e, F.col("end") == F.col("src_id")).select(F.concat("ids", F.array("dst_id")).alias("ids"), F.col("dst_id").alias("end"))
    return cur.select("ids")


def bank_set_flows(edges: DataFrame, acct: DataFrame) -> DataFrame:
    """B8 x B9 for k = 3 in one pass: (mask, n_banks, n_walks) of each bank set, from counts per bank."""
    banks = acct.select(F.col("acct").alias("b"), "bank")
    per = edges.join(banks, "b").groupBy("bank").agg(F.count("*").alias("n"))
    masks = bank_subsets(acct.select("bank").distinct())
    on = F.expr("shiftright(mask, bank) % 2 = 1")
    return masks.join(F.broadcast(per), on, "left").groupBy("mask", "n_banks").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_walks"))


def _peel(rows: list[tuple], leak: float) -> list[tuple[int, float]]:
    """Greedy removal: the account whose retained-minus-leaked flow is least goes first; the best average seen wins."""
    inn: dict[int, int] = {}
    out: dict[int, int] = {}
    near: dict[int, list] = {}
    for a, b, m in rows:
        out[a] = out.get(a, 0) + m
        inn[b] = inn.get(b, 0) + m
        near.setdefault(a, []).append((b, m, True))
        near.setdefault(b, []).append((a, m, False))
    score = {v: min(inn.get(v, 0), out.get(v, 0)) - leak * abs(inn.get(v, 0) - out.get(v, 0)) for v in near}
    heap = [(s, v) for v, s in score.items()]
    heapq.heapify(heap)
    gone, total, order = set(), sum(score.values()), []
    best, keep = total / max(1, len(near)), 0
    while heap:
        s, v = heapq.heappop(heap)
        if v in gone or s != score[v]:
            continue
        gone.add(v)
        order.append(v)
        total -= score[v]
        for u, m, to in near[v]:
            if u in gone:
                continue
            total -= score[u]
            if to:
                inn[u] -= m
            else:
                out[u] -= m
            score[u] = min(inn.get(u, 0), out.get(u, 0)) - leak * abs(inn.get(u, 0) - out.get(u, 0))
            total += score[u]
            heapq.heappush(heap, (score[u], u))
        left = len(near) - len(gone)
        if left and total / left > best:
            best, keep = total / left, len(order)
    return [(v, best) for v in sorted(set(near) - set(order[:keep]))]


def peel(pay: DataFrame, leak_penalty: float = 0.8, keys=KEYS) -> DataFrame:
    """Dense multipartite peeling within each flow: (keys, acct, density) of what is left."""
    kinds = dict(pay.dtypes)
    packed = pay.groupBy(*keys).agg(F.array_sort(F.collect_list(F.array("payer", "payee", "amount"))).alias("arcs"))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            for _, r in f.iterrows():
                got = _peel([tuple(map(int, x)) for x in r["arcs"]], leak_penalty)
                if got:
                    yield pd.DataFrame({**{k: [r[k]] * len(got) for k in keys}, "acct": [x for x, _ in got], "density": [float(x) for _, x in got]})

    return packed.mapInPandas(run, ", ".join(f"{k} {kinds[k]}" for k in keys) + ", acct long, density double")
