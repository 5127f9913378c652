"""Disjoint communities of payments.

The edges are split into weakly connected components first; no community with positive gains spans two.
Components of up to ``task_limit`` edges are dealt to tasks in packs and solved by the in-memory
kernel; larger ones go through a distributed engine. m is that of the whole window (A25).
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from trailgraph.functions.runtime import materialize
from trailgraph.operators import leiden_kernel
from trailgraph.operators.components import wcc_by

TASK_LIMIT = 200_000
PACK = 50_000


def windowed(edges: DataFrame, window: str, assign: str = "both") -> DataFrame:
    """Edges with ``window_start``: that of the source payment; ``both`` keeps edges that end in it too."""
    x = edges.withColumn("window_start", F.window("t_src", window)["start"])
    if assign == "both":
        x = x.where(F.window("t_dst", window)["start"] == F.col("window_start"))
    return x


def _weight(weight: str | None) -> Column:
    return F.lit(1.0) if weight is None else F.col(weight).cast("double")


def detect(edges: DataFrame, weight: str | None = "w", quality: str = "modularity", resolution: float = 1.0, max_comm_size: int | None = None, window: str | None = None, assign: str = "both", seed: int = 42, engine: str = "auto", directed: bool = True, task_limit: int = TASK_LIMIT, m_scope: str = "window") -> DataFrame:
    """MEMBER(window_start, comm_id, txn_id): comm_id is the least txn_id of the community."""
    x = windowed(edges, window, assign) if window else edges.withColumn("window_start", F.lit(None).cast("timestamp"))
    x = x.select("window_start", "src_id", "dst_id", _weight(weight).alias("w"))
    x = x.withColumn("u", F.coalesce(F.unix_micros("window_start"), F.lit(-1).cast("long")))
    labels = wcc_by(x, "u", "src_id", "dst_id").withColumnRenamed("node", "src_id")
    x = x.join(labels, ["u", "src_id"]).select("window_start", "u", "component", "src_id", "dst_id", "w")
    per = ["u", "component"] if m_scope == "component" else ["u"]
    mass = x.groupBy(*per).agg(F.sum("w").alias("m"))
    sizes = x.groupBy("u", "component").agg(F.count("*").alias("n_edges")).join(mass, per)
    routed, _ = materialize(x.join(sizes, ["u", "component"]), "routed")
    kernel = dict(resolution=resolution, max_comm_size=max_comm_size, seed=seed, quality=quality, directed=directed)
    small = routed if engine == "kernel" else routed.where(F.lit(engine != "distributed") & (F.col("n_edges") <= task_limit))
    parts = []
    if engine != "distributed":
        parts.append(_by_kernel(small, kernel))
    if engine != "kernel":
        large = routed.where(F.lit(engine == "distributed") | (F.col("n_edges") > task_limit))
        if not large.isEmpty():
            parts.append(_distributed(large, kernel, task_limit))
    out = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
    return out.select(F.when(F.col("u") >= 0, F.timestamp_micros("u")).alias("window_start"), "comm_id", "txn_id")


_APART = 10_000  # edges from which each visiting order of a component is a group of its own


def _by_kernel(edges: DataFrame, kernel: dict) -> DataFrame:
    """Components packed by hash into groups of about ``PACK`` edges, solved one by one inside.

    The visiting orders of components over ``_APART`` edges are dealt to tasks one by one, and the best labelling stays, as in the
    kernel itself. Where ``edges`` has ``n_src`` and ``n_dst``, its nodes stand for so many payments.
    """
    total = edges.count()
    packs = max(int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions")), total // PACK + 1)
    sizes = ["n_src", "n_dst"] if "n_src" in edges.columns else []
    key = ["u", "component"]
    apart = edges.groupBy(*key).agg(F.count("*").alias("n")).where(F.lit(kernel["quality"] == "modularity") & (F.col("n") > _APART)).select(*key)
    cols = [*key, "src_id", "dst_id", "w", "m", *sizes]
    few = edges.join(F.broadcast(apart), key, "left_anti").select(*cols, F.lit(-1).alias("start"))
    many = edges.join(F.broadcast(apart), key, "left_semi").select(*cols, F.explode(F.array(*map(F.lit, range(leiden_kernel.RESTARTS)))).alias("start"))

    def solve(pdf: pd.DataFrame) -> pd.DataFrame:
        out = []
        for (u, component, start), g in pdf.sort_values([*key, "start", "src_id", "dst_id"]).groupby([*key, "start"], sort=False):
            size = {**dict(zip(g["src_id"], g["n_src"])), **dict(zip(g["dst_id"], g["n_dst"]))} if sizes else None
            graph, rest = (g["src_id"].tolist(), g["dst_id"].tolist(), g["w"].tolist()), kernel | {"m": float(g["m"].iloc[0]), "size": size}
            worth, got = (0.0, leiden_kernel.run(*graph, **rest)) if start < 0 else leiden_kernel.one_start(*graph, **rest | {"seed": kernel["seed"] + start})
            out.append(pd.DataFrame({"u": u, "component": component, "start": start, "worth": worth, "comm_id": list(got.values()), "txn_id": list(got)}))
        return pd.concat(out) if out else pd.DataFrame({c: [] for c in ("u", "component", "start", "worth", "comm_id", "txn_id")}, dtype="int64")

    kind = "u long, component long, start int, worth double, comm_id long, txn_id long"
    packed = few.withColumn("pack", F.pmod(F.xxhash64(*key), F.lit(packs)))
    found = packed.groupBy("pack").applyInPandas(solve, kind).select("u", "comm_id", "txn_id")
    if apart.isEmpty():
        return found
    tried, _ = materialize(many.groupBy(*key, "start").applyInPandas(solve, kind), "starts")
    best = tried.groupBy(*key).agg(F.max(F.struct("worth", (-F.col("start")).alias("start"))).alias("best")).select(*key, (-F.col("best.start")).alias("start"))
    return found.unionByName(tried.join(F.broadcast(best), [*key, "start"]).select("u", "comm_id", "txn_id"))


def _distributed(edges: DataFrame, kernel: dict, task_limit: int) -> DataFrame:
    """M11d: levels of local moving, refinement and contraction until each component fits a task, or no two nodes gain by merging.

    In a level every node points to the partner it gains most with, and what points to one place is dealt to one pack. Packs are moved
    and refined with the strengths of the whole graph; the parts, which are connected, are the nodes of the next level. Two
    nodes that are each other's best share a pack, or, where more than ``PACK`` pairs point to one place, do so by the hash of some level. Undirected weights count both ways, as in the kernel.
    """
    base = edges.select("u", "component", "src_id", "dst_id", "w", "m")
    if not kernel["directed"]:
        back = base.select("u", "component", F.col("dst_id").alias("src_id"), F.col("src_id").alias("dst_id"), "w", "m")
        base = base.unionByName(back).withColumn("m", 2 * F.col("m"))
    kernel = kernel | {"directed": True}
    one = lambda a, o, i: base.select("u", "component", F.col(a).alias("id"), o.alias("o"), i.alias("i"), "m")
    both = one("src_id", F.col("w"), F.lit(0.0)).unionByName(one("dst_id", F.lit(0.0), F.col("w")))
    nodes, _ = materialize(both.groupBy("u", "id").agg(*_summed(F.lit(1).cast("long"))), "nodes")
    home, g, level = nodes.select("u", "id", F.col("id").alias("top")), base, 0
    while True:
        parts = _level(g, nodes, kernel, level)
        if parts is None:
            break
        level += 1
        home, _ = materialize(_renamed(home, parts, "top"), "home")
        nodes, _ = materialize(_renamed(nodes, parts, "id").groupBy("u", "id").agg(*_summed(F.sum("size"))), "nodes")
        after = _renamed(_renamed(g, parts, "src_id"), parts, "dst_id").groupBy("u", "component", "src_id", "dst_id")
        g, _ = materialize(after.agg(F.sum("w").alias("w"), F.first("m").alias("m")), "level")
        if g.groupBy("u", "component").count().where(F.col("count") > task_limit).isEmpty():
            break
    sized = lambda x, side: x.join(nodes.select("u", F.col("id").alias(f"{side}_id"), F.col("size").alias(f"n_{side}")), ["u", f"{side}_id"])
    many = g.groupBy("u", "component").agg(F.count("*").alias("n_edges")).where(F.col("n_edges") > task_limit).select("u", "component")
    labels = _by_kernel(sized(sized(g.join(many, ["u", "component"], "left_anti"), "src"), "dst"), kernel)
    labels = labels.unionByName(nodes.join(many, ["u", "component"], "left_semi").select("u", F.col("id").alias("comm_id"), F.col("id").alias("txn_id")))
    found = home.join(labels.withColumnRenamed("txn_id", "top"), ["u", "top"]).select("u", "comm_id", "id")
    least = found.groupBy("u", "comm_id").agg(F.min("id").alias("least"))
    return found.join(least, ["u", "comm_id"]).select("u", F.col("least").alias("comm_id"), F.col("id").alias("txn_id"))


def _summed(size: Column) -> list[Column]:
    return [F.first("component").alias("component"), F.first("m").alias("m"), F.sum("o").alias("o"), F.sum("i").alias("i"), size.alias("size")]


def _renamed(x: DataFrame, parts: DataFrame, c: str) -> DataFrame:
    """Node ids in column ``c`` replaced by their parts; nodes without one keep theirs."""
    to = parts.select(F.col("u").alias("pu"), F.col("id").alias("pid"), "part")
    return x.join(to, (F.col("u") == F.col("pu")) & (F.col(c) == F.col("pid")), "left").withColumn(c, F.coalesce("part", c)).drop("pu", "pid", "part")


_HOPS = 4  # from a node to its best partner, to that one's, and so on


def _level(g: DataFrame, nodes: DataFrame, kernel: dict, level: int) -> DataFrame | None:
    """(u, id, part) of the nodes that take part in a level; None if no two nodes gain by merging."""
    cap, quality, resolution, seed = kernel["max_comm_size"], kernel["quality"], kernel["resolution"], kernel["seed"]
    end = lambda x: nodes.select("u", F.col("id").alias(x), *[F.col(k).alias(f"{x}_{k}") for k in ("o", "i", "size")], *(["m"] if x == "a" else []))
    ties = g.where("src_id <> dst_id").groupBy("u", F.least("src_id", "dst_id").alias("a"), F.greatest("src_id", "dst_id").alias("b")).agg(F.sum("w").alias("w"))
    x = ties.join(end("a"), ["u", "a"]).join(end("b"), ["u", "b"])
    cost = F.col("a_size") * F.col("b_size") if quality == "cpm" else (F.col("a_o") * F.col("b_i") + F.col("a_i") * F.col("b_o")) / F.col("m")
    x = x.withColumn("gain", F.col("w") - resolution * cost).where("gain > 1e-9")
    if cap is not None:
        x = x.where(F.col("a_size") + F.col("b_size") <= cap)
    one = lambda a, b: F.struct(F.col(a).alias("id"), F.struct("gain", (-F.col(b)).alias("no")).alias("best"))
    best = x.select("u", "gain", F.explode(F.array(one("a", "b"), one("b", "a"))).alias("x")).groupBy("u", "x.id").agg(F.max("x.best").alias("best"), F.count("*").alias("load"))
    best, _ = materialize(best.select("u", "id", (-F.col("best.no")).alias("to"), "load"), "best")
    total = best.agg(F.sum("load")).first()[0]
    if not total:
        return None
    packs = max(int(g.sparkSession.conf.get("spark.sql.shuffle.partitions")), total // PACK + 1)
    at, hop = best.withColumn("at", F.col("id")), best.select("u", F.col("id").alias("at"), F.col("to").alias("next"))
    for _ in range(_HOPS):
        at = at.join(hop, ["u", "at"]).select("u", "id", "load", F.col("at").alias("last"), F.col("next").alias("at"))
    at = at.select("u", "id", "load", F.least("at", "last").alias("root"))  # two nodes that are each other's best end every way
    heavy = at.groupBy("u", "root").agg(F.sum("load").alias("s")).where(F.col("s") > PACK).select("u", "root", F.ceil(F.col("s") / PACK).alias("k"))
    dealt = F.pmod(F.xxhash64(F.lit(seed + level), "id"), F.coalesce("k", F.lit(1)))
    at, _ = materialize(at.join(heavy, ["u", "root"], "left").select("u", "id", F.pmod(F.xxhash64(F.lit(seed + level), "u", "root", dealt), F.lit(packs)).alias("pack")), "packs")
    side = lambda c, p: at.select("u", F.col("id").alias(c), F.col("pack").alias(p))
    inside = g.where("src_id <> dst_id").join(side("src_id", "pack"), ["u", "src_id"]).join(side("dst_id", "p"), ["u", "dst_id"]).where("pack = p")
    inside = inside.select("pack", "u", "m", "src_id", "dst_id", "w")
    mine = nodes.join(at, ["u", "id"]).select("pack", "u", "m", "id", "o", "i", "size")

    def solve(n: pd.DataFrame, e: pd.DataFrame) -> pd.DataFrame:
        out, links = [], dict(list(e.sort_values(["src_id", "dst_id"]).groupby(["u", "m"])))
        for k, x in n.sort_values("id").groupby(["u", "m"]):
            if k in links:
                part = leiden_kernel.parts(x, links[k], float(k[1]), resolution, cap, seed + level, quality)
                out.append(pd.DataFrame({"u": k[0], "id": x["id"].to_numpy(), "part": part}))
        return pd.concat(out) if out else pd.DataFrame({"u": [], "id": [], "part": []}, dtype="int64")

    met = mine.groupBy("pack").cogroup(inside.groupBy("pack")).applyInPandas(solve, "u long, id long, part long")
    return materialize(met, "parts")[0]


def modularity(edges: DataFrame, member: DataFrame, weight: str = "w", resolution: float = 1.0, by: str | None = None) -> DataFrame:
    """Directed modularity of a labelling (txn_id, comm_id), per ``by`` or in one row; m is that of all its edges."""
    k = [by] if by else []
    s, d = member.select(*k, F.col("txn_id").alias("src_id"), F.col("comm_id").alias("cs")), member.select(*k, F.col("txn_id").alias("dst_id"), F.col("comm_id").alias("cd"))
    e = edges.select(*k, "src_id", "dst_id", F.col(weight).cast("double").alias("w")).join(s, [*k, "src_id"]).join(d, [*k, "dst_id"])
    rows = e.select(*k, F.explode(F.array(F.struct(F.col("cs").alias("c"), F.col("w").alias("o"), F.lit(0.0).alias("i"), F.when(F.col("cs") == F.col("cd"), F.col("w")).otherwise(0.0).alias("inside")), F.struct(F.col("cd").alias("c"), F.lit(0.0).alias("o"), F.col("w").alias("i"), F.lit(0.0).alias("inside")))).alias("x"))
    per = rows.groupBy(*k, F.col("x.c").alias("c")).agg(F.sum("x.o").alias("o"), F.sum("x.i").alias("i"), F.sum("x.inside").alias("inside"))
    m = F.sum("o")
    return per.groupBy(*k).agg((F.sum("inside") / m - resolution * F.sum(F.col("o") * F.col("i")) / m / m).alias("modularity"))


def recurring_accounts(member: DataFrame, txn: DataFrame, r: int = 2, max_pairs_flow: int = 200) -> DataFrame:
    """(acct, acct2, n_windows) of accounts that share a flow in r windows or more.

    Accounts that are in just the same flows form a class, and pairs are counted between classes; only those with r windows are
    spread to their accounts, after the last shuffle. The classes of a flow are dealt to blocks of about ``max_pairs_flow``; pairs of
    blocks are the join keys, so a flow of any size gives all its pairs and none is one task's.
    """
    both = member.join(txn, "txn_id").select("window_start", "comm_id", F.explode(F.array("payer", "payee")).alias("acct")).where("acct is not null and window_start is not null and comm_id is not null")
    flows = both.groupBy("acct").agg(F.sort_array(F.collect_set(F.struct("window_start", "comm_id"))).alias("flows"))
    flows = flows.withColumn("n_windows", F.size(F.array_distinct("flows.window_start")).cast("long")).where(F.col("n_windows") >= r)
    classes = flows.groupBy("flows").agg(F.min("acct").alias("rep"), F.first("n_windows").alias("n_windows"), F.sort_array(F.collect_list("acct")).alias("accts"))
    classes, _ = materialize(classes, "account-classes")
    acc = classes.select(F.explode("flows").alias("f"), F.col("rep").alias("acct")).select("f.window_start", "f.comm_id", "acct")
    sizes = acc.groupBy("window_start", "comm_id").agg(F.ceil(F.count("*") / max_pairs_flow).alias("k"))
    dealt = acc.join(sizes, ["window_start", "comm_id"]).withColumn("i", F.pmod(F.xxhash64("acct"), F.col("k"))).withColumn("j", F.explode(F.expr("sequence(0L, k - 1)")))
    cells = dealt.select("window_start", "comm_id", F.least("i", "j").alias("u"), F.greatest("i", "j").alias("v"), "i", "acct")
    other = cells.select("window_start", "comm_id", "u", "v", F.col("i").alias("i2"), F.col("acct").alias("acct2"))
    met = cells.join(other, ["window_start", "comm_id", "u", "v"]).where("acct < acct2 and (u = v or i <> i2)")
    pairs = met.groupBy("acct", "acct2").agg(F.countDistinct("window_start").alias("n_windows")).where(F.col("n_windows") >= r)
    pairs = pairs.unionByName(classes.where(F.size("accts") > 1).select(F.col("rep").alias("acct"), F.col("rep").alias("acct2"), "n_windows"))
    parts = classes.select("rep", "accts", F.explode(F.expr(f"sequence(1, size(accts), {int(max_pairs_flow)})")).alias("at"))
    parts = parts.select("rep", F.slice("accts", F.col("at"), F.lit(int(max_pairs_flow))).alias("accts"))
    side = lambda k, v: parts.select(F.col("rep").alias(k), F.col("accts").alias(v))
    spread = pairs.join(side("acct", "xs"), "acct").join(side("acct2", "ys"), "acct2").select("n_windows", (F.col("acct") == F.col("acct2")).alias("own"), F.explode("xs").alias("x"), "ys")
    spread = spread.select("n_windows", "own", "x", F.explode("ys").alias("y")).where("not own or x < y")
    return spread.select(F.least("x", "y").alias("acct"), F.greatest("x", "y").alias("acct2"), "n_windows")


def recurring_communities(pairs: DataFrame, **kw) -> DataFrame:
    """Communities of accounts by how often they share a flow: MEMBER with accounts in place of payments."""
    edges = pairs.select(F.col("acct").alias("src_id"), F.col("acct2").alias("dst_id"), F.col("n_windows").alias("w"))
    return detect(edges, directed=False, **kw).select("comm_id", F.col("txn_id").alias("acct"))
