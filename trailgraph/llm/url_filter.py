"""Operator 6 [native]: URL filter with redirect equivalence.

Rules (verdict, host, path) fit a host with all its subdomains and every path that starts with theirs;
the longest rule that fits decides. A page that no rule fits takes over the decision of its aliases:
pages joined by redirect (meta refresh) and canonical-link edges, or that share a normalised URL, form
one component. In a component an explicit allow goes before an explicit block; without either the
page is allowed.

Defined cases: null url, or one without ``://``: empty host and path, no rule, no edge, allow. Null
html: no edge. Repeated pages are judged alike. Empty table: no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from trailgraph.functions.runtime import fresh, let, materialize, row_hashes
from trailgraph.operators.components import wcc

LOWER = ("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
RULES = (("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/"))
INLINE_RULES = 64

_CANONICAL = r"""(?is)<link\b(?=[^>]*\brel\s*=\s*["']?\s*canonical\b)[^>]*?\bhref\s*=\s*["']?([^"'\s>]+)"""
_REFRESH = r"""(?is)<meta\b(?=[^>]*\bhttp-equiv\s*=\s*["']?\s*refresh\b)[^>]*?\bcontent\s*=\s*["'][^"'>]*?url\s*=\s*["']?([^"'\s>]+)"""


def _rest(url: Column) -> Column:
    at = F.instr(url, "://")
    return F.when(at > 0, F.substring(url, at + 3, F.length(url))).otherwise(F.lit(""))


def host_of(url: Column) -> Column:
    return F.coalesce(F.translate(F.regexp_extract(_rest(url), r"^[^/?#]*", 0), *LOWER), F.lit(""))


def path_of(url: Column) -> Column:
    return F.coalesce(F.regexp_extract(_rest(url), r"^[^/?#]*([^?#]*)", 1), F.lit(""))


def node_of(url: Column) -> Column:
    """What names a resource: host, path and query; null where there is no host."""
    host = host_of(url)
    query = F.regexp_extract(_rest(url), r"^[^?#]*(\?[^#]*)?", 1)
    return F.when(host != "", F.concat(host, F.when(path_of(url) == "", F.lit("/")).otherwise(path_of(url)), query))


def resolve(base: Column, link: Column) -> Column:
    """An absolute URL for ``link`` found in the page ``base``."""
    scheme = F.regexp_extract(base, r"^[^:/?#]+", 0)
    folder = F.regexp_extract(path_of(base), r"^.*/", 0)
    return (
        F.when(link.contains("://"), link)
        .when(link.startswith("//"), F.concat(scheme, F.lit(":"), link))
        .when(link.startswith("/"), F.concat(scheme, F.lit("://"), host_of(base), link))
        .otherwise(F.concat(scheme, F.lit("://"), host_of(base), F.when(folder == "", F.lit("/")).otherwise(folder), link))
    )


def matching_rule(host: Column, path: Column, rules=RULES) -> Column:
    """struct(size, rule, verdict) of the longest rule that fits, else null; for a list of rules that an expression can hold."""
    fits = [
        F.when(((host == h) | host.endswith("." + h)) & path.startswith(p), F.struct(F.lit(len(h + p)).alias("size"), F.lit(h + p).alias("rule"), F.lit(v).alias("verdict")))
        for v, h, p in rules
    ]
    return F.array_max(F.array(*fits)) if fits else F.lit(None).cast("struct<size:int,rule:string,verdict:string>")


def with_rule(rows: DataFrame, rules=RULES) -> DataFrame:
    """``rows`` (host, path, ...) with the struct ``m`` of the longest rule that fits, or null.

    More than ``INLINE_RULES`` rules are a table that meets every host by the host's suffixes.
    """
    if len(rules) <= INLINE_RULES:
        return rows.withColumn("m", matching_rule(F.col("host"), F.col("path"), rules))
    table = rows.sparkSession.createDataFrame([(h, p, len(h + p), h + p, v) for v, h, p in rules], "rh string, rp string, size int, rule string, verdict string")
    labels = F.split("h", r"\.")
    suffixes = F.transform(F.sequence(F.lit(1), F.size(labels)), lambda i: F.array_join(F.slice(labels, i, F.size(labels)), "."))
    asked = rows.select(F.col("host").alias("h"), F.col("path").alias("p")).distinct()
    met = asked.withColumn("rh", F.explode(suffixes)).join(table, "rh")
    best = met.where(F.col("p").startswith(F.col("rp"))).groupBy("h", "p").agg(F.max(F.struct("size", "rule", "verdict")).alias("m"))
    return rows.join(best, (F.col("host") == F.col("h")) & (F.col("path") == F.col("p")), "left").drop("h", "p")


def alias_edges(pages: DataFrame, url: str = "url", html: str = "html") -> DataFrame:
    """(src, dst) between the nodes of pages and of what they redirect to or name as canonical."""
    u = F.col(f"`{url}`")
    links = F.filter(F.array(*[F.regexp_extract(F.col(f"`{html}`"), p, 1) for p in (_CANONICAL, _REFRESH)]), lambda x: x != "")
    found = pages.where(F.col(f"`{html}`").isNotNull()).select(u.alias("u"), F.explode(links).alias("l"))
    pairs = found.select(let(F.col("u"), node_of).alias("src"), let(resolve(F.col("u"), F.replace("l", F.lit("&amp;"), F.lit("&"))), node_of).alias("dst"))
    return pairs.where("src <> dst")


def _judged(pages: DataFrame, names: list[Column], rules, url: str, html: str) -> DataFrame:
    """The columns ``names`` with host, path, m, cv and verdict of every page."""
    u = F.col(f"`{url}`")
    rows = with_rule(pages.select(*names, host_of(u).alias("host"), path_of(u).alias("path"), node_of(u).alias("node")), rules)
    edges, _ = materialize(alias_edges(pages, url, html), "alias")
    labels = wcc(edges)
    decided = rows.where("m is not null and node is not null").select("node", F.col("m.verdict").alias("v")).groupBy("node").agg(F.min("v").alias("v"))  # allow sorts before block
    tv = F.concat(F.lit("http://"), F.col("node"))
    targets = edges.select(F.col("dst").alias("node")).distinct().select("node", host_of(tv).alias("host"), path_of(tv).alias("path"))
    aimed = with_rule(targets, rules).select("node", F.col("m.verdict").alias("v")).where("v is not null")
    known = decided.union(aimed).groupBy("node").agg(F.min("v").alias("v"))
    by_component = known.join(labels, "node").groupBy("component").agg(F.min("v").alias("cv"))
    by_node = labels.join(by_component, "component").select("node", "cv")
    own = decided.join(by_node, "node", "left_anti").select("node", F.col("v").alias("cv"))
    x = rows.join(by_node.union(own), "node", "left")
    return x.withColumn("verdict", F.coalesce(F.col("m.verdict"), F.col("cv"), F.lit("allow")))


def judge(pages: DataFrame, rules=RULES, id_col: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """page_id, host, path, rule, verdict, component_verdict (null where the page has no alias that a rule fits)."""
    x = _judged(pages, [F.col(f"`{id_col}`").alias("page_id")], rules, url, html)
    return x.select("page_id", "host", "path", F.col("m.rule").alias("rule"), "verdict", F.col("cv").alias("component_verdict"))


def allowed(pages: DataFrame, rules=RULES, id_col: str = "page_id", url: str = "url", html: str = "html") -> DataFrame:
    """The pages that are not blocked, with all their columns; rows are told apart by all of them, not by id."""
    k1, k2 = row_hashes(pages)
    kept = _judged(pages, [k1.alias("k1"), k2.alias("k2")], rules, url, html).where("verdict = 'allow'").select("k1", "k2").distinct()
    a, b = fresh(pages, "__k1"), fresh(pages, "__k2")
    mine = pages.select("*", k1.alias(a), k2.alias(b))
    return mine.join(kept, (F.col(a) == F.col("k1")) & (F.col(b) == F.col("k2")), "left_semi").drop(a, b)
