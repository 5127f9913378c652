"""DuckDB SQL that says the same as the engine, as pieces of WITH clauses."""

from __future__ import annotations

HOUR, DAY = 3_600_000_000, 86_400_000_000

EVENTS = """raw AS (SELECT event_id AS txn_id, epoch_us(ts) AS us, user_id * 2 AS payer, 2 * CAST(json_extract_string(props, '$.k') AS BIGINT) AS payee,
  CAST(round(value * 100) AS BIGINT) * 100 AS amount, event_type AS channel FROM events),
txn AS (SELECT * FROM raw WHERE payer <> payee AND amount > 0)"""

TRADE = """lines AS (SELECT *, row_number() OVER (PARTITION BY l_orderkey ORDER BY l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_returnflag, l_linestatus, l_shipdate) AS rn FROM lineitem),
j AS (SELECT l.*, o_custkey, o_orderdate, 2 * (l.l_orderkey * 100 + rn) AS id,
  CAST(round(l_extendedprice * 100) AS BIGINT) * (100 - CAST(round(l_discount * 100) AS BIGINT)) AS amount FROM lines l JOIN orders o ON l.l_orderkey = o.o_orderkey),
txn AS (SELECT * FROM (SELECT id AS txn_id, epoch_us(o_orderdate) AS us, o_custkey * 2 AS payer, l_suppkey * 2 + 1 AS payee, amount, 'purchase' AS channel FROM j
  UNION ALL SELECT id + 1, epoch_us(l_shipdate), l_suppkey * 2 + 1, o_custkey * 2, amount, 'refund' FROM j WHERE l_returnflag = 'R') WHERE amount > 0)"""

ACCT = """acct AS (SELECT x.acct, x.kind, x.segment, CAST(x.nation AS INTEGER) AS nation, CAST(n_regionkey AS INTEGER) AS bank FROM (
  SELECT c_custkey * 2 AS acct, 'customer' AS kind, c_mktsegment AS segment, c_nationkey AS nation FROM customer
  UNION ALL SELECT s_suppkey * 2 + 1, 'supplier', 'SUPPLIER', s_nationkey FROM supplier) x JOIN nation ON nation = n_nationkey)"""


def tedge(delta: int, txn: str = "txn", name: str = "tedge") -> str:
    return f"""{name} AS (SELECT s.txn_id AS src_id, d.txn_id AS dst_id, s.payer AS a, s.payee AS b, d.payee AS c, s.us AS us, d.us AS ud
  FROM {txn} s JOIN {txn} d ON s.payee = d.payer AND s.us < d.us AND d.us < s.us + {delta})"""


SEDGE = "sedge AS (SELECT a, b, c, count(*) AS n FROM tedge GROUP BY a, b, c)"
WTS = """tot AS (SELECT *, CAST(sum(n) OVER (PARTITION BY a, b) AS BIGINT) AS n_out, CAST(sum(n) OVER (PARTITION BY b, c) AS BIGINT) AS n_in FROM sedge),
wts AS (SELECT a, b, c, n, n / n_out AS p_fwd, n / n_in AS p_bwd, greatest(n / n_out, n / n_in) AS w FROM tot)"""


def wedge(theta: float = 0.5) -> str:
    return f"{SEDGE}, {WTS}, wedge AS (SELECT t.*, x.n, x.p_fwd, x.p_bwd, x.w FROM tedge t JOIN wts x USING (a, b, c) WHERE x.w >= {theta})"


WCC = """sym AS (SELECT src_id AS u, dst_id AS v FROM wedge UNION SELECT dst_id, src_id FROM wedge),
reach AS (SELECT DISTINCT u AS node, u AS l FROM sym UNION SELECT s.v, r.l FROM reach r JOIN sym s ON s.u = r.node),
member AS (SELECT node AS txn_id, min(l) AS comm_id FROM reach GROUP BY node)"""

PAY = "pay AS (SELECT m.comm_id, t.* FROM member m JOIN txn t USING (txn_id))"
ROLES = """sides AS (SELECT comm_id, payer AS acct, amount AS paid, CAST(NULL AS BIGINT) AS received FROM pay UNION ALL SELECT comm_id, payee, NULL, amount FROM pay),
per AS (SELECT comm_id, acct, CAST(coalesce(sum(paid), 0) AS BIGINT) AS paid, CAST(coalesce(sum(received), 0) AS BIGINT) AS received, count(paid) AS np, count(received) AS nr FROM sides GROUP BY comm_id, acct),
roles AS (SELECT comm_id, acct, CASE WHEN nr = 0 THEN 'dispense' WHEN np = 0 THEN 'sink' ELSE 'mid' END AS role, paid, received FROM per)"""
SUMMARY = """s1 AS (SELECT comm_id, count(*) AS n_txn, CAST(sum(amount) AS BIGINT) AS amount, min(us) AS first_us, max(us) AS last_us FROM pay GROUP BY comm_id),
s2 AS (SELECT comm_id, count(*) AS n_acct, count(*) FILTER (role = 'dispense') AS n_dispense, count(*) FILTER (role = 'sink') AS n_sink, count(*) FILTER (role = 'mid') AS n_mid,
  CAST(coalesce(sum(paid) FILTER (role = 'dispense'), 0) AS BIGINT) AS dispensed, CAST(coalesce(sum(received) FILTER (role = 'sink'), 0) AS BIGINT) AS sunk FROM roles GROUP BY comm_id),
summary AS (SELECT *, CASE WHEN dispensed > 0 THEN CAST(sunk * 100 AS DOUBLE) / CAST(dispensed AS DOUBLE) END AS sunk_pct FROM s1 JOIN s2 USING (comm_id))"""


def c1(quantifier: str = "all") -> str:
    ok = "bool_and(ok) AND bool_or(role = 'dispense') AND bool_or(role = 'sink')" if quantifier == "all" else "bool_or(role = 'dispense' AND ok) AND bool_or(role = 'sink' AND ok)"
    return f"""ends AS (SELECT r.comm_id, r.role, coalesce(a.segment IN ('HOUSEHOLD', 'MACHINERY', 'FURNITURE'), false) AS ok FROM roles r LEFT JOIN acct a USING (acct) WHERE role <> 'mid'),
c1 AS (SELECT s.comm_id, coalesce(x.c1, false) AS c1 FROM (SELECT DISTINCT comm_id FROM roles) s LEFT JOIN (SELECT comm_id, {ok} AS c1 FROM ends GROUP BY comm_id) x USING (comm_id))"""


def q(*parts: str, select: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(parts) + "\n" + select
