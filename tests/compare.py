"""Rows of Spark and of DuckDB in one comparable form."""

import duckdb

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def database(sf: str):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"create view {t} as select * from '{sf}/{t}.parquet'")
    return con


def plain(v):
    if v is None or v != v:
        return "~"
    if isinstance(v, bool):
        return str(v)
    if isinstance(v, float):
        return f"{v:.10g}"
    return str(v)


def rows(df) -> list:
    names = sorted(df.columns)
    return sorted(tuple(plain(r[c]) for c in names) for r in df.collect())


def expected(con, sql: str) -> list:
    r = con.sql(sql)
    order = [r.columns.index(c) for c in sorted(r.columns)]
    return sorted(tuple(plain(x[i]) for i in order) for x in r.fetchall())
