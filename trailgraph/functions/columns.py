"""Column helpers (2.5, scalar functions) and the UDF surface."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T


def pair_label(a: str, b: str) -> Column:
    return F.concat_ws("->", F.col(a).cast("string"), F.col(b).cast("string"))


def pseudonym(acct: str, salt: str = "trail") -> Column:
    """An account's stand-in for exports."""
    return F.substring(F.sha2(F.concat(F.lit(salt + ":"), F.col(acct).cast("string")), 256), 1, 16)


def has_bank(mask: str, bank: str) -> Column:
    """Bit test of a bank set."""
    return F.shiftright(F.col(mask), 0).bitwiseAND(F.expr(f"shiftleft(1, {bank})")) != 0


def bucketed(value: Column, step: float) -> Column:
    return F.floor(value / F.lit(step))


@F.pandas_udf(T.DoubleType())
def median_hold(gap: pd.Series) -> float:
    """A grouped aggregate."""
    return float(gap.median()) if len(gap) else float("nan")


@F.pandas_udf(T.StringType())
def mask_account(acct: pd.Series) -> pd.Series:
    """U4: all but the last two digits starred."""
    return acct.map(lambda x: None if x is None else "*" * max(0, len(x) - 2) + x[-2:])


@F.udtf(returnType=T.StructType([T.StructField("depth", T.IntegerType()), T.StructField("node", T.LongType())]))
class Reach:
    """Nodes within ``hops`` of a start, over an adjacency list packed as "a:b,c;b:d"."""

    def eval(self, start: int, packed: str, hops: int) -> Iterator[tuple]:
        out = {int(k): [int(x) for x in v.split(",") if x] for k, v in (p.split(":") for p in (packed or "").split(";") if p)}
        seen, edge = {start}, [start]
        for depth in range(1, hops + 1):
            edge = sorted({y for x in edge for y in out.get(x, ()) if y not in seen})
            seen.update(edge)
            for y in edge:
                yield depth, y
