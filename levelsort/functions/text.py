"""String primitives as column expressions: common prefixes, sentinels, fingerprints."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

FINGERPRINT_SPACE = 1 << 40


def lcp(a: Column, b: Column) -> Column:
    """Characters that a and b share at their start; null if either is null.

    Equal prefixes are monotone, so their length is found by halving steps from the largest power of two within the
    shorter string: no bound on the length, and few steps for short strings.
    """
    shorter = F.least(F.length(a), F.length(b))
    top = F.floor(F.log2(F.greatest(shorter, F.lit(1)))).cast("int")
    steps = F.transform(F.sequence(top, F.lit(0), F.lit(-1)), lambda i: F.pow(F.lit(2), i).cast("int"))
    grow = lambda acc, t: acc + F.when((acc + t <= shorter) & (F.left(a, acc + t) == F.left(b, acc + t)), t).otherwise(F.lit(0))
    return F.when(a.isNull() | b.isNull(), F.lit(None).cast("int")).otherwise(F.aggregate(steps, F.lit(0), grow))


def lcp_sql(inner: str, a: str = "s", b: str = "t", out: str = "h", max_len: int = 1 << 24) -> str:
    """The same search as nested DuckDB selects around ``inner``; strings of up to 2 ``max_len`` characters."""
    q = f"SELECT *, 0 AS {out} FROM ({inner})"
    step = 1 << max(0, (max_len - 1).bit_length())
    while step:
        n = f"{out} + {step}"
        q = f"SELECT * REPLACE (CAST(CASE WHEN {b} IS NULL THEN NULL WHEN {n} <= least(length({a}), length({b})) AND left({a}, {n}) = left({b}, {n}) THEN {n} ELSE {out} END AS INT) AS {out}) FROM ({q})"
        step //= 2
    return q


@F.pandas_udf(T.IntegerType())
def lcp_bytes(a: pd.Series, b: pd.Series) -> pd.Series:
    """Common prefix in bytes of the UTF-8 forms (byte mode), for very long strings."""
    import os

    return pd.Series([len(os.path.commonprefix([x.encode(), y.encode()])) if x is not None and y is not None else None for x, y in zip(a, b, strict=True)], dtype="Int32")


def fingerprint(s: Column, d: Column, m: int = FINGERPRINT_SPACE, seed: int = 0) -> Column:
    """Slot in [0, m) of the d-prefix with its sentinel: equal for equal padded prefixes."""
    text = F.concat(F.least(F.length(s) + 1, d).cast("string"), F.lit(":"), F.left(s, d))
    text = F.concat(F.lit(f"{seed}:"), text) if seed else text
    return F.pmod(F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("bigint"), F.lit(m))


def fingerprint_sql(s: str, d: str, m: int = FINGERPRINT_SPACE) -> str:
    return f"(('0x' || substr(md5(CAST(least(length({s}) + 1, {d}) AS VARCHAR) || ':' || left({s}, {d})), 1, 15))::BIGINT % {m})"


def common_prefix(s: Column) -> Column:
    """Aggregate: the longest common prefix of a group, which its least and greatest string share."""
    return F.left(F.min(s), lcp(F.min(s), F.max(s)))


@F.udtf(returnType="d int, prefix string")
class DoublingPrefixes:
    """Rows (d, prefix) at lengths 4, 8, ... until the whole string is covered."""

    def eval(self, s: str) -> Iterator[tuple[int, str]]:
        d = 4
        while s is not None:
            yield d, s[:d]
            if d > len(s):
                return
            d *= 2


def register(spark: SparkSession) -> None:
    """SQL names: lcp_bytes(a, b), doubling_prefixes(s), and lcp(a, b) as a SQL function over the built-in ones."""
    spark.udf.register("lcp_bytes", lcp_bytes)
    spark.sql("""CREATE OR REPLACE TEMPORARY FUNCTION lcp(a STRING, b STRING) RETURNS INT RETURN
        CASE WHEN a IS NOT NULL AND b IS NOT NULL THEN aggregate(
            transform(sequence(CAST(floor(log2(greatest(least(length(a), length(b)), 1))) AS INT), 0, -1), i -> CAST(pow(2, i) AS INT)), 0,
            (acc, t) -> acc + IF(acc + t <= least(length(a), length(b)) AND left(a, acc + t) = left(b, acc + t), t, 0)) END""")
    spark.udtf.register("doubling_prefixes", DoublingPrefixes)
