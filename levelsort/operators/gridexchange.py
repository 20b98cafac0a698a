"""Indirect exchange over a grid of lanes: a string goes digit by digit to its target, one hop per dimension.

A lane is read as a number in mixed radix, one digit per factor; hop i sets digit i to the target's. A lane then talks to
the lanes of one line of the grid per hop (sum of the factors less one each, instead of all lanes), and every string
moves once per hop.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from levelsort.staging import cut


def next_lane(here: Column, target: Column, factors: tuple[int, ...], hop: int) -> Column:
    """``here`` with the digit of ``hop`` (0-based) taken from ``target``."""
    stride = math.prod(factors[hop + 1 :])
    digit = lambda lane: F.pmod(F.floor(lane / stride), F.lit(factors[hop]))
    return (here + (digit(target) - digit(here)) * stride).cast("int")


def grid_exchange(rows: DataFrame, factors: tuple[int, ...], source: str = "sender", target: str = "target", text: str = "s") -> tuple[DataFrame, list[DataFrame]]:
    """(rows at their targets, per hop: src, dst, n, chars). Sources beyond the grid enter it at their number modulo its size."""
    lanes = math.prod(factors)
    state, hops = rows.withColumn("_here", F.pmod(F.col(source), F.lit(lanes)).cast("int")), []
    for hop in range(len(factors)):
        via = next_lane(F.col("_here"), F.col(target), factors, hop)
        moved = cut(state.withColumn("_via", via).repartitionById(lanes, F.col("_via")))
        hops.append(moved.groupBy(F.col("_here").alias("src"), F.col("_via").alias("dst")).agg(F.count("*").alias("n"), F.sum(F.length(text)).alias("chars")))
        state = moved.drop("_here").withColumnRenamed("_via", "_here")
    return state.drop("_here"), hops


def hop_volumes(hops: list[DataFrame]) -> DataFrame:
    """hop, src, dst, n, chars over all hops."""
    out = None
    for i, h in enumerate(hops, 1):
        one = h.select(F.lit(i).alias("hop"), "src", "dst", "n", "chars")
        out = one if out is None else out.unionByName(one)
    return out
