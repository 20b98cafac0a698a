"""Cost measures: messages, volume, balance from the recorded moves of a run; closed forms of the time bounds."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def messages(moves: list[DataFrame]) -> DataFrame:
    """Per level: messages, max_messages_per_lane, chars_total, chars_max_lane (received)."""
    rows = None
    for i, m in enumerate(moves, 1):
        pairs = m.groupBy("lane", "target").agg(F.sum("chars").alias("chars"))
        sent = pairs.groupBy("lane").agg(F.count("*").alias("c")).agg(F.max("c").alias("max_messages_per_lane"))
        got = pairs.groupBy("target").agg(F.sum("chars").alias("chars")).agg(F.max("chars").alias("chars_max_lane"))
        one = pairs.agg(F.count("*").alias("messages"), F.sum("chars").alias("chars_total")).crossJoin(sent).crossJoin(got).select(F.lit(i).alias("level"), "messages", "max_messages_per_lane", "chars_total", "chars_max_lane")
        rows = one if rows is None else rows.unionByName(one)
    return rows


def imbalance(rows: DataFrame, lanes: int) -> DataFrame:
    """strings and chars: max over mean per lane, empty lanes included."""
    per = rows.groupBy("lane").agg(F.count("*").alias("n"), F.sum(F.length("s")).alias("c"))
    return per.agg(F.round(F.max("n") * lanes / F.sum("n"), 6).alias("strings"), F.round(F.max("c") * lanes / F.sum("c"), 6).alias("chars"))


def imbalance_by_level(moves: list[DataFrame], lanes: int) -> DataFrame:
    """level, strings, chars: max over mean of what a lane holds after each level, empty lanes included."""
    rows = None
    for i, m in enumerate(moves, 1):
        per = m.groupBy("target").agg(F.sum("n").alias("n"), F.sum("chars").alias("c"))
        one = per.agg(F.round(F.max("n") * lanes / F.sum("n"), 6).alias("strings"), F.round(F.max("c") * lanes / F.sum("c"), 6).alias("chars")).select(F.lit(i).alias("level"), "strings", "chars")
        rows = one if rows is None else rows.unionByName(one)
    return rows


def overloaded(rows: DataFrame, lanes: int, budget: float = 1.5) -> DataFrame:
    """Lanes whose characters exceed ``budget`` times the mean: where a machine without spilling would fail."""
    per = rows.groupBy("lane").agg(F.sum(F.length("s")).alias("chars"))
    mean = per.agg((F.sum("chars") / lanes).alias("mean"))
    return per.crossJoin(F.broadcast(mean)).where(F.col("chars") > budget * F.col("mean")).select("lane", "chars")


def exchange_bound(r: float, h: float, alpha: float, beta: float) -> float:
    return alpha * r + beta * h


def bucket_bound(n: int, r: int, v: int, level: int) -> float:
    """Most strings of a bucket after ``level`` levels of string-based sampling (unique strings)."""
    return (1 + r / v) ** level * n / r**level


def padded(n: int, chars: int, p: int, k: int, r: int, l_max: int, l_min: int) -> tuple[float, float]:
    """Characters and strings with the slack that uneven splitting may add."""
    return chars + k * k * r * l_max * p, (l_max / max(1, l_min)) * (n + k * k * r * p)


def merge_sort_time(n: int, chars: int, d: int, p: int, k: int, l_max: int, sigma: int = 256, alpha: float = 1e-5, beta: float = 1e-9) -> dict[str, float]:
    """Terms of the merge sort's time: local sort, partitioning, exchange, merging (work units plus alpha-beta seconds)."""
    r, bits = p ** (1 / k), math.log2(sigma)
    lp = math.log2(max(2, p))
    n1, c1 = n + k * k * r * p, chars + k * k * r * l_max * p
    return {
        "local": n / p * math.log2(max(2, n)) + d / p, "merge": k * c1 / p + n1 / p * lp,
        "partition": k * (alpha * lp * lp + k * r * l_max * lp * (1 + beta * bits)), "exchange": k * exchange_bound(r, c1 / p * bits, alpha, beta),
    }


def doubling_time(n: int, d: int, d_max: int, p: int, k: int, sigma: int = 256, alpha: float = 1e-5, beta: float = 1e-9) -> dict[str, float]:
    """What prefix doubling adds, and the merge sort of the prefixes."""
    r, lp = p ** (1 / k), math.log2(max(2, p))
    extra = math.log2(max(2, d_max)) * alpha * k * r + k * beta * n / p * lp + k * n / p * math.log2(max(2, k)) * math.log2(max(2, math.log2(sigma)))
    return {"approximate": extra} | merge_sort_time(n, d, d, p, k, d_max, sigma, alpha, beta)


def filter_size(n: int, c: float = math.e) -> int:
    return math.ceil(c * n)


def fingerprint_bits(n: int, p: int, m: int) -> float:
    return math.log2(m * p / max(1, n))


def grid_hops(p: int, k: int) -> tuple[int, int]:
    """(messages per lane of a k-dimensional indirect exchange, times each character moves)."""
    side = 1
    while side**k < p:
        side += 1
    return k * (side - 1), k


def slope(xs: list[float], ys: list[float]) -> float:
    """Log-log growth of times."""
    lx, ly = [math.log(x) for x in xs], [math.log(y) for y in ys]
    mx, my = sum(lx) / len(lx), sum(ly) / len(ly)
    return sum((a - mx) * (b - my) for a, b in zip(lx, ly, strict=True)) / sum((a - mx) ** 2 for a in lx)


def crossover(ps: list[int], single: list[float], multi: list[float]) -> int | None:
    """Smallest p from which on the multi-level times are not above the single-level ones."""
    good = [a >= b for a, b in zip(single, multi, strict=True)]
    return next((p for i, p in enumerate(ps) if all(good[i:])), None)


def simplified_time(n: int, chars: int, p: int, k: int, sigma: int = 256, alpha: float = 1e-5, beta: float = 1e-9) -> float:
    """The merge sort's time where ``simplified_holds``: local work, latency, volume."""
    return chars / p * math.log2(max(2, n)) + alpha * k * p ** (1 / k) + beta * k * chars / p * math.log2(sigma)


def levels_hold(p: int, k: int) -> bool:
    """Few enough levels for the number of lanes."""
    lp = math.log2(p)
    return k <= lp / (2 * math.log2(lp)) if lp > 2 else k == 1


def simplified_holds(chars: int, l_max: int, p: int, k: int) -> bool:
    return l_max <= chars / (k * k * p ** (1 + 1 / k) * math.log2(max(2, p))) and levels_hold(p, k)


def filter_holds(n: int, m: int, p: int, k: int) -> bool:
    """The k-level filter's bound: enough operations for the lanes, and slots for them."""
    return n > k * k * p ** (1 + 1 / k) * math.log2(max(2, p)) and m >= math.e * n


def approximation_holds(n: int, p: int, k: int) -> bool:
    """The prefix approximation's bound: enough strings per lane."""
    lp = math.log2(max(4, p))
    return n / p > k * k * p ** (1 / k) * lp * math.log2(lp) and levels_hold(p, k)


def shortest_approximated(p: int, sigma: int) -> float:
    """Distinguishing prefixes from this length on are approximated within a constant factor, in expectation."""
    return math.log2(p) / math.log2(sigma)


def assignment_volume(r: int, chars: int) -> float:
    """What assigning pieces by characters sends per lane: r offsets below the total, in bits."""
    return r * math.log2(max(2, chars))


def single_level_scales(n: int, p: int) -> bool:
    """One level is held up by partitioning unless there are this many strings."""
    return n >= p * p * math.log2(max(2, p))


def speedup(single: list[float], multi: list[float]) -> list[float]:
    return [a / b for a, b in zip(single, multi, strict=True)]


def match_lanes(ps: list[int], times: list[float], box: list[float]) -> int | None:
    """Smallest number of lanes from which on a run is no slower than the single box on the same input."""
    return crossover(ps, box, times)
