"""Prefix doubling: approximate distinguishing prefixes by fingerprint tests, then sort only those prefixes."""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from levelsort.functions.text import FINGERPRINT_SPACE, fingerprint, lcp
from levelsort.operators.mergesort import Sorted, dense_index, level_merge_sort
from levelsort.plans.levels import LevelPlan
from levelsort.staging import Bucketed, cut


def duplicate_counts(fps: DataFrame, k: int = 1, lanes: int = 8, m: int = FINGERPRINT_SPACE) -> list[DataFrame]:
    """Hops of the k-level fingerprint filter over (lane, fp): each fixes one digit of the owner lane and adds up equal
    fingerprints that meet there. The last table is (fp, cnt) over the whole input; k = 1 is one hash aggregate."""
    b = 1
    while b**k < lanes:
        b += 1
    owner = F.floor(F.col("fp") * lanes / m)  # fp < 2^40 and few lanes: exact in double precision
    rows = fps.select(F.pmod(F.col("lane"), F.lit(b**k)).alias("at"), "fp", F.lit(1).cast("bigint").alias("cnt"))
    hops = []
    for j in range(k):
        size = b ** (k - 1 - j)
        digit = F.pmod(F.floor(owner / size), F.lit(b))
        here = F.pmod(F.floor(F.col("at") / size), F.lit(b))
        rows = rows.withColumn("at", (F.col("at") + (digit - here) * size).cast("bigint")).groupBy("at", "fp").agg(F.sum("cnt").alias("cnt"))
        hops.append(rows)
    return hops


def unique_by_sort(fps: DataFrame) -> DataFrame:
    """The detector for few strings: sort fingerprints, compare neighbours; (src_id, pos, dup)."""
    from pyspark.sql import Window as W

    # range partitions meet at their borders: a border's fingerprint never splits, as the range is by fp alone
    dealt = fps.select("fp", "src_id", "pos").repartitionByRange("fp").withColumn("part", F.spark_partition_id())
    w = W.partitionBy("part").orderBy("fp", "src_id", "pos")
    same = lambda c: F.coalesce(c == F.col("fp"), F.lit(False))
    return dealt.withColumn("dup", same(F.lag("fp").over(w)) | same(F.lead("fp").over(w))).select("src_id", "pos", "dup")


LOCATOR = ["src_id", "pos"]
#: A copy of the strings still active is written once they are at most one in ``COMPACT`` of the last copy, if that is large.
COMPACT = 8
COMPACT_ROWS = 1_000_000


def switch_threshold(lanes: int, k: int) -> int:
    """Active strings below which the k-level filter's cost bound no longer holds, and sorting takes over."""
    return math.ceil(k * k * lanes ** (1 + 1 / k) * math.log2(max(2, lanes)))


def prints(s: DataFrame, d: int, m: int = FINGERPRINT_SPACE, detector: str = "filter", seed: int = 0) -> DataFrame:
    """src_id, pos, len, fp: what a round sends of a string; the d-prefix itself only for the exact detector."""
    exact = F.concat(F.least(F.length("s") + 1, F.lit(d)).cast("string"), F.lit(":"), F.left("s", F.lit(d)))
    return s.select(*LOCATOR, F.length("s").alias("len"), (exact if detector == "exact" else fingerprint(F.col("s"), F.lit(d), m, seed)).alias("fp"))


def marked(fps: DataFrame, m: int = FINGERPRINT_SPACE, detector: str = "filter", k: int = 1, lanes: int = 8) -> DataFrame:
    """src_id, pos, len, dup: whether another string sent the same fingerprint."""
    if detector == "sort":
        return fps.select(*LOCATOR, "len").join(unique_by_sort(fps), LOCATOR)
    if detector == "exact":
        counts = fps.groupBy("fp").agg(F.count("*").alias("cnt"))
    else:
        lane = F.pmod(F.xxhash64(*LOCATOR), F.lit(lanes))
        counts = duplicate_counts(fps.select(lane.alias("lane"), "fp"), k, lanes, m)[-1].select("fp", "cnt")
    dups = counts.where("cnt > 1").select("fp", F.lit(True).alias("dup"))
    return fps.join(dups, "fp", "left").select(*LOCATOR, "len", F.coalesce("dup", F.lit(False)).alias("dup"))


def doubling_round(active: DataFrame, d: int, m: int = FINGERPRINT_SPACE, detector: str = "filter", k: int = 1, lanes: int = 8, seed: int = 0) -> DataFrame:
    """src_id, pos, done: the d-prefix is unique among the active strings, or the string is shorter than d."""
    tested = marked(prints(active, d, m, detector, seed), m, detector, k, lanes)
    return tested.select(*LOCATOR, (~F.col("dup") | (F.col("len") < d)).alias("done"))


class Doubling:
    """The rounds over one string set, whose strings are written once, bucketed by locator, and never moved by a round.

    A round reads the strings where they lie, sends (fingerprint, locator) and gets back the locators that stay
    active. ``rounds`` is the trace; ``dist`` gives (src_id, pos, len, dist_approx); ``prefixes`` the cut strings.
    ``detector='auto'`` tests by filter while at least ``threshold`` strings are active, by sorting below it; with
    ``finish`` the first round below it sorts the few strings themselves, which settles all further rounds at once.
    """

    def __init__(
        self, s: DataFrame, d0: int = 4, growth: int = 2, m: int = FINGERPRINT_SPACE, detector: str = "filter", k: int = 1, lanes: int = 8,
        threshold: int | None = None, seed: int = 0, buckets: int | None = None, finish: bool = False,
    ):
        buckets = buckets or int(s.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        least = switch_threshold(lanes, k) if threshold is None else threshold
        self.strings = Bucketed(s.select(*LOCATOR, "s"), LOCATOR, buckets)
        self.rounds: list[dict] = []
        self._sent: list[DataFrame] = []
        self._settled: DataFrame | None = None
        held, n_held, rows, d = self.strings, None, self.strings.df, d0
        how = "filter" if detector == "auto" else detector
        while True:
            fps = cut(prints(rows, d, m, how, seed))
            n = fps.count()
            if self.rounds:
                self.rounds[-1]["n_retired"] = self.rounds[-1]["n_active"] - n
            if not n:
                break
            n_held = n_held or n
            if detector == "auto":
                how = "filter" if n >= least else "sort"
            if finish and how == "sort":
                self.rounds.append({"round": len(self.rounds) + 1, "d": d, "n_active": n, "n_retired": n, "detector": "strings"})
                self._settled = cut(self._settle(rows, d0 if len(self.rounds) == 1 else d // growth))
                break
            self.rounds.append({"round": len(self.rounds) + 1, "d": d, "n_active": n, "n_retired": n, "detector": how})
            self._sent.append(fps.select(*LOCATOR, "len", F.lit(d).alias("d")))
            active = marked(fps, m, how, k, lanes).where(F.col("dup") & (F.col("len") >= d)).select(*LOCATOR)
            if n * COMPACT <= n_held and n_held > COMPACT_ROWS:
                smaller = Bucketed(held.df.join(active, LOCATOR, "left_semi"), LOCATOR, buckets)
                if held is not self.strings:
                    held.drop()
                held, n_held, rows = smaller, n, smaller.df
            else:
                rows = held.df.join(active, LOCATOR, "left_semi")
            d *= growth
        if held is not self.strings:
            held.drop()

    @staticmethod
    def _settle(rows: DataFrame, least: int) -> DataFrame:
        """src_id, pos, len, d of fewer strings than the threshold, which the plan bounds: one sorted window."""
        w = W.orderBy("s", *LOCATOR)
        shared = F.greatest(*[F.coalesce(lcp(F.col("s"), near("s").over(w)), F.lit(0)) for near in (F.lag, F.lead)])
        return rows.select(*LOCATOR, F.length("s").alias("len"), F.greatest(F.lit(least), shared + 1).alias("d"))

    def dist(self) -> DataFrame:
        """src_id, pos, len, dist_approx: the length of the last round that a string took part in."""
        if self._settled is not None:
            self._sent, self._settled = [*self._sent, self._settled], None
        if not self._sent:
            return self.strings.spark.createDataFrame([], "src_id bigint, pos int, len int, dist_approx int")
        last = reduce(DataFrame.unionByName, self._sent).groupBy(*LOCATOR).agg(F.max("len").alias("len"), F.max("d").alias("d"))
        return last.select(*LOCATOR, "len", F.least("d", F.col("len") + 1).alias("dist_approx"))

    def prefixes(self) -> DataFrame:
        """src_id, pos, s: each string cut to its approximate distinguishing prefix."""
        return self.strings.df.join(self.dist().select(*LOCATOR, "dist_approx"), LOCATOR).select(*LOCATOR, F.left("s", F.col("dist_approx")).alias("s"))


def approx_dist(s: DataFrame, **options) -> tuple[DataFrame, list[dict]]:
    """((src_id, pos, len, dist_approx), trace). Strings retire once a prefix is proved unique; rounds end when none is left."""
    run = Doubling(s, **options)
    run.strings.drop()
    return run.dist(), run.rounds


def prefixes(s: DataFrame, **options) -> DataFrame:
    """src_id, pos, s: each string cut to its approximate distinguishing prefix."""
    run = Doubling(s, **options)
    out = cut(run.prefixes())
    run.strings.drop()
    return out


#: Of whole prefix-doubling sorts: few long rounds, the filter over as many levels as the plan has, sorting for the rest.
SORT_ROUNDS = {"d0": 8, "growth": 4, "detector": "auto", "finish": True}


def sort_prefixes(s: DataFrame, plan: LevelPlan, **options) -> Sorted:
    """The level sort of the prefixes, with its moves."""
    sort_options = {k: options.pop(k) for k in ("sampling", "v", "assign") if k in options}
    rounds = SORT_ROUNDS | {"k": len(plan.factors), "lanes": plan.lanes} | options
    return level_merge_sort(prefixes(s, **rounds), plan, **sort_options)


def prefix_doubling_sort(s: DataFrame, plan: LevelPlan, **options) -> DataFrame:
    """rank, src_id, pos: where to find the string of each rank; only prefixes are sorted and moved."""
    return sort_prefixes(s, plan, **options).ranked().select("rank", "src_id", "pos")


def materialize(permutation: DataFrame, s: DataFrame) -> DataFrame:
    return permutation.join(s.select("src_id", "pos", "s"), ["src_id", "pos"]).select("rank", "src_id", "pos", "s")


def suffixes(docs: DataFrame, key: str = "text", id_col: str = "item_id") -> DataFrame:
    """(src_id, pos) of all suffixes with the suffix as a column expression over the text."""
    return docs.select(F.col(id_col).cast("bigint").alias("src_id"), F.posexplode(F.sequence(F.lit(1), F.length(key))).alias("pos", "at"), F.col(key).alias("_t")).select("src_id", "pos", F.expr("substring(_t, at)").alias("s"))


def windows(docs: DataFrame, width: int, key: str = "text", id_col: str = "item_id") -> DataFrame:
    """All substrings of one width."""
    long = docs.where(F.length(key) >= width)
    return long.select(F.col(id_col).cast("bigint").alias("src_id"), F.posexplode(F.sequence(F.lit(1), F.length(key) - (width - 1))).alias("pos", "at"), F.col(key).alias("_t")).select("src_id", "pos", F.expr(f"substring(_t, at, {width})").alias("s"))


def suffix_ranks(docs: DataFrame, key: str = "text", id_col: str = "item_id") -> DataFrame:
    """rank, src_id, pos of all suffixes in order, without making any: places are ordered by 1, 2, 4, ... characters.

    Every place carries the class of its next ``step`` characters; with the class ``step`` places further on it makes that
    of twice as many, numbered over the distinct pairs. A round moves places and numbers, never text. It ends when
    every place is a class of its own or no class was split (equal suffixes: ties go by locator).
    """
    text = docs.select(F.col(id_col).cast("bigint").alias("src_id"), F.posexplode(F.regexp_extract_all(key, F.lit("(?s)."), F.lit(0))).alias("pos", "c"))
    state = cut(text.select("src_id", "pos", F.ascii("c").cast("bigint").alias("cls")))
    n, classes, step = state.count(), 0, 1
    while n:
        after = state.select("src_id", (F.col("pos") - step).alias("pos"), F.col("cls").alias("nxt")).where("pos >= 0")
        pairs = cut(state.join(after, ["src_id", "pos"], "left").select("src_id", "pos", "cls", F.coalesce("nxt", F.lit(-1)).alias("nxt")))
        numbers = cut(dense_index(pairs.select("cls", "nxt").distinct(), ["cls", "nxt"]))
        found = numbers.count()
        if found == classes:
            break
        state = cut(pairs.join(numbers, ["cls", "nxt"]).select("src_id", "pos", F.col("idx").cast("bigint").alias("cls")))
        classes, step = found, 2 * step
        if classes == n:
            break
    placed = dense_index(state, ["cls", "src_id", "pos"])
    return placed.select((F.col("idx") + 1).cast("bigint").alias("rank"), "src_id", "pos")
