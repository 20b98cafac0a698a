"""Multi-level merge sort of strings: local sort, then per level sample, split, assign, exchange, merge.

State: (grp, lane, lpos, src_id, pos, s), one partition per lane, sorted inside it; ``lpos`` is the 1-based place there,
numbered while the sorted partition streams by, so no window moves strings. A level reads the state to sample, reads it
again to route, and moves each string once (``repartitionById`` to the target lane); sizes, samples, splitters and
assignments are tables of p rows, or p r, set by the plan and not the data. The first level reads the input where it
lies: its lanes are the input's partitions, unless rows come placed (with a ``lane``).
Ties are broken by (src_id, pos); equal strings share a bucket unless ``tie_break`` splits them by locator too.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from levelsort.operators.gridexchange import grid_exchange
from levelsort.plans.levels import DEFAULTS, LevelPlan, plan_equal
from levelsort.staging import cut, forget, scratch

ORDER = ("s", "src_id", "pos")


_LOW = (1 << 33) - 1


def numbered(df: DataFrame, keys: list[str] | tuple[str, ...] = ORDER) -> DataFrame:
    """Each partition sorted by ``keys``; adds lane (its number) and lpos (1-based place), without moving a row."""
    at = df.sortWithinPartitions(*keys).withColumn("_at", F.monotonically_increasing_id())
    return at.withColumn("lane", F.shiftrightunsigned("_at", 33).cast("int")).withColumn("lpos", F.col("_at").bitwiseAND(F.lit(_LOW)) + 1).drop("_at")


def lane_bases(rows: DataFrame) -> DataFrame:
    """lane, base: rows of the lanes before it; one row per lane."""
    before = F.coalesce(F.sum("n").over(W.orderBy("lane").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    return rows.groupBy("lane").agg(F.count("*").alias("n")).select("lane", before.alias("base"))


def dense_index(df: DataFrame, keys: list[str]) -> DataFrame:
    """Adds idx = 0-based place by ``keys`` without one global window: range partitions, their counts, local numbers."""
    dealt = cut(numbered(df.repartitionByRange(*keys).withColumnsRenamed({"lane": "_lane", "lpos": "_lpos"}), keys))
    placed = dealt.join(F.broadcast(lane_bases(dealt)), "lane").withColumn("idx", F.col("base") + F.col("lpos") - 1)
    return placed.drop("lane", "base", "lpos").withColumnsRenamed({"_lane": "lane", "_lpos": "lpos"})


def place_blocks(s: DataFrame, p: int) -> DataFrame:
    """Lane = block of the dense id order: floor(idx p / n)."""
    indexed = dense_index(s.select("src_id", "pos", "s"), ["src_id", "pos"])
    n = indexed.agg(F.count("*").alias("n"))
    return indexed.crossJoin(F.broadcast(n)).select(F.floor(F.col("idx") * p / F.col("n")).cast("int").alias("lane"), "src_id", "pos", "s")


def place_hash(s: DataFrame, p: int) -> DataFrame:
    return s.select(F.pmod(F.xxhash64("src_id", "pos"), F.lit(p)).cast("int").alias("lane"), "src_id", "pos", "s")


def local_sort(placed: DataFrame) -> DataFrame:
    """Adds lpos, the 1-based place inside the lane."""
    return placed.withColumn("lpos", F.row_number().over(W.partitionBy("lane").orderBy(*ORDER)))


def lane_sizes(state: DataFrame) -> DataFrame:
    return state.groupBy("grp", "lane").agg(F.count("*").alias("n"), F.sum(F.length("s")).alias("chars"))


def sample_counts(sizes: DataFrame, p1: int, v: int, by: str, placed: bool = True) -> DataFrame:
    """grp, lane, n, w, m: samples each lane draws so that a group has p1 (v + 1) of them, integers throughout.

    ``placed``: the group's lanes are numbered from grp * p1, empty ones included; otherwise they are those in ``sizes``.
    """
    total = p1 * (v + 1)
    w = F.col("n") if by == "strings" else F.col("chars")
    g = W.partitionBy("grp")
    if placed:
        spark = sizes.sparkSession
        lanes = sizes.select("grp").distinct().join(spark.range(p1).select(F.col("id").cast("int").alias("at")))
        lanes = lanes.select("grp", (F.col("grp") * p1 + F.col("at")).cast("int").alias("lane"), "at")
        full = lanes.join(sizes.select("grp", "lane", "n", w.alias("w")), ["grp", "lane"], "left").fillna(0, ["n", "w"])
    else:
        full = sizes.select("grp", "lane", "n", w.alias("w"), (F.row_number().over(g.orderBy("lane")) - 1).alias("at"))
    m = F.greatest(F.lit(0), F.floor((F.col("w") * total + F.sum("w").over(g) - 1) / F.sum("w").over(g)) - 1)
    drawn = full.withColumn("m", m)
    missing = F.lit(total) - F.sum("m").over(g)
    drawn = drawn.withColumn("m", F.col("m") + F.when(F.col("at") < missing, 1).otherwise(0)).drop("at")
    return drawn.withColumn("m", F.least("m", "n")) if by == "strings" else drawn.withColumn("m", F.when(F.col("n") == 0, 0).otherwise(F.col("m")))


def draw_samples(state: DataFrame, p1: int, v: int, by: str = "strings", placed: bool = True) -> DataFrame:
    """grp, lane, s, src_id, pos, mult: evenly spaced strings of sorted lanes, or those at evenly spaced characters."""
    counts = F.broadcast(sample_counts(lane_sizes(state), p1, v, by, placed).where("m > 0"))
    lane = W.partitionBy("lane").orderBy(*ORDER)
    ranked = state if "lpos" in state.columns else state.withColumn("lpos", F.row_number().over(lane))
    if by == "strings":
        t = F.explode(F.sequence(F.lit(1), F.col("m").cast("int")))
        want = counts.select("grp", "lane", t.alias("t"), "n", "m").select("grp", "lane", F.greatest(F.lit(1), F.floor(F.col("t") * F.col("n") / (F.col("m") + 1))).cast("bigint").alias("lpos"))
        want = want.groupBy("grp", "lane", "lpos").agg(F.count("*").alias("mult"))
        return ranked.join(F.broadcast(want), ["grp", "lane", "lpos"]).select("grp", "lane", "s", "src_id", "pos", "mult")
    end = F.sum(F.length("s")).over(lane.rowsBetween(W.unboundedPreceding, 0))
    spans = ranked.withColumn("end", end).withColumn("start", F.col("end") - F.length("s")).join(counts.select("grp", "lane", "w", "m"), ["grp", "lane"])
    # offsets t w div (m+1) inside [start, end): count them by arithmetic, no row per offset
    below = lambda x: F.greatest(F.lit(0), F.floor((x * (F.col("m") + 1) - 1) / F.col("w")))  # noqa: E731  numbers t >= 1 with t w div (m+1) < x
    hits = F.least(F.col("m"), below(F.col("end"))) - F.least(F.col("m"), below(F.col("start")))
    return spans.withColumn("mult", hits.cast("long")).where("mult > 0").select("grp", "lane", "s", "src_id", "pos", "mult")


def splitters(samples: DataFrame, r: int) -> DataFrame:
    """grp, j, s, src_id, pos: r-1 splitters per group, by index arithmetic over multiplicities."""
    g = W.partitionBy("grp")
    return splitters_at(samples.withColumn("stop", F.sum("mult").over(g.orderBy(*ORDER))).withColumn("size", F.sum("mult").over(g)), r)


def splitters_at(v: DataFrame, r: int) -> DataFrame:
    """Splitters of samples that carry ``size``, the samples of their group, and ``stop``, those up to and with them in order."""
    v = v.withColumn("start", F.col("stop") - F.col("mult"))
    js = F.explode(F.sequence(F.lit(1), F.lit(r - 1))) if r > 1 else F.explode(F.array().cast("array<int>"))
    j = v.select("grp", *ORDER, "start", "stop", "size", js.alias("j"))
    at = F.greatest(F.lit(0), F.floor(F.col("j") * F.col("size") / r) - 1)
    return j.where((at >= F.col("start")) & (at < F.col("stop"))).select("grp", "j", *ORDER)


def splitters_by_hypercube(samples: DataFrame, r: int, lanes: int) -> DataFrame:
    """The same with samples sorted by hypercube quicksort: no task holds more than a lane's share of them."""
    from levelsort.operators.baselines import hypercube_moves

    keys = ("grp", *ORDER)
    last = samples.select(*keys, "mult")
    for moved in hypercube_moves(last, lanes, keys):
        last = moved
    rows = (last if "lane" in last.columns else last.withColumn("lane", F.lit(0))).select("lane", *keys, "mult")
    sums = rows.groupBy("grp", "lane").agg(F.sum("mult").alias("m"))  # a row per group and lane that it reaches into
    g = W.partitionBy("grp")
    before = F.coalesce(F.sum("m").over(g.orderBy("lane").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    placed = rows.join(F.broadcast(sums.select("grp", "lane", before.alias("before"), F.sum("m").over(g).alias("size"))), ["grp", "lane"])
    own = F.sum("mult").over(W.partitionBy("lane", "grp").orderBy(*ORDER))
    return splitters_at(placed.withColumn("stop", F.col("before") + own), r)


def truncate_splitters(f: DataFrame) -> DataFrame:
    """Splitters cut to what tells them apart from their neighbours (equal ones stay whole)."""
    from levelsort.functions.text import lcp

    g = W.partitionBy("grp").orderBy("s", "j")
    near = f.withColumn("a", F.lag("s").over(g)).withColumn("b", F.lead("s").over(g))
    keep = F.greatest(F.coalesce(lcp(F.col("s"), F.col("a")), F.lit(0)), F.coalesce(lcp(F.col("s"), F.col("b")), F.lit(0))) + 1
    return near.select("grp", "j", F.left("s", keep).alias("s"))


UNROLLED = 32
SPLITTER_CHARS = 64_000_000


def bucketize(state: DataFrame, f: DataFrame, r: int | None = None, tie_break: bool = False) -> DataFrame:
    """Adds bucket = number of the group's splitters below the string; equal goes left.

    With few parts (``r``) the comparisons are one expression in the generated code; otherwise a bisection. With
    ``tie_break`` strings and splitters are compared with their locators.
    """
    key = F.struct(*ORDER) if tie_break else F.col("s")
    arrays = f.groupBy("grp").agg(F.array_sort(F.collect_list(key)).alias("fs"))  # r-1 strings per group
    below = lambda i: F.coalesce(F.get("fs", i) < key, F.lit(False))
    if r is not None and r <= UNROLLED:
        bucket = F.lit(0)
        for i in range(r - 1):
            bucket = bucket + below(F.lit(i)).cast("int")
    else:
        steps = F.array(*[F.lit(1 << i) for i in reversed(range(31 if r is None else r.bit_length()))])
        grow = lambda at, t: at + F.when((at + t <= F.size("fs")) & below(at + t - 1), t).otherwise(F.lit(0))
        bucket = F.coalesce(F.aggregate(steps, F.lit(0), grow), F.lit(0))
    return state.join(F.broadcast(arrays), "grp", "left").withColumn("bucket", bucket.cast("int")).drop("fs")


def bucketize_by_join(state: DataFrame, f: DataFrame) -> DataFrame:
    """The same by range join: f_j < s <= f_{j+1}, open ends at the borders."""
    g = W.partitionBy("grp").orderBy("j")
    ranges = f.select("grp", F.col("j").alias("bucket"), F.col("s").alias("lo"), F.lead("s").over(g).alias("hi")).union(f.where("j = 1").select("grp", F.lit(0), F.lit(None).cast("string"), F.col("s")))
    on = (state["grp"] == ranges["grp"]) & (F.col("lo").isNull() | (F.col("lo") < F.col("s"))) & (F.col("hi").isNull() | (F.col("s") <= F.col("hi")))
    return state.join(F.broadcast(ranges), on).select(state["grp"], "lane", "src_id", "pos", "s", F.col("bucket").cast("int").alias("bucket"))


def bucket_counts(bucketed: DataFrame) -> DataFrame:
    return bucketed.groupBy("grp", "lane", "bucket").agg(F.count("*").alias("n"), F.sum(F.length("s")).alias("chars"))


def grid_target(p1: int, r: int) -> Column:
    """Column j of the grid, row of the sender: no balance promised, at most r messages per lane."""
    p2 = p1 // r
    base = F.col("grp") * p1
    return (base + F.col("bucket") * p2 + F.pmod(F.col("lane") - base, F.lit(p2))).cast("int")


def assign_prefix(counts: DataFrame, p1: int, r: int, weight: str = "n") -> DataFrame:
    """Exact equal shares by running sums over lanes: (grp, lane, bucket, lo, hi, target) in weight offsets."""
    p2 = p1 // r
    b = W.partitionBy("grp", "bucket")
    run = F.coalesce(F.sum(weight).over(b.orderBy("lane").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    rows = counts.withColumn("start", run).withColumn("total", F.sum(weight).over(b)).withColumn("w", F.col(weight))
    t = rows.withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(p2 - 1))))
    lo = F.greatest(F.col("start"), F.floor(F.col("t") * F.col("total") / p2))
    hi = F.least(F.col("start") + F.col("w"), F.floor((F.col("t") + 1) * F.col("total") / p2))
    return t.withColumn("lo", (lo - F.col("start")).cast("long")).withColumn("hi", (hi - F.col("start")).cast("long")).where("hi > lo").select("grp", "lane", "bucket", "lo", "hi", (F.col("grp") * p1 + F.col("bucket") * p2 + F.col("t")).cast("int").alias("target"))


def assign_bounded(counts: DataFrame, p1: int, r: int, by: str = "strings") -> DataFrame:
    """Balanced shares with O(r) messages per lane: small pieces go whole, r to a lane; large ones fill what is left.

    Rows: grp, lane, bucket, lo, hi (weight offsets inside the piece), target.
    """
    p2 = p1 // r
    w = F.col("n" if by == "strings" else "chars")
    b = W.partitionBy("grp", "bucket")
    pieces = counts.where(w > 0).select("grp", "lane", "bucket", w.alias("w")).withColumn("total", F.sum("w").over(b)).withColumn("small", 2 * r * p2 * F.col("w") <= F.col("total"))
    number = F.row_number().over(W.partitionBy("grp", "bucket", "small").orderBy("lane")) - 1
    small = pieces.where("small").withColumn("t", F.least(F.floor(number / r), F.lit(p2 - 1)).cast("int"))
    done = small.groupBy("grp", "bucket", "t").agg(F.sum("w").alias("got"))
    buckets = pieces.select("grp", "bucket", "total").distinct().withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(p2 - 1))))
    cap = F.floor((F.col("t") + 1) * F.col("total") / p2) - F.floor(F.col("t") * F.col("total") / p2)
    rest = buckets.join(done, ["grp", "bucket", "t"], "left").withColumn("room", F.greatest(F.lit(0), cap - F.coalesce("got", F.lit(0))))
    by_t = W.partitionBy("grp", "bucket").orderBy("t")
    rest = rest.withColumn("c1", F.sum("room").over(by_t)).withColumn("c0", F.col("c1") - F.col("room")).withColumn("last", F.col("t") == p2 - 1)
    large = pieces.where("not small").withColumn("o1", F.sum("w").over(W.partitionBy("grp", "bucket").orderBy("lane"))).withColumn("o0", F.col("o1") - F.col("w"))
    end = F.when(F.col("last"), F.greatest(F.col("c1"), F.col("o1"))).otherwise(F.col("c1"))
    met = large.join(rest.select("grp", "bucket", "t", "c0", "c1", "last"), ["grp", "bucket"]).withColumn("a", F.greatest("o0", "c0")).withColumn("z", F.least(F.col("o1"), end)).where("z > a")
    target = (F.col("grp") * p1 + F.col("bucket") * p2 + F.col("t")).cast("int").alias("target")
    return small.select("grp", "lane", "bucket", F.lit(0).cast("long").alias("lo"), F.col("w").cast("long").alias("hi"), target).union(met.select("grp", "lane", "bucket", (F.col("a") - F.col("o0")).cast("long"), (F.col("z") - F.col("o0")).cast("long"), target))


RANGE_ROWS = 1_000_000


def route(bucketed: DataFrame, ranges: DataFrame, by: str = "strings", rows: int | None = None) -> DataFrame:
    """Adds target: the range of its (lane, bucket) piece that holds the string's first offset.

    ``rows``: how many ranges there are at most; they are broadcast up to ``RANGE_ROWS`` of them, joined by piece beyond.
    """
    r = ranges.select(F.col("grp").alias("_g"), F.col("lane").alias("_l"), F.col("bucket").alias("_b"), "lo", "hi", "target")
    if by == "strings" and "lpos" in bucketed.columns:  # a sorted lane holds its buckets one after the other
        starts = bucketed.groupBy("grp", "lane", "bucket").agg(F.min("lpos").alias("_first"))
        r = r.join(starts.select(F.col("grp").alias("_g"), F.col("lane").alias("_l"), F.col("bucket").alias("_b"), "_first"), ["_g", "_l", "_b"])
        placed, offset = bucketed, F.col("lpos") - F.col("_first")
    else:
        w = F.lit(1) if by == "strings" else F.length("s")
        order = W.partitionBy("grp", "lane", "bucket").orderBy(*ORDER)
        placed = bucketed.withColumn("_o", F.coalesce(F.sum(w).over(order.rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
        offset = F.col("_o")
    on = (F.col("grp") == F.col("_g")) & (F.col("lane") == F.col("_l")) & (F.col("bucket") == F.col("_b")) & (offset >= F.col("lo")) & (offset < F.col("hi"))
    return placed.join(F.broadcast(r) if rows is None or rows <= RANGE_ROWS else r.hint("merge"), on).drop("_g", "_l", "_b", "lo", "hi", "_o", "_first")


@dataclass
class Sorted:
    """``rows``: (lane, lpos, src_id, pos, s), lanes in order; ``moves``: per level (grp, lane, bucket, target, n, chars);
    ``states``: what each level started from; ``hops``: per level and hop (src, dst, n, chars) of exchanges over a grid."""

    rows: DataFrame
    moves: list[DataFrame] = field(default_factory=list)
    samples: list[DataFrame] = field(default_factory=list)
    cuts: list[DataFrame] = field(default_factory=list)
    states: list[DataFrame] = field(default_factory=list)
    hops: list[list[DataFrame]] = field(default_factory=list)

    def ranked(self) -> DataFrame:
        """rank (1-based), src_id, pos, s: rows of the lanes before, plus the place in the lane."""
        return self.rows.join(F.broadcast(lane_bases(self.rows)), "lane").select((F.col("base") + F.col("lpos")).cast("bigint").alias("rank"), "src_id", "pos", "s")


def to_lanes(rows: DataFrame, lanes: int, target: str) -> DataFrame:
    """The one exchange: every row to the partition named by ``target``, sorted there; adds lane (= target) and lpos."""
    return numbered(rows.repartitionById(lanes, F.col(target)))


def _shared(a: str, b: str) -> int:
    """Common prefix of two Python strings, compared in doubling slices."""
    n, at, step = min(len(a), len(b)), 0, 16
    while at < n and a[at : at + step] == b[at : at + step]:
        at, step = min(n, at + step), 2 * step
    while at < n and step > 1:
        step //= 2
        if a[at : at + step] == b[at : at + step]:
            at = min(n, at + step)
    return at


def _encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """s -> (seq, h, tail): what the string before it on the way to the same target does not share."""
    target, last, seq = None, "", 0
    for b in batches:
        hs, tails, seqs = [], [], []
        for to, s in zip(b.column("target").to_pylist(), b.column("s").to_pylist(), strict=True):
            h = _shared(last, s) if to == target else 0
            hs.append(h)
            tails.append(s[h:])
            seqs.append(seq)
            target, last, seq = to, s, seq + 1
        rest = [c for c in b.schema.names if c != "s"]
        yield pa.RecordBatch.from_arrays([*(b.column(c) for c in rest), pa.array(seqs, pa.int64()), pa.array(hs, pa.int32()), pa.array(tails, pa.string())], [*rest, "seq", "h", "tail"])


def _decode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    way, last = None, ""
    for b in batches:
        out = []
        for to, sender, h, tail in zip(*(b.column(c).to_pylist() for c in ("target", "sender", "h", "tail")), strict=True):
            last = (last[:h] if (to, sender) == way else "") + tail
            way = (to, sender)
            out.append(last)
        rest = [c for c in b.schema.names if c not in ("seq", "tail")]
        yield pa.RecordBatch.from_arrays([*(b.column(c) for c in rest), pa.array(out, pa.string())], [*rest, "s"])


_SENT = "grp int, sender int, bucket int, target int, src_id bigint, pos int"


def front_coded(sent: DataFrame) -> DataFrame:
    """What a front-coded exchange sends: ``sent`` sorted by target in its partitions, s as seq, h, tail."""
    ordered = sent.select("grp", "sender", "bucket", "target", "src_id", "pos", "s").sortWithinPartitions("target", *ORDER)
    return ordered.mapInArrow(_encode, f"{_SENT}, seq bigint, h int, tail string")


def sent_volume(sent: DataFrame, compress: bool) -> DataFrame:
    """grp, lane, bucket, target, n, chars (and coded) of an exchange, counted at the senders: nothing is moved."""
    rows = front_coded(sent) if compress else sent
    chars = F.sum(F.col("h") + F.length("tail")) if compress else F.sum(F.length("s"))
    coded = [F.sum(F.length("tail")).alias("coded")] if compress else []
    return rows.groupBy("grp", F.col("sender").alias("lane"), "bucket", "target").agg(F.count("*").alias("n"), chars.alias("chars"), *coded)


def level_moves(placed: DataFrame, plan: LevelPlan, levels: int | None = None, compress: bool = False) -> list[DataFrame]:
    """The moves of ``level_merge_sort`` (rows with a lane, default options) over the first ``levels`` levels, all by default.

    For counters alone: strings are moved only between levels that are counted, and a level's strings are deleted once
    the next level has them.
    """
    spark, moves = placed.sparkSession, []
    kept = cut(to_lanes(placed.select(F.col("lane").alias("_to"), "src_id", "pos", "s"), plan.lanes, "_to").drop("_to"), keep=True)
    state = kept.select(F.lit(0).alias("grp"), "lane", "lpos", "src_id", "pos", "s")
    steps = list(zip(plan.group_sizes, plan.factors, strict=True))[:levels]
    for i, (p1, r) in enumerate(steps, 1):
        with scratch(spark):
            fs = cut(splitters(draw_samples(state, p1, DEFAULTS["v"], DEFAULTS["sampling"]), r))
            if (fs.agg(F.sum(F.length("s"))).first()[0] or 0) > SPLITTER_CHARS:
                fs = truncate_splitters(fs)
            routed = bucketize(state, fs, r).withColumn("target", grid_target(p1, r))
            sent = routed.select("grp", F.col("lane").alias("sender"), "bucket", "target", "src_id", "pos", "s")
            moves.append(cut(sent_volume(sent, compress), keep=True))
            moved = cut(to_lanes(sent, plan.lanes, "target"), keep=True) if i < len(steps) else None
        forget(kept)
        if moved is not None:
            kept = moved
            state = moved.select(F.floor(F.col("target") / (p1 // r)).cast("int").alias("grp"), F.col("target").alias("lane"), "lpos", "src_id", "pos", "s")
    return moves


def front_coded_lanes(sent: DataFrame, lanes: int) -> DataFrame:
    """``to_lanes`` with front coding: tails and common prefix lengths travel, strings are restored on arrival.

    A partition of ``sent`` is one sender; h is kept, so the volume that travelled can be summed.
    """
    coded = front_coded(sent)
    arrived = coded.repartitionById(lanes, F.col("target")).sortWithinPartitions("target", "sender", "seq")
    return numbered(arrived.mapInArrow(_decode, f"{_SENT}, h int, s string"))


def level_merge_sort(rows: DataFrame, plan: LevelPlan, sampling: str = DEFAULTS["sampling"], v: int = DEFAULTS["v"], assign: str = DEFAULTS["assign"], tie_break: bool = False, compress: bool = DEFAULTS["compress"], sample_sort: str = DEFAULTS["sample_sort"], hops: int = DEFAULTS["hops"], spend: bool = False) -> Sorted:
    """Sort (src_id, pos, s) over the plan's levels, one full exchange per level, front-coded with ``compress``.

    Samples are sorted by one window, or by hypercube quicksort over the lanes (``sample_sort="hypercube"``). With
    ``hops`` > 1 an exchange goes over a grid of so many dimensions, each string moving once per dimension.

    Rows with a ``lane`` are first brought to that lane; rows without are sampled and routed from where they lie. With
    ``spend`` the strings that a level started from are deleted once the next level has them: volumes are counted at
    once, samples and states are not given.
    """
    placed, held = "lane" in rows.columns, None
    if placed:
        held = state = cut(to_lanes(rows.select(F.col("lane").alias("_to"), "src_id", "pos", "s"), plan.lanes, "_to").drop("_to"))
    else:
        state = numbered(rows.select("src_id", "pos", "s"))
    state = state.select(F.lit(0).alias("grp"), "lane", "lpos", "src_id", "pos", "s")
    if not placed and (sampling != "strings" or assign != "grid"):  # their windows and offsets need the numbers to stand
        state = cut(state)
    out = Sorted(state)
    for level, (p1, r) in enumerate(zip(plan.group_sizes, plan.factors, strict=True)):
        p2 = p1 // r
        samples = draw_samples(state, p1, v, sampling, placed or level > 0)
        cuts = cut(splitters_by_hypercube(samples, r, plan.lanes) if sample_sort == "hypercube" else splitters(samples, r))
        fs = cuts
        if not tie_break and (cuts.agg(F.sum(F.length("s"))).first()[0] or 0) > SPLITTER_CHARS:
            fs = truncate_splitters(cuts)
        if not placed and level == 0 and assign == "grid":  # unsorted: only the partition's number is needed to route
            state = rows.select(F.lit(0).alias("grp"), F.spark_partition_id().alias("lane"), "src_id", "pos", "s")
        bucketed = bucketize(state, fs, r, tie_break)
        if assign == "grid" or p2 == 1:
            routed = bucketed.withColumn("target", grid_target(p1, r))
        else:
            by = "chars" if assign.endswith("chars") else "strings"
            pieces = cut(bucket_counts(bucketed))
            ranges = assign_prefix(pieces, p1, r, "n" if by == "strings" else "chars") if assign.startswith("prefix") else assign_bounded(pieces, p1, r, by)
            routed = route(bucketed, ranges, by, plan.lanes * (r + p2))
        sent = routed.select("grp", F.col("lane").alias("sender"), "bucket", "target", "src_id", "pos", "s")
        if hops > 1:
            sent, way = grid_exchange(sent, plan_equal(plan.lanes, hops).factors)
            out.hops.append(way)
        moved = cut(front_coded_lanes(sent, plan.lanes) if compress else to_lanes(sent, plan.lanes, "target"))
        volume = [F.count("*").alias("n"), F.sum(F.length("s")).alias("chars")] + ([F.sum(F.length("s") - F.col("h")).alias("coded")] if compress else [])
        out.moves.append(moved.groupBy("grp", F.col("sender").alias("lane"), "bucket", "target").agg(*volume))
        out.cuts.append(cuts)
        if spend:
            out.moves[-1] = cut(out.moves[-1])
            if held is not None:
                forget(held)
            held = moved
        else:
            out.samples.append(samples)
            out.states.append(state)
        state = moved.select(F.floor(F.col("target") / p2).cast("int").alias("grp"), F.col("target").alias("lane"), "lpos", "src_id", "pos", "s")
    out.rows = state.select("lane", "lpos", "src_id", "pos", "s")
    return out


def global_rank(rows: DataFrame) -> DataFrame:
    """rank (1-based), src_id, pos, s of rows whose lanes are in order: offset of the lane plus place inside it."""
    return local_sort(rows).join(F.broadcast(lane_bases(rows)), "lane").select((F.col("base") + F.col("lpos")).cast("bigint").alias("rank"), "src_id", "pos", "s")
