"""Jaccard self-join over word shingles by token-combination prefixes.

Every document is the set of 64-bit hashes of its distinct word 5-grams; copies of one set are one set from the
start. Two different sets x, y with J(x, y) >= t overlap in at least ceil(t n_x) and ceil(t n_y) hashes, and in
at least two, so under any global token order their prefixes of n - ceil(t n) + k hashes share at least k (or
their whole overlap, if that is less). That is used four times:

1. *Support filter* under plain hash order with prefixes extended by k = 2 + n // 10 (``reach``): a set stays only
   if enough (``needed``) of its prefix hashes occur in another set's prefix. About a third of the hashes move, once.
2. *Clusters first*: sets that share a min-hash are compared inside bounded blocks; this only joins documents
   whose Jaccard was checked.
3. *Support across clusters*: the same count over the same prefixes, of hashes that a set of another cluster has too.
   Sets below it can only be linked inside their cluster, so only the few others are indexed with all their hashes.
4. *Index* under the order (dead, document frequency, hash), where a token is dead if all its documents lie in
   one cluster. Prefixes are extended by one, so two linked documents of different clusters share two live
   tokens there: either a rare one, indexed alone, or two frequent ones, indexed as a 2-combination of their classes
   (tokens whose posting lists have the same min-hash document).
   Posting lists are compared in blocks of bounded size; pairs already known to be connected are skipped.

Links join clusters by rounds of minimum-label contraction, until no edge is left. No step has a cap that drops
work: large key groups are cut into blocks and every pair of blocks is visited. Joins back from clusters and sets
to their members salt the keys that have many of them (``spread_join``).

Defined results: null or empty text has an empty set, n_shingles 0, and is linked with nothing; a null
doc_id is never linked and has a null component; repeated rows get equal results; other columns are ignored.
Set identity is a 64-bit hash of the set (two different sets among d coincide with probability d*d / 2^65).
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from functools import reduce
from itertools import count

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from levelsort.llm.common import Stage, fresh, lean, release, settled, small, spread_join

BLOCK = 256
RARE = 64
ROUNDS = 4
BROADCAST_ROWS = 500_000
_FACTOR, _MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)


def _mix(a: np.ndarray) -> np.ndarray:
    a = a ^ (a >> np.uint64(29))
    a = a * _MIX
    return a ^ (a >> np.uint64(32))


def shingle_hashes(text: str | None, width: int = 5) -> np.ndarray:
    """Sorted distinct int64 hashes of the word shingles; a shorter text is one shingle of all its words."""
    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return np.empty(0, np.int64)
    with np.errstate(over="ignore"):
        w = np.fromiter(map(xxhash.xxh3_64_intdigest, words), np.uint64, len(words))
        if len(w) < width:
            s = np.array([len(w)], np.uint64)
            for x in w:
                s = s * _FACTOR + x
        else:
            s = w[: len(w) - width + 1].copy()
            for k in range(1, width):
                s = s * _FACTOR + w[k : len(w) - width + 1 + k]
        return np.unique(_mix(s).view(np.int64))


def set_id(h: np.ndarray) -> int:
    with np.errstate(over="ignore"):
        u = h.view(np.uint64)
        return int(_mix(np.array([u.sum() * _FACTOR + np.bitwise_xor.reduce(u) + np.uint64(len(u))], np.uint64)).view(np.int64)[0]) if len(u) else 0


def lost(n: int, percent: int) -> int:
    """Most hashes of a set of n that a linked set may lack."""
    return n + (-percent * n // 100)


def reach(n: int, percent: int) -> int:
    """Length of the prefix in hash order that a set of n sends to the support filters."""
    return min(n, lost(n, percent) + 2 + n // 10)


def _needed(percent: int) -> Column:
    """Hashes that the prefixes of two linked, different sets share at least; ``n`` is the size of either."""
    return F.lit(2) + F.floor(F.floor(F.col("n") * percent / 100) / 10)


def linked(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    """a, b sorted and distinct."""
    if len(a) > len(b):
        a, b = b, a
    if 100 * len(a) < percent * len(b):
        return False
    at = np.searchsorted(b, a)
    at[at == len(b)] = 0
    both = int(np.count_nonzero(b[at] == a))
    return 100 * both >= percent * (len(a) + len(b) - both)


def _lists(values: list[np.ndarray]) -> pa.Array:
    ends = np.cumsum([0, *map(len, values)])
    flat = np.concatenate(values) if values else np.empty(0, np.int64)
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(flat, pa.int64()))


def _sketch(percent: int, width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 512):
                part = b.slice(at, 512)
                sets = [shingle_hashes(t, width) for t in part.column("text").to_pylist()]
                n = [len(s) for s in sets]
                yield pa.RecordBatch.from_arrays(
                    [part.column("doc_id"), pa.array(map(set_id, sets), pa.int64()), pa.array(n, pa.int64()), _lists([s[: reach(k, percent)] for s, k in zip(sets, n, strict=True)])],
                    ["doc_id", "sid", "n", "prefix"],
                )

    return run


def _full_sets(percent: int, width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for at in range(0, b.num_rows, 256):
                part = b.slice(at, 256)
                sets = [shingle_hashes(t, width) for t in part.column("text").to_pylist()]
                ids = [set_id(s) for s in sets]
                with np.errstate(over="ignore"):
                    second = [int(_mix(s.view(np.uint64) * _FACTOR).view(np.int64).min()) if len(s) else 0 for s in sets]
                yield pa.RecordBatch.from_arrays(
                    [part.column("sid"), pa.array([reach(len(s), percent) for s in sets], pa.int32()), pa.array([i == j for i, j in zip(ids, part.column("sid").to_pylist(), strict=True)]), pa.array([int(s[0]) if len(s) else 0 for s in sets], pa.int64()), pa.array(second, pa.int64()), _lists(sets)],
                    ["sid", "reach", "same", "low1", "low2", "hashes"],
                )

    return run


class _Forest:
    def __init__(self, labels: list[int]):
        self.up = {x: x for x in labels}

    def top(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = x = self.up[self.up[x]]
        return x

    def join(self, a: int, b: int) -> None:
        a, b = self.top(a), self.top(b)
        self.up[max(a, b)] = min(a, b)


def _split(t: pa.Table, name: str) -> list[np.ndarray]:
    c = t.column(name).combine_chunks()
    c = c if isinstance(c, pa.ListArray) else pa.concat_arrays(c.chunks)
    flat, ends = c.values.to_numpy(zero_copy_only=False), c.offsets.to_numpy()
    return [flat[i:j] for i, j in zip(ends[:-1], ends[1:], strict=True)]


def _cluster(percent: int):
    """Labels of one block: the smallest sid that checked links reach inside it."""

    def run(t: pa.Table) -> pa.Table:
        sid, sets = t.column("sid").to_pylist(), _split(t, "hashes")
        forest, tops = _Forest(sid), []
        for i, s in enumerate(sets):
            for j in tops:
                if forest.top(sid[i]) != forest.top(sid[j]) and linked(s, sets[j], percent):
                    forest.join(sid[i], sid[j])
            if forest.top(sid[i]) == sid[i] or all(forest.top(sid[i]) != forest.top(sid[j]) for j in tops):
                tops.append(i)
        return pa.table({"sid": pa.array(sid, pa.int64()), "label": pa.array([forest.top(x) for x in sid], pa.int64())})

    return run


def _compare(percent: int):
    """Checked links between the labels of two blocks of one posting list (or inside one block)."""

    def run(t: pa.Table) -> pa.Table:
        sid, label, side = (t.column(c).to_pylist() for c in ("sid", "label", "block"))
        sets, forest, links = _split(t, "hashes"), _Forest(label), []
        order = sorted(range(len(sid)), key=lambda i: len(sets[i]))
        same = len(set(side)) == 1
        for k, i in enumerate(order):
            for j in order[:k]:
                if (same or side[i] != side[j]) and forest.top(label[i]) != forest.top(label[j]) and linked(sets[j], sets[i], percent):
                    forest.join(label[i], label[j])
                    links.append((min(label[i], label[j]), max(label[i], label[j])))
        return pa.table({"a": pa.array([x[0] for x in links], pa.int64()), "b": pa.array([x[1] for x in links], pa.int64())})

    return run


def _check_pairs(percent: int):
    """Pairs (hashes, other_hashes, a, b) -> the label pairs a, b whose sets are linked."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                t = pa.Table.from_batches([batch.slice(at, 256)])
                ok = [linked(x, y, percent) for x, y in zip(_split(t, "hashes"), _split(t, "other_hashes"), strict=True)]
                yield from t.select(["a", "b"]).filter(pa.array(ok, pa.bool_())).to_batches()

    return run


def _clustered(sets: Stage, rows: DataFrame, key: str, percent: int) -> DataFrame:
    """sid, label for sets (``rows``: sid, key) that share ``key`` with another; large key groups are dealt into blocks."""
    sizes = rows.groupBy(key).agg(F.count("*").alias("m")).where("m > 1")
    shared = Stage(rows.join(sizes, key).select("sid", F.col(key).alias("key"), F.pmod(F.xxhash64("sid"), F.ceil(F.col("m") / BLOCK)).cast("int").alias("block")), "key-groups")
    dealt = sets.df.select("sid", "hashes").join(small(shared.df, shared.df.count(), BROADCAST_ROWS), "sid")
    return dealt.groupBy("key", "block").applyInArrow(_cluster(percent), "sid long, label long")


def contract(edges: DataFrame) -> DataFrame:
    """node, root for every node of ``edges`` (a, b); nodes of one component, and no others, share a root.

    Each round every node hooks onto the neighbour (or itself) of lowest priority, a hash that changes with the
    round, follows that hook once more, and the edges are mapped to the hooks. The image of a component stays
    connected and loses about half of its nodes, so the rounds are logarithmic also on long chains.
    """
    spark = edges.sparkSession
    live = Stage(edges.where("a <> b").select("a", "b").distinct(), "edges")
    maps: list[Stage] = []
    for r in count():
        if live.df.isEmpty():
            break
        both = live.df.select("a", "b").union(live.df.select("b", "a"))
        near = both.select(F.col("a").alias("node"), "b").groupBy("node").agg(F.min(F.struct(F.xxhash64(F.lit(r), "b").alias("p"), "b")).alias("m"))
        hooks = near.select("node", F.when(F.col("m.p") < F.xxhash64(F.lit(r), "node"), F.col("m.b")).otherwise(F.col("node")).alias("up"))
        further = hooks.select(F.col("node").alias("up"), F.col("up").alias("up2"))
        jumped = Stage(hooks.join(further, "up").select("node", F.col("up2").alias("up")), "hooks")
        to = jumped.df
        moved = (
            live.df.join(to.select(F.col("node").alias("a"), F.col("up").alias("ua")), "a").join(to.select(F.col("node").alias("b"), F.col("up").alias("ub")), "b")
            .where("ua <> ub").select(F.least("ua", "ub").alias("a"), F.greatest("ua", "ub").alias("b")).distinct()
        )
        nxt = Stage(moved, "edges")
        live.drop()
        maps.append(jumped)
        live = nxt
    if not maps:
        return spark.createDataFrame([], "node long, root long")
    root = maps[-1].df.select("node", F.col("up").alias("root"))
    for m in reversed(maps[:-1]):
        later = root.select(F.col("node").alias("up"), "root")
        root = Stage(m.df.join(later, "up", "left").select("node", F.coalesce("root", "up").alias("root")), "roots").df
    return root


def _shared_hits(tokens: DataFrame, owner: str, label: str, rounds: int, mark: str = "mark") -> DataFrame:
    """owner, hits: how many of its tokens (owner, mark, h) occur under another mark as well; an owner can be its own mark.

    Counted in disjoint rounds of tokens, which bounds the disk that their shuffles hold at once. A token's rows move
    once and are judged in a window where they arrive: no second shuffle of the tokens' marks, and no join back.
    """
    counted, same = [], Window.partitionBy("h")
    for part in range(rounds):  # a token is in one round: a round's shuffles are gone from the disks before the next one
        rows = tokens.where(F.pmod("h", F.lit(rounds)) == part) if rounds > 1 else tokens
        met = rows.select(owner, F.min(mark).over(same).alias("m0"), F.max(mark).over(same).alias("m1")).where("m0 < m1")
        counted.append(Stage(met.groupBy(owner).agg(F.count("*").alias("hits")), label))
        del rows, met
        release(counted[-1].spark)
    return reduce(DataFrame.unionByName, [c.df for c in counted]).groupBy(owner).agg(F.sum("hits").alias("hits"))


def _supported(sketch: DataFrame, classes: DataFrame, percent: int) -> DataFrame:
    """sid, rep of the sets with enough prefix hashes that occur in another set's prefix.

    Only here hashes and set ids are cut (48 and 40 bits) to move fewer bytes: a hash that meets another by its cut
    lets a set through that the later steps drop. Two sets with one cut id (about d / 2^40 of d sets) would hide
    the hashes that only they share, so a set that shares its cut id passes without a count.
    """
    short = lambda c: F.shiftrightunsigned(c, 24)
    reps = classes.select("sid", F.col("rep").alias("doc_id"))
    once = sketch.where("n > 1 and doc_id is not null").join(small(reps, classes.count(), BROADCAST_ROWS), ["sid", "doc_id"], "left_semi")
    tokens = once.select(short(F.col("sid")).alias("s"), F.explode("prefix").alias("h")).select("s", F.shiftrightunsigned("h", 16).alias("h"))
    hits = _shared_hits(tokens, "s", "hits", ROUNDS, mark="s")
    cut = classes.withColumn("s", short(F.col("sid"))).where("n > 1")
    alike = cut.groupBy("s").agg(F.count("*").alias("sets"))
    judged = cut.join(alike, "s").join(hits, "s", "left")
    return judged.where((F.col("hits") >= _needed(percent)) | (F.col("sets") > 1)).select("sid", "rep")


def _across(sets: DataFrame, labels: DataFrame, n_sets: int, percent: int) -> DataFrame:
    """sid, label of the sets that may be linked with a set of another cluster."""
    prefix = sets.select("sid", F.slice("hashes", F.lit(1), F.col("reach")).alias("p")).join(small(labels, n_sets, BROADCAST_ROWS), "sid")
    tokens = prefix.select("sid", F.col("label").alias("mark"), F.explode("p").alias("h"))
    hits = _shared_hits(tokens, "sid", "cross-hits", 1)
    return sets.select("sid", F.size("hashes").alias("n")).join(hits, "sid").where(F.col("hits") >= _needed(percent)).join(labels, "sid").select("sid", "label")


def _labels(sets: Stage, percent: int) -> DataFrame:
    """sid, label: clusters found by two min-hashes; every step of a cluster is a checked link."""
    first = Stage(_clustered(sets, sets.df.select("sid", "low1"), "low1", percent).groupBy("sid").agg(F.min("label").alias("l1")), "clusters-1")
    tops = sets.df.select("sid", "low2").join(first.df.where("l1 <> sid").select("sid"), "sid", "left_anti")
    second = Stage(_clustered(sets, tops, "low2", percent).groupBy(F.col("sid").alias("l1")).agg(F.min("label").alias("l2")), "clusters-2")
    once = sets.df.select("sid").join(first.df, "sid", "left").withColumn("l1", F.coalesce("l1", "sid"))
    return once.join(second.df, "l1", "left").select("sid", F.coalesce("l2", "l1").alias("label"))


def _alive(sets: DataFrame, labels: DataFrame | None, rounds: int) -> DataFrame:
    """sid, h, df, kin: the tokens that sets of two clusters have, with document frequency and min-hash document.

    Counted in disjoint rounds of tokens like the support, each token's rows moved once: only the few that are alive
    outlast a round on the disks. ``labels`` is None where the sets carry their label: joined here, a large table of
    labels makes every round move all sets.
    """
    rows, found, same = sets if labels is None else sets.select("sid", "hashes").join(labels, "sid"), [], Window.partitionBy("h")
    for part in range(rounds):
        mine = F.filter("hashes", lambda h: F.pmod(h, F.lit(rounds)) == part) if rounds > 1 else F.col("hashes")  # noqa: B023
        grams = rows.select("sid", "label", F.explode(mine).alias("h"))
        over = {"df": F.count("*"), "l0": F.min("label"), "l1": F.max("label"), "kin": F.min(F.xxhash64("sid"))}
        seen = grams.select("sid", "h", *(c.over(same).alias(name) for name, c in over.items())).where("l0 < l1")
        found.append(Stage(seen.select("sid", "h", "df", "kin"), "alive"))
        del grams, seen
        release(found[-1].spark)
    return reduce(DataFrame.unionByName, [f.df for f in found])


def _index(sets: DataFrame, percent: int) -> DataFrame:
    """sid, label, n, key, rare: live prefix tokens alone (rare ones) or in twos (frequent ones)."""
    alive = _alive(sets, None, ROUNDS).groupBy("sid").agg(F.array_sort(F.collect_list(F.struct("df", "h", "kin"))).alias("alive"))
    sized = alive.join(sets.select("sid", "label", F.size("hashes").alias("n")), "sid")
    budget = F.col("n") - F.ceil(F.col("n") * percent / 100) + 2 - (F.col("n") - F.size("alive"))
    prefix = sized.withColumn("take", F.greatest(F.lit(0), F.least(budget, F.size("alive"))).cast("int")).where("take > 0").withColumn("alive", F.slice("alive", 1, F.col("take")))
    rare = prefix.select("sid", "label", "n", F.explode(F.expr(f"transform(filter(alive, x -> x.df <= {RARE}), x -> x.h)")).alias("t")).select("sid", "label", "n", F.xxhash64("t").alias("key"), F.lit(True).alias("rare"), F.lit(False).alias("in_lo"), F.lit(False).alias("in_hi"))
    # frequent tokens whose posting lists have the same min-hash document are one class; 2-combinations are of classes,
    # a class with itself where two of its tokens are there, so near-equal lists do not multiply the combinations
    often = prefix.select("sid", "label", "n", F.expr(f"transform(filter(alive, x -> x.df > {RARE}), x -> x.kin)").alias("f")).where("size(f) > 1")
    kinds = often.select("sid", "label", "n", F.array_distinct("f").alias("d"), "f")
    firsts = kinds.select("sid", "label", "n", "d", F.expr("transform(d, c -> size(filter(f, y -> y = c)) > 1)").alias("twice"), F.posexplode("d").alias("i", "t"))
    twice = lambda at: F.get("twice", F.array_position("d", at).cast("int") - 1)
    partners = F.concat(F.slice("d", F.col("i") + 2, F.size("d")), F.when(F.get("twice", F.col("i")), F.array("t")).otherwise(F.array().cast("array<bigint>")))
    made = firsts.select("sid", "label", "n", "d", "twice", "t", F.explode(partners).alias("u")).withColumns({"lo": F.least("t", "u"), "hi": F.greatest("t", "u")})
    twos = made.select("sid", "label", "n", F.xxhash64("lo", "hi").alias("key"), F.lit(False).alias("rare"), (twice(F.col("lo")) & (F.col("lo") != F.col("hi"))).alias("in_lo"), (twice(F.col("hi")) & (F.col("lo") != F.col("hi"))).alias("in_hi"))
    return rare.unionByName(twos)


def _links(index: Stage, sets: Stage, percent: int) -> DataFrame:
    """a, b: linked labels. Rare lists (at most RARE rows) give distinct pairs, frequent ones pairs of blocks."""
    lists = index.df.groupBy("key", "rare").agg(
        F.count("*").alias("m"), F.min("label").alias("l0"), F.max("label").alias("l1"), F.sum(F.pmod(F.xxhash64("sid"), F.lit(1 << 40))).alias("g1"), F.sum(F.pmod(F.xxhash64(F.lit(1), "sid"), F.lit(1 << 40))).alias("g2"), F.bool_and("in_lo").alias("in_lo"), F.bool_and("in_hi").alias("in_hi")
    ).where("l0 < l1 and not in_lo and not in_hi")  # if all members hold one of the classes twice, that class's own list has them all
    lists = Stage(lists.groupBy("rare", "m", "g1", "g2").agg(F.min("key").alias("key")), "lists")  # equal lists are compared once
    listed = index.df.join(lists.df.select("key", "rare", "m"), ["key", "rare"])

    left = listed.where("rare").select("key", F.col("sid").alias("x"), F.col("label").alias("lx"), F.col("n").alias("nx"))
    right = listed.where("rare").select("key", F.col("sid").alias("y"), F.col("label").alias("ly"), F.col("n").alias("ny"))
    near = (F.col("x") < F.col("y")) & (F.col("lx") != F.col("ly")) & (100 * F.least("nx", "ny") >= percent * F.greatest("nx", "ny"))
    pairs = Stage(left.join(right, "key").where(near).select("x", "y", F.least("lx", "ly").alias("a"), F.greatest("lx", "ly").alias("b")).distinct(), "pairs")
    members = Stage(pairs.df.select(F.col("x").alias("sid")).union(pairs.df.select("y")).distinct(), "pair-members")
    used = Stage(sets.df.select("sid", "hashes").join(small(members.df, members.df.count(), BROADCAST_ROWS), "sid"), "pair-sets")
    both = pairs.df.join(used.df.select(F.col("sid").alias("x"), "hashes"), "x").join(used.df.select(F.col("sid").alias("y"), F.col("hashes").alias("other_hashes")), "y")
    found = both.select("a", "b", "hashes", "other_hashes").mapInArrow(lean(_check_pairs(percent)), "a long, b long")

    dealt = listed.where("not rare").withColumn("blocks", F.ceil(F.col("m") / BLOCK).cast("int")).withColumn("block", F.pmod(F.xxhash64("sid", "key"), F.col("blocks")).cast("int"))
    tasks = Stage(dealt.select("key", "sid", "label", "block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")).select(
        "key", "sid", "label", "block", F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi")
    ), "block-tasks")
    boxed = sets.df.select("sid", "hashes").join(small(tasks.df, tasks.df.count(), BROADCAST_ROWS), "sid")
    return found.union(boxed.groupBy("key", "lo", "hi").applyInArrow(_compare(percent), "a long, b long")).distinct()


def near_components(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", percent: int = 75, width: int = 5) -> DataFrame:
    """One row per input row: doc_id, n_shingles, component_id (smallest doc_id reachable by links)."""
    spark = docs.sparkSession
    texts = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))
    sketch = Stage(texts.mapInArrow(lean(_sketch(percent, width)), "doc_id long, sid long, n long, prefix array<long>"), "sketch")
    base = Stage(sketch.df.select("doc_id", "sid", "n"), "set-ids")
    classes = Stage(base.df.where("n > 0 and doc_id is not null").groupBy("sid").agg(F.min("doc_id").alias("rep"), F.count("*").alias("m"), F.min("n").alias("n")), "classes")
    chosen = settled(lambda: _supported(sketch.df, classes.df, percent), "survivors")
    sketch.drop()
    n_chosen = chosen.df.count()

    wanted = small(chosen.df.withColumnRenamed("rep", "doc_id"), n_chosen, BROADCAST_ROWS)
    full = texts.join(wanted, "doc_id").select("sid", "text").mapInArrow(lean(_full_sets(percent, width)), "sid long, reach int, same boolean, low1 long, low2 long, hashes array<long>")
    sets = Stage(full.where("same").drop("same"), "sets")
    chosen.drop()
    if (n_sets := sets.df.count()) > n_chosen:  # repeated rows of a representative
        repeated, sets = sets, Stage(sets.df.dropDuplicates(["sid"]), "sets-once")
        repeated.drop()
    labels = settled(lambda: _labels(sets, percent), "labels")

    across = settled(lambda: _across(sets.df, labels.df, n_sets, percent), "across")
    open_sets = Stage(sets.df.select("sid", "hashes").join(small(across.df, across.df.count(), BROADCAST_ROWS), "sid"), "open-sets")
    for spent in (sets, across):
        spent.drop()
    release(spark)
    index = settled(lambda: _index(open_sets.df, percent), "index")
    links = settled(lambda: _links(index, open_sets, percent), "links")
    for spent in (index, open_sets):
        spent.drop()

    # cluster -> component on the (distinct) labels, then cluster -> set, then set -> row
    lows = labels.df.join(classes.df.select("sid", "rep"), "sid").groupBy("label").agg(F.min("rep").alias("low"), F.count("*").alias("m"))
    rooted = settled(lambda: lows.join(contract(links.df).withColumnRenamed("node", "label"), "label", "left").withColumn("root", F.coalesce("root", "label")), "rooted")
    tops = rooted.df.groupBy("root").agg(F.min("low").alias("component_id"), F.count("*").alias("m"))

    def members() -> DataFrame:
        of_label = spread_join(rooted.df.select("label", "root"), tops.select("root", "component_id"), ["root"], "label", tops.select("root", "m"))
        of_set = spread_join(labels.df.select("sid", "label"), of_label.select("label", "component_id"), ["label"], "sid", rooted.df.select("label", "m"))
        return classes.df.select("sid", "rep", "m").join(of_set.select("sid", "component_id"), "sid", "left").select("sid", "m", F.coalesce("component_id", "rep").alias("component_id"))

    known = settled(members, "members")
    for spent in (links, rooted, labels, classes):
        spent.drop()
    out = spread_join(base.df.select("doc_id", "sid", F.col("n").alias("n_shingles")), known.df.select("sid", "component_id"), ["sid"], "doc_id", known.df.select("sid", "m"))
    alone = (F.col("n_shingles") == 0) | F.col("doc_id").isNull()
    return out.select("doc_id", "n_shingles", F.when(alone, F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"))


def keep_one_per_component(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows whose document represents its component; documents without words all stay.

    Joined with the ids that go, as a rule far fewer than those that stay: up to the bound for broadcasts no text moves.
    """
    id_tmp = fresh(docs, "goes")

    def going() -> DataFrame:
        stays = F.bool_or(F.col("component_id").eqNullSafe(F.col("doc_id"))).alias("stays")
        return near_components(docs, id_col, text_col).groupBy("doc_id").agg(stays).where("not stays").select(F.col("doc_id").alias(id_tmp))

    gone = settled(going, "gone-near")
    return docs.join(small(gone.df, gone.df.count(), BROADCAST_ROWS), F.col(id_col).cast("long") == F.col(id_tmp), "left_anti")
