import random

import pytest

from levelsort.operators import baselines, cost, doubling, gridexchange, lcp, merge
from levelsort.operators import mergesort as ms
from levelsort.functions import text
from levelsort.plans.levels import LevelPlan, plan_equal, plan_node_aligned
from levelsort.sources import strings as sources

TOY = ["barn", "cat", "bar", "base", "cab"]
EDGE = ["", "a", "aa", "aaa", "é", "z", "a", "same", "same", "same"]


def strings(spark, values):
    return spark.createDataFrame([(i, 0, v) for i, v in enumerate(values)], "src_id bigint, pos int, s string")


def expected(values):
    return [(r, i) for r, (_, i) in enumerate(sorted((v.encode(), i) for i, v in enumerate(values)), 1)]


def ranks(df):
    return sorted((r["rank"], r["src_id"]) for r in df.collect())


def test_plans():
    assert plan_node_aligned(192, 3, 48).factors == (2, 2, 48)
    assert plan_node_aligned(192, 2, 48).factors == (4, 48)
    assert plan_equal(64, 3).factors == (4, 4, 4)
    assert plan_node_aligned(4, 3, 48).factors == (4,)
    with pytest.raises(ValueError):
        LevelPlan(8, (3, 3))


@pytest.mark.parametrize("values", [TOY, EDGE, ["x"], []])
@pytest.mark.parametrize("factors", [(4,), (2, 2), (3,)])
def test_all_sorters_agree(spark, values, factors):
    s, plan = strings(spark, values), LevelPlan(__import__("math").prod(factors), factors)
    want = expected(values)
    assert ranks(ms.level_merge_sort(ms.place_blocks(s, plan.lanes), plan).ranked()) == want
    assert ranks(doubling.prefix_doubling_sort(s, plan, d0=2)) == want
    assert ranks(baselines.spark_sort(s)) == want
    assert ranks(baselines.hypercube_sort(s, plan.lanes)) == want


@pytest.mark.parametrize("options", [{"sampling": "chars"}, {"assign": "bounded_chars"}, {"assign": "prefix_strings"}, {"tie_break": True}, {"v": 16}, {"sample_sort": "hypercube"}, {"hops": 3}])
def test_options_do_not_change_the_order(spark, options):
    rnd = random.Random(3)
    values = ["".join(rnd.choice("ab") for _ in range(rnd.randint(1, 12))) for _ in range(300)]
    plan = LevelPlan(8, (2, 4))
    assert ranks(ms.level_merge_sort(ms.place_blocks(strings(spark, values), 8), plan, **options).ranked()) == expected(values)


def test_toy_numbers(spark):
    t = lcp.lcp_array(strings(spark, TOY)).orderBy("rank").collect()
    assert [r["s"] for r in t] == ["bar", "barn", "base", "cab", "cat"]
    assert [r["h"] for r in t] == [None, 3, 2, 0, 2]
    assert sum(r["dist"] for r in lcp.dist_prefix(lcp.lcp_array(strings(spark, TOY))).collect()) == 17
    dist, trace = doubling.approx_dist(strings(spark, TOY), d0=2)
    assert [x["n_retired"] for x in trace] == [0, 5]
    assert sum(r["dist_approx"] for r in dist.collect()) == 20


def test_approximation_is_one_sided_even_with_collisions(spark):
    s = strings(spark, [f"{i % 7}{i}" * 3 for i in range(200)])
    exact = {r["src_id"]: r["dist"] for r in lcp.dist_prefix(lcp.lcp_array(s)).collect()}
    for m in (1 << 40, 97):
        assert all(r["dist_approx"] >= exact[r["src_id"]] for r in doubling.approx_dist(s, m=m)[0].collect())


def test_merge_kernels():
    rnd = random.Random(5)
    rows = [("".join(rnd.choice("abc") for _ in range(rnd.randint(0, 9))), i, 0) for i in range(120)]
    runs = [sorted(rows[k::4]) for k in range(4)]
    out, h, looked = merge.merge_with_lcp(runs)
    plain, looked_plain = merge.merge_plain(runs)
    assert out == plain == sorted(rows)
    import os

    assert h[1:] == [len(os.path.commonprefix([a[0], b[0]])) for a, b in zip(out, out[1:], strict=False)]
    assert looked < looked_plain


def test_loser_tree_on_odd_numbers_of_runs():
    for seed in range(60):
        rnd = random.Random(seed)
        k = rnd.randint(1, 9)
        rows = [("".join(rnd.choice("ab") for _ in range(rnd.randint(0, 7))), i, 0) for i in range(rnd.randint(0, 60))]
        runs = [sorted(rows[j::k]) for j in range(k)]
        assert merge.merge_with_lcp(runs)[0] == merge.merge_plain(runs)[0] == sorted(rows)


@pytest.mark.parametrize("texts", [["banana", "é😀a\né", "banana", "", None, "aaaaaaaaa"], ["x"], [None, ""]])
def test_suffix_ranks_equal_sorted_suffixes(spark, texts):
    docs = spark.createDataFrame(list(enumerate(texts)), "item_id bigint, text string")
    want = sorted((t[i:].encode(), d, i) for d, t in enumerate(texts) if t for i in range(len(t)))
    got = sorted(map(tuple, doubling.suffix_ranks(docs).collect()))
    assert got == [(r, d, i) for r, (_, d, i) in enumerate(want, 1)]


def test_grid_exchange_arrives_and_stays_on_lines(spark):
    rows = spark.range(600).selectExpr("cast(id % 12 AS int) AS sender", "cast(id * 7 % 12 AS int) AS target", "cast(id AS string) AS s")
    out, hops = gridexchange.grid_exchange(rows, (3, 4))
    assert out.where(ms.F.spark_partition_id() != ms.F.col("target")).isEmpty() and out.count() == 600
    for h, same in zip(hops, (lambda x: x % 4, lambda x: x // 4), strict=True):
        assert all(same(r["src"]) == same(r["dst"]) for r in h.collect())


def test_front_coding_round_trip(spark):
    placed = ms.place_hash(strings(spark, EDGE + TOY), 3)
    back = lcp.front_decode(lcp.front_encode(placed))
    assert sorted(map(tuple, back.select("src_id", "s").collect())) == sorted(enumerate(EDGE + TOY))


def test_cost_forms():
    assert cost.grid_hops(64, 2) == (14, 2)
    assert cost.crossover([1, 2, 4], [3, 3, 3], [4, 3, 1]) == 2
    assert abs(cost.slope([1, 2, 4], [2, 4, 8]) - 1) < 1e-9
    one, two = (cost.merge_sort_time(10**6, 10**8, 10**7, 4096, k, 1000)["partition"] for k in (1, 2))
    assert two < one  # more levels make partitioning cheaper


def exchanged(df):
    """The columns of each shuffle in the plan."""

    def listed(seq):
        return [seq.apply(i) for i in range(seq.size())]

    def moved(node):
        own = [[a.name() for a in listed(node.output())]] if node.nodeName() == "Exchange" else []
        return own + [x for c in listed(node.children()) for x in moved(c)]

    plan = df._jdf.queryExecution().executedPlan()
    return moved(plan.initialPlan() if plan.nodeName() == "AdaptiveSparkPlan" else plan)


def test_a_doubling_round_moves_no_strings(spark):
    s = strings(spark, [f"{'x' * (i % 40)}{i % 90}" for i in range(2000)])
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        run = doubling.Doubling(s, threshold=0, buckets=4)
        fps = doubling.prints(run.strings.df, 16)
        active = doubling.marked(fps, k=2, lanes=8).where("dup").select("src_id", "pos")
        nxt = doubling.prints(run.strings.df.join(active, doubling.LOCATOR, "left_semi"), 32)
        sent = exchanged(nxt)
        # the strings are read in their buckets; fingerprints, counts and locators are all that is exchanged
        assert sent and not any("s" in columns for columns in sent), sent
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    run.strings.drop()


def test_a_level_exchanges_the_strings_once(spark):
    s = strings(spark, [str(i * 7919 % 1000) for i in range(1000)])
    rows = s.repartition(4).cache()
    sample = ms.draw_samples(ms.numbered(rows).select(ms.F.lit(0).alias("grp"), "lane", "lpos", "src_id", "pos", "s"), 8, 2, placed=False)
    assert not any("src_id" in columns for columns in exchanged(sample))  # sampling reads the strings where they lie
    out = ms.level_merge_sort(rows, LevelPlan(8, (2, 4)))
    assert ranks(out.ranked()) == expected([str(i * 7919 % 1000) for i in range(1000)])
    for i, (state, splits, r) in enumerate(zip(out.states, out.cuts, (2, 4), strict=True)):
        routed = ms.bucketize(state, splits, r).withColumn("target", ms.grid_target(8 if i == 0 else 4, r))
        moved = ms.to_lanes(routed.select("target", "src_id", "pos", "s"), 8, "target")
        assert sum("src_id" in columns for columns in exchanged(moved)) == 1


def test_long_common_prefixes_have_no_cap(spark):
    long = "a" * 300_000
    t = lcp.lcp_array(strings(spark, [long + "b", long + "c", "z"])).orderBy("rank").collect()
    assert [r["h"] for r in t] == [None, 300_000, 0]
    two = strings(spark, ["abcx", "abcyy", "abc"]).agg(text.common_prefix(ms.F.col("s")).alias("p")).first()["p"]
    assert two == "abc"


@pytest.mark.parametrize(("n", "length", "ratio"), [(7919, 60, 0.5), (300, 2000, 0.25), (50, 40, 1.0)])
def test_generated_strings(spark, n, length, ratio):
    rows = sources.dn_strings(spark.range(n).withColumnRenamed("id", "i"), n, length, ratio)
    assert rows.select("s").distinct().count() == n
    assert {r["len"] for r in rows.select(ms.F.length("s").alias("len")).distinct().collect()} == {length}
    got = lcp.string_stats(lcp.lcp_array(rows)).first()["dn_ratio"]
    assert abs(got - max(ratio, sources.DN_DIGITS / length)) < 0.15


def test_negative_locators_and_ties(spark):
    values = ["dup", "dup\x00", "du"] * 40
    rows = spark.createDataFrame([(-i * 37, -i % 5, v) for i, v in enumerate(values)], "src_id bigint, pos int, s string")
    want = [(r, x) for r, (_, x, _) in enumerate(sorted((v.encode(), -i * 37, -i % 5) for i, v in enumerate(values)), 1)]
    assert ranks(ms.level_merge_sort(rows, LevelPlan(8, (2, 4)), tie_break=True).ranked()) == want


def test_read_lines_and_keys(spark, tmp_path):
    (tmp_path / "a.txt").write_text("one\ntwo\n")
    (tmp_path / "b.txt").write_text("three\n")
    got = sources.read_lines(spark, str(tmp_path))
    assert dict(got.dtypes) == {"src_id": "bigint", "pos": "int", "s": "string"}
    rows = got.collect()
    assert sorted(r["s"] for r in rows) == ["one", "three", "two"] and all(r["src_id"] >= 0 and r["pos"] >= 0 for r in rows)
    assert len({(r["src_id"], r["pos"]) for r in rows}) == 3
    numbers = [-(1 << 63), -5, -1, 0, 7, (1 << 63) - 1]
    df = spark.createDataFrame([(x,) for x in numbers], "x bigint")
    keys = [r["k"] for r in df.select("x", sources.as_key(df, ["x"]).alias("k")).orderBy("k").collect()]
    assert [r["x"] for r in df.select("x", sources.as_key(df, ["x"]).alias("k")).orderBy("k").collect()] == numbers and keys == sorted(keys)


def _bytes(path) -> int:
    return sum(f.stat().st_size for f in path.rglob("part-*"))


def test_moves_alone_equal_those_of_the_sort_and_leave_no_strings(spark, tmp_path):
    from pyspark.sql import functions as F

    rows = spark.range(4000).select("id", F.lit(0).alias("pos"), F.concat(F.lit("same start "), F.md5(F.col("id").cast("string")).substr(1, 9)).alias("s")).withColumnRenamed("id", "src_id")
    placed, plan = ms.place_blocks(rows, 8), LevelPlan(8, (2, 4))
    for compress in (False, True):
        whole = ms.level_merge_sort(placed, plan, compress=compress).moves
        spark.sparkContext.setCheckpointDir(str(tmp_path / str(compress)))
        alone = ms.level_moves(placed, plan, compress=compress)
        for a, b in zip(whole, alone, strict=True):
            assert sorted(map(tuple, a.select(*b.columns).collect())) == sorted(map(tuple, b.collect()))
        assert 0 < _bytes(tmp_path / str(compress)) < 40_000  # one copy of the strings has over 80,000 characters
    assert len(ms.level_moves(placed, plan, levels=1)) == 1


def test_spent_sort_equals_the_sort_and_keeps_the_last_strings_only(spark, tmp_path):
    from pyspark.sql import functions as F

    rows = spark.range(4000).select("id", F.lit(0).alias("pos"), F.concat(F.lit("same start "), F.md5(F.col("id").cast("string"))).alias("s")).withColumnRenamed("id", "src_id")
    placed, plan = ms.place_blocks(rows, 8).localCheckpoint(), LevelPlan(8, (2, 4))
    left, runs = [], []
    for spend in (False, True):
        spark.sparkContext.setCheckpointDir(str(tmp_path / str(spend)))
        runs.append(ms.level_merge_sort(placed, plan, compress=True, spend=spend))
        left.append(_bytes(tmp_path / str(spend)))
    whole, spent = runs
    assert left[1] < left[0] / 2  # one table of strings of three
    assert sorted(map(tuple, whole.rows.collect())) == sorted(map(tuple, spent.rows.collect()))
    for a, b in zip(whole.moves, spent.moves, strict=True):
        assert sorted(map(tuple, a.collect())) == sorted(map(tuple, b.collect()))
