"""Registered queries of the cost measures over whole runs: volumes per level and method, primitives, closed forms, counters."""

from __future__ import annotations

from pyspark.sql import Window as W
from pyspark.sql import functions as F

from levelsort.catalog.sorting import _DIST, PLANS, V, P, _one, _state, lcp_table_sql, level_one_sql, ranked_sql, rounds_sql
from levelsort.operators import baselines, cost, doubling, lcp
from levelsort.operators import mergesort as ms
from levelsort.plans.levels import LevelPlan, plan_equal
from levelsort.registry import add
from levelsort.sources.strings import SETS, string_set
from levelsort.staging import cut, forget, scratch

ALPHA, BETA = 1e-5, 1e-9


# --- volumes: every level moves every character once; prefix doubling moves only the prefixes -------------------------
def _run(spark, d, name: str, method: str, plan: LevelPlan) -> ms.Sorted:
    s = string_set(spark, d, name)
    return ms.level_merge_sort(ms.place_blocks(s, plan.lanes), plan) if method == "lms" else doubling.sort_prefixes(s, plan, d0=4, growth=2, finish=False)


def _volumes(name: str, method: str, k: int):
    def query(spark, d):
        moves = _run(spark, d, name, method, PLANS[k]).moves
        rows = [m.agg(F.sum("n").alias("strings"), F.sum("chars").alias("chars")).select(F.lit(i).alias("level"), "strings", "chars") for i, m in enumerate(moves, 1)]
        out = rows[0]
        for r in rows[1:]:
            out = out.unionByName(r)
        return out

    return query


for _k in (1, 2, 3):
    _levels = f"(SELECT CAST(unnest(range(1, {_k + 1})) AS INT) AS level)"
    for _n in ("lines", "url"):
        add(f"cost_volume_lms{_k}_{_n}", _volumes(_n, "lms", _k), f"SELECT level, count(*) AS strings, CAST(sum(length(s)) AS BIGINT) AS chars FROM {_levels} CROSS JOIN ({SETS[_n][1]}) GROUP BY level")
        add(f"cost_volume_pds{_k}_{_n}", _volumes(_n, "pds", _k), rounds_sql(_n, 17) + f"SELECT level, count(*) AS strings, CAST(sum(least(len, dist_approx)) AS BIGINT) AS chars FROM {_levels} CROSS JOIN retired GROUP BY level")


# --- primitives -------------------------------------------------------------------------------------------------------
_line_one = level_one_sql("lines", 4)
add("prim_prefix_sum", lambda spark, d: ms.lane_sizes(_state(spark, d, "lines")).select("lane", F.coalesce(F.sum("n").over(W.orderBy("lane").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)).cast("bigint").alias("before")),
    _line_one + "SELECT lane, CAST(sum(n) OVER (ORDER BY lane) - n AS BIGINT) AS before FROM sizes WHERE n > 0")
add("prim_allreduce", lambda spark, d: ms.lane_sizes(_state(spark, d, "lines")).agg(F.sum("n").alias("n"), F.sum("chars").alias("chars")), _line_one + "SELECT CAST(sum(n) AS BIGINT) AS n, CAST(sum(chars) AS BIGINT) AS chars FROM sizes")
add("prim_allgather", lambda spark, d: _one(spark, d)[2].groupBy("grp").agg(F.array_join(F.array_sort(F.collect_list("s")), "|").alias("all_splitters")).select("all_splitters"), _line_one + "SELECT string_agg(s, '|' ORDER BY s) AS all_splitters FROM f")
add("prim_broadcast_sizes", lambda spark, d: _one(spark, d)[2].agg(F.count("*").alias("strings"), F.sum(F.length("s")).alias("chars")), _line_one + "SELECT count(*) AS strings, CAST(sum(length(s)) AS BIGINT) AS chars FROM f")


# --- closed forms over counted quantities -----------------------------------------------------------------------------
def _sizes(spark, d, name: str):
    return lcp.dist_prefix(lcp.lcp_array(string_set(spark, d, name))).agg(F.count("*").alias("n"), F.sum(F.least("dist", "len")).alias("dist"))


add("cost_local_work", lambda spark, d: _sizes(spark, d, "lines").select("n", "dist", F.round(F.col("n") / P * F.log2("n") + F.col("dist") / P, 3).alias("work")),
    f"SELECT n, dist, round(n / {P} * log2(n) + dist / {P}, 3) AS work FROM (SELECT count(*) AS n, CAST(sum({_DIST.format('')}) AS BIGINT) AS dist FROM ({lcp_table_sql('lines')}))")
add("cost_model_time", lambda spark, d: cost.messages(ms.level_merge_sort(ms.place_blocks(string_set(spark, d, "lines"), P), PLANS[2]).moves).where("level = 1").select(F.round(1e6 * (ALPHA * F.col("max_messages_per_lane") + 8 * BETA * F.col("chars_max_lane")), 4).alias("micros")),
    level_one_sql("lines", PLANS[2].factors[0]) + f"SELECT round(1e6 * ({ALPHA} * (SELECT max(c) FROM (SELECT count(DISTINCT target) AS c FROM grid GROUP BY lane)) + 8 * {BETA} * (SELECT max(c) FROM (SELECT sum(chars) AS c FROM grid GROUP BY target))), 4) AS micros")


def _lower_bound(spark, d):
    s = string_set(spark, d, "url")
    letters = s.select(F.explode(F.split("s", "")).alias("c")).where("c <> ''").agg(F.countDistinct("c").alias("sigma"))
    return _sizes(spark, d, "url").crossJoin(F.broadcast(letters)).select("n", "sigma", F.round(F.col("dist") / F.col("n"), 6).alias("avg_dist"), F.round(F.log2("n") / F.log2("sigma"), 6).alias("bound"))


add("dn_lower_bound", _lower_bound,
    f"SELECT n, sigma, round(dist / n, 6) AS avg_dist, round(log2(n) / log2(sigma), 6) AS bound FROM (SELECT count(*) AS n, CAST(sum({_DIST.format('')}) AS BIGINT) AS dist FROM ({lcp_table_sql('url')})) CROSS JOIN (SELECT count(DISTINCT c) AS sigma FROM (SELECT unnest(string_split(s, '')) AS c FROM ({SETS['url'][1]})) WHERE c <> '')")

# --- the string-aware hypercube sort, and what merging looks at ---------------------------------------------------------
add("hc_lcp_url", lambda spark, d: baselines.hypercube_sort(string_set(spark, d, "url"), P, with_lcp=True), ranked_sql("url"))
add("hc_lcp_lines", lambda spark, d: baselines.hypercube_sort(string_set(spark, d, "lines"), P, with_lcp=True), ranked_sql("lines"))
add("hc_merge_looked", lambda spark, d: baselines.hypercube_merge_work(string_set(spark, d, "url"), P))


# --- grid of counters: how messages, volume and balance move with p, k and the method ------------------------------------
def counters(spark, d, name: str = "lines", lanes: tuple[int, ...] = (16, 64)):
    """method, p, k, level, messages, max_messages_per_lane, chars_total, chars_max_lane, sample_strings."""
    out, s = None, string_set(spark, d, name)
    with scratch(spark):
        prefixes = cut(doubling.prefixes(s), keep=True)
    for p in lanes:
        for method, rows in (("lms", s), ("pds", prefixes)):
            with scratch(spark):
                placed = cut(ms.place_blocks(rows, p), keep=True)
            for k in (1, 2, 3):
                drawn = sum(p1 * (V + 1) for p1 in plan_equal(p, k).group_sizes)
                one = cost.messages(ms.level_moves(placed, plan_equal(p, k))).select(F.lit(method).alias("method"), F.lit(p).alias("p"), F.lit(k).alias("k"), "level", "messages", "max_messages_per_lane", "chars_total", "chars_max_lane", F.lit(drawn).alias("sample_strings"))
                out = one if out is None else out.unionByName(one)
            forget(placed)
    forget(prefixes)
    return out


add("counters_grid", counters)
