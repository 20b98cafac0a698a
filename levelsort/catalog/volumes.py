"""Registered queries: front-coded exchange, volume per phase, conditions of the bounds, characteristics of the sets."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelsort.catalog.sorting import _DIST, PLANS, P, _docs, _placed_run, _suffix_sql, lcp_table_sql, level_one_sql, levels_sql, ranked_sql
from levelsort.functions.text import lcp_sql, register
from levelsort.operators import cost, doubling, gridexchange, lcp
from levelsort.operators import mergesort as ms
from levelsort.plans.levels import plan_equal, plan_node_aligned
from levelsort.registry import add
from levelsort.sources.sinks import manifest
from levelsort.sources.strings import SETS, string_set
from levelsort.staging import cut, scratch, shared_dir
from levelsort.streaming import events

DN = ("dn000", "dn025", "dn050", "dn075", "dn100")


def stacked(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


# --- exchange with front coding -----------------------------------------------------------------------------------
for _n in ("url", "lines"):
    add(f"lms2_{_n}_front", lambda spark, d, n=_n: ms.level_merge_sort(string_set(spark, d, n), PLANS[2], compress=True).ranked(), ranked_sql(_n))


def bytes_per_string(spark, d):
    """Each set goes through the whole front-coded sort, one set at a time; the volume of its first exchange is given."""
    runs = []
    for n in DN:
        with scratch(spark):
            run = _placed_run(spark, d, n, 2, compress=True, spend=True)
            runs.append((n, cut(run.moves[0], keep=True)))
    return stacked([m.agg(F.round(F.sum("chars") / F.sum("n"), 6).alias("raw"), F.round(F.sum("coded") / F.sum("n"), 6).alias("coded")).select(F.lit(n).alias("name"), "raw", "coded") for n, m in runs])


def bytes_per_string_sql(name: str) -> str:
    one = levels_sql(name, PLANS[2].factors[:1])
    pairs = one + "SELECT s, lag(s) OVER (PARTITION BY lane, bucket ORDER BY s, src_id, pos) AS t FROM bucketed1"
    return f"SELECT '{name}' AS name, round(sum(length(s)) / count(*), 6) AS raw, round(sum(length(s) - coalesce(h, 0)) / count(*), 6) AS coded FROM ({lcp_sql(pairs)})"


add("cost_bytes_per_string", bytes_per_string, " UNION ALL ".join(bytes_per_string_sql(n) for n in DN))


def front_ratio(spark, d):
    tables = [(n, lcp.lcp_array(string_set(spark, d, n))) for n in ("lines", "markup", "plain", "url", "customer")]
    tail = F.sum(F.length("s") - F.coalesce("h", F.lit(0)))
    return stacked([t.agg(F.sum(F.length("s")).alias("chars"), tail.alias("tails"), F.round(tail / F.sum(F.length("s")), 6).alias("ratio")).select(F.lit(n).alias("name"), "chars", "tails", "ratio") for n, t in tables])


add("front_ratio_by_set", front_ratio, " UNION ALL ".join(
    f"SELECT '{n}' AS name, CAST(sum(length(s)) AS BIGINT) AS chars, CAST(sum(length(s) - coalesce(h, 0)) AS BIGINT) AS tails, round(sum(length(s) - coalesce(h, 0)) / sum(length(s)), 6) AS ratio FROM ({lcp_table_sql(n)})"
    for n in ("lines", "markup", "plain", "url", "customer")))


# --- volume per phase and level -----------------------------------------------------------------------------------
def phase_volume(spark, d, k: int):
    run = _placed_run(spark, d, "lines", k)
    rows = []
    for i, (v, f, m) in enumerate(zip(run.samples, run.cuts, run.moves, strict=True), 1):
        drawn = v.agg(F.count("*").alias("sample_strings"), F.sum(F.length("s")).alias("sample_chars"))
        cuts = f.agg(F.count("*").alias("splitters"))
        moved = m.agg(F.sum("chars").alias("exchange_chars"))
        rows.append(drawn.crossJoin(F.broadcast(cuts)).crossJoin(F.broadcast(moved)).select(F.lit(i).alias("level"), "sample_strings", "sample_chars", "splitters", "exchange_chars"))
    return stacked(rows)


for _k in (2, 3):
    add(f"cost_phase_volume_k{_k}", lambda spark, d, k=_k: phase_volume(spark, d, k), levels_sql("lines", PLANS[_k].factors) + " UNION ALL ".join(
        f"SELECT CAST({i} AS INT) AS level, (SELECT count(*) FROM v{i}) AS sample_strings, CAST((SELECT sum(length(s)) FROM v{i}) AS BIGINT) AS sample_chars, (SELECT count(*) FROM f{i}) AS splitters, CAST((SELECT sum(chars) FROM grid{i}) AS BIGINT) AS exchange_chars"
        for i in range(1, _k + 1)))

# --- conditions of the bounds over counted sets -------------------------------------------------------------------
CONDITION_GRID = [(p, k) for p in (64, 1024, 49152) for k in (1, 2, 3)]


def conditions(spark, d):
    n, chars, l_max = string_set(spark, d, "lines").agg(F.count("*"), F.sum(F.length("s")), F.max(F.length("s"))).first()
    rows = [(p, k, cost.simplified_holds(chars, l_max, p, k), cost.levels_hold(p, k), cost.filter_holds(n, 1 << 40, p, k), cost.approximation_holds(n, p, k), cost.single_level_scales(n, p)) for p, k in CONDITION_GRID]
    return spark.createDataFrame(rows, "p int, k int, simplified boolean, levels boolean, filter_ok boolean, approximation boolean, single_level boolean")


add("cost_conditions", conditions, f"""SELECT CAST(p AS INT) AS p, CAST(k AS INT) AS k, l_max <= chars / (k * k * p ** (1 + 1.0 / k) * log2(p)) AND few AS simplified, few AS levels,
    n > k * k * p ** (1 + 1.0 / k) * log2(p) AND {1 << 40} >= exp(1.0) * n AS filter_ok, n / p > k * k * p ** (1.0 / k) * log2(p) * log2(log2(p)) AND few AS approximation, n >= CAST(p AS DOUBLE) * p * log2(p) AS single_level
    FROM (SELECT *, k <= log2(p) / (2 * log2(log2(p))) AS few FROM (VALUES {', '.join(map(str, CONDITION_GRID))}) t(p, k)) CROSS JOIN (SELECT count(*) AS n, sum(length(s)) AS chars, max(length(s)) AS l_max FROM ({SETS['lines'][1]}))""")

# --- characteristics, neighbours, skew ----------------------------------------------------------------------------
for _n in ("url", "lines", "markup"):
    add(f"alphabet_{_n}", lambda spark, d, n=_n: lcp.alphabet(string_set(spark, d, n)),
        f"SELECT (SELECT count(DISTINCT s) FROM ({SETS[_n][1]})) AS n_unique, count(DISTINCT c) AS sigma FROM (SELECT unnest(string_split(s, '')) AS c FROM ({SETS[_n][1]})) WHERE c <> ''")
for _n in ("url", "lines"):
    add(f"lcp_neighbors_{_n}", lambda spark, d, n=_n: lcp.lcp_array(string_set(spark, d, n)).select("rank", "h", "h2"), f"SELECT rank, h, h2 FROM ({lcp_table_sql(_n)})")
add("dn_generator_stats", lambda spark, d: stacked([lcp.string_stats(lcp.lcp_array(string_set(spark, d, n))).select(F.lit(n).alias("name"), "n", "avg_len", "dn_ratio") for n in DN]),
    " UNION ALL ".join(f"SELECT '{n}' AS name, count(*) AS n, round(sum(length(s)) / count(*), 6) AS avg_len, round(sum({_DIST.format('')}) / sum(length(s)), 6) AS dn_ratio FROM ({lcp_table_sql(n)})" for n in DN))
add("dup_lane_skew", lambda spark, d: cost.imbalance(_placed_run(spark, d, "props", 1).rows, P), level_one_sql("props", 8) + f"SELECT round(max(n) * {P} / sum(n), 6) AS strings, round(max(c) * {P} / sum(c), 6) AS chars FROM (SELECT count(*) AS n, sum(length(s)) AS c FROM bucketed GROUP BY bucket)")
add("manifest_ranges", lambda spark, d: manifest(_placed_run(spark, d, "lines", 1).rows), level_one_sql("lines", 8) + "SELECT bucket AS lane, min(s) AS first, max(s) AS last, count(*) AS n, CAST(sum(length(s)) AS BIGINT) AS chars FROM bucketed GROUP BY bucket")


def sql_lcp(spark, d):
    register(spark)
    string_set(spark, d, "url").createOrReplaceTempView("levelsort_urls")
    return spark.sql("SELECT a.src_id, b.src_id AS other, lcp(a.s, b.s) AS h FROM levelsort_urls a JOIN levelsort_urls b ON b.src_id = a.src_id + 1")


add("sql_lcp_view", sql_lcp, "SELECT src_id, other, h FROM (" + lcp_sql(f"SELECT a.src_id, b.src_id AS other, a.s, b.s AS t FROM ({SETS['url'][1]}) a JOIN ({SETS['url'][1]}) b ON b.src_id = a.src_id + 1") + ")")


def map_counts(spark, d):
    kinds = spark.read.parquet(f"{d}/events.parquet").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = kinds.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    at = lambda kind: F.coalesce(F.try_element_at("m", F.lit(kind)), F.lit(0)).cast("bigint")
    return maps.select("user_id", at("view").alias("views"), at("click").alias("clicks"))


add("fn_map_counts", map_counts, "SELECT user_id, count(*) FILTER (event_type = 'view') AS views, count(*) FILTER (event_type = 'click') AS clicks FROM events GROUP BY user_id")


# --- other ways through a level: samples sorted by hypercube, exchange over a grid, node-aligned levels --------------
add("lms2_lines_hypercube_samples", lambda spark, d: ms.level_merge_sort(string_set(spark, d, "lines"), PLANS[2], sample_sort="hypercube").ranked(), ranked_sql("lines"))
for _i in (1, 2):
    add(f"splitters_hypercube_l{_i}_lines", lambda spark, d, i=_i: _placed_run(spark, d, "lines", 2, sample_sort="hypercube").cuts[i - 1].select("grp", F.col("j").cast("int").alias("j"), "s"),
        levels_sql("lines", PLANS[2].factors) + f"SELECT CAST(grp AS INT) AS grp, j, s FROM f{_i}")
for _h in (2, 3):
    add(f"lms1_lines_grid_{_h}_hops", lambda spark, d, h=_h: ms.level_merge_sort(string_set(spark, d, "lines"), PLANS[1], hops=h).ranked(), ranked_sql("lines"))


def hop_volumes_sql(name: str, factors: tuple[int, ...]) -> str:
    """Volumes per hop and line of the grid: before hop i the first digits are the target's, the rest the sender's."""
    parts = []
    for i in range(len(factors)):
        at = []
        for done in (i, i + 1):
            tail = 1
            for f in factors[done:]:
                tail *= f
            at.append(f"CAST(target // {tail} * {tail} + lane % {tail} AS INT)")
        parts.append(f"SELECT CAST({i + 1} AS INT) AS hop, {at[0]} AS src, {at[1]} AS dst, CAST(sum(n) AS BIGINT) AS n, CAST(sum(chars) AS BIGINT) AS chars FROM grid GROUP BY ALL")
    return level_one_sql(name, P) + " UNION ALL ".join(parts)


for _h in (2, 3):
    add(f"grid_exchange_volume_{_h}", lambda spark, d, h=_h: gridexchange.hop_volumes(_placed_run(spark, d, "lines", 1, hops=h).hops[0]), hop_volumes_sql("lines", plan_equal(P, _h).factors))
for _name, _plan in {"12_lanes": plan_node_aligned(12, 2, 2), "192_lanes": plan_node_aligned(192, 3, 48)}.items():
    add(f"lms_node_aligned_{_name}", lambda spark, d, p=_plan: ms.level_merge_sort(string_set(spark, d, "url"), p).ranked(), ranked_sql("url"))

# --- strong scaling: one set, more lanes ----------------------------------------------------------------------------
SCALING = [(p, k) for p in (4, 8, 16, 32) for k in (1, 2)]


def strong_scaling(spark, d, name: str):
    """p, k, level, messages, max_messages_per_lane, chars_total, chars_max_lane of level sorts of one set on more and more lanes."""
    rows, parts = cut(string_set(spark, d, name)), []
    for p, k in SCALING:
        run = ms.level_merge_sort(ms.place_blocks(rows, p), plan_equal(p, k))
        parts.append(cost.messages(run.moves).select(F.lit(p).alias("p"), F.lit(k).alias("k"), "level", "messages", "max_messages_per_lane", "chars_total", "chars_max_lane"))
    return stacked(parts)


def strong_scaling_sql(name: str) -> str:
    parts = []
    for p, k in SCALING:
        level = """SELECT CAST({1} AS INT) AS p, CAST({2} AS INT) AS k, CAST({0} AS INT) AS level, count(*) AS messages, (SELECT max(c) FROM (SELECT count(DISTINCT target) AS c FROM grid{0} GROUP BY lane)) AS max_messages_per_lane,
            CAST(sum(chars) AS BIGINT) AS chars_total, CAST((SELECT max(c) FROM (SELECT sum(chars) AS c FROM grid{0} GROUP BY target)) AS BIGINT) AS chars_max_lane FROM (SELECT lane, target, sum(chars) AS chars FROM grid{0} GROUP BY ALL)"""
        parts.append("SELECT * FROM (" + levels_sql(name, plan_equal(p, k).factors, p) + " UNION ALL ".join(level.format(i, p, k) for i in range(1, k + 1)) + ")")
    return " UNION ALL ".join(parts)


for _n in ("url", "plain"):
    add(f"strong_scaling_{_n}", lambda spark, d, n=_n: strong_scaling(spark, d, n), strong_scaling_sql(_n))

# --- suffixes ordered without making them, runs of a stream ---------------------------------------------------------
add("suffix_ranks_benchmark", lambda spark, d: doubling.suffix_ranks(_docs(spark, d)), f"SELECT row_number() OVER (ORDER BY s, src_id, pos) AS rank, src_id, pos FROM ({_suffix_sql})")


def stream_runs(spark, d):
    """URLs read as a stream, sorted run by run, the runs merged."""
    where = f"{shared_dir(spark)}/runs-{uuid.uuid4().hex}"
    pages = spark.read.parquet(f"{d}/pages.parquet").schema
    urls = spark.readStream.schema(pages).parquet(f"{d}/pages.parque[t]").select(F.col("page_id").alias("src_id"), F.lit(0).alias("pos"), F.col("url").alias("s"))
    events.sorted_runs(urls, f"{where}/runs", f"{where}/progress").awaitTermination()
    return events.merged_runs(spark, f"{where}/runs")


add("stream_runs_twin", stream_runs, ranked_sql("url"))
