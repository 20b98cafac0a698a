"""Registered queries of the sorting methods, their parts, baselines and measures, each beside its DuckDB statement."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from levelsort.functions.text import fingerprint, fingerprint_sql, lcp_sql
from levelsort.operators import baselines, cost, doubling, lcp, merge
from levelsort.operators import mergesort as ms
from levelsort.plans import levels
from levelsort.registry import add
from levelsort.sources.strings import SETS, load, string_set
from levelsort.staging import cut

P, V = 8, 2
PLANS = {1: levels.LevelPlan(8, (8,)), 2: levels.LevelPlan(8, (2, 4)), 3: levels.LevelPlan(8, (2, 2, 2))}
BIG = "CAST({} AS BIGINT)"


def ranked_sql(name: str, text: bool = True) -> str:
    return f"SELECT CAST(row_number() OVER (ORDER BY s, src_id, pos) AS BIGINT) AS rank, src_id, pos{', s' if text else ''} FROM ({SETS[name][1]})"


# --- whole sorts: every method and plan gives the one exact order -------------------------------------------------
def _lms(name: str, k: int, **options):
    return lambda spark, d: ms.level_merge_sort(string_set(spark, d, name), PLANS[k], **options).ranked()


def _pds(name: str, k: int, **options):
    return lambda spark, d: doubling.prefix_doubling_sort(string_set(spark, d, name), PLANS[k], **options)


for _k, _names in {1: ("url", "lines"), 2: ("url", "lines", "lineitem", "conv"), 3: ("lines", "url")}.items():
    for _n in _names:
        add(f"lms{_k}_{_n}", _lms(_n, _k), ranked_sql(_n))
for _k, _names in {1: ("url",), 2: ("url", "lines", "customer", "part"), 3: ("lines",)}.items():
    for _n in _names:
        add(f"pds{_k}_{_n}", _pds(_n, _k), ranked_sql(_n, False))
add("lms2_lines_by_chars", _lms("lines", 2, sampling="chars", assign="bounded_chars"), ranked_sql("lines"))
add("lms2_lines_bounded", _lms("lines", 2, assign="bounded_strings"), ranked_sql("lines"))
add("lms2_lines_prefix_shares", _lms("lines", 2, assign="prefix_strings"), ranked_sql("lines"))
add("lms2_tiebreak_props", _lms("props", 2, tie_break=True), ranked_sql("props"))
add("pds2_materialized", lambda spark, d: doubling.materialize(doubling.prefix_doubling_sort(string_set(spark, d, "url"), PLANS[2]), string_set(spark, d, "url")), ranked_sql("url"))
add("hc_plain_url", lambda spark, d: baselines.hypercube_sort(string_set(spark, d, "url"), P), ranked_sql("url"))
add("hc_plain_lines", lambda spark, d: baselines.hypercube_sort(string_set(spark, d, "lines"), P), ranked_sql("lines"))
add("hc_fold", lambda spark, d: baselines.hypercube_sort(string_set(spark, d, "url"), 12), ranked_sql("url"))
add("single_node_url", lambda spark, d: baselines.single_node_sort(string_set(spark, d, "url")), ranked_sql("url"))
add("spark_sort_lines", lambda spark, d: baselines.spark_sort(string_set(spark, d, "lines")), ranked_sql("lines"))
add("rank_lines", lambda spark, d: baselines.spark_sort(string_set(spark, d, "lines")), ranked_sql("lines"))
def _hypercube(name: str, with_lcp: bool):
    return lambda spark, d: baselines.hypercube_sort(string_set(spark, d, name), P, with_lcp)


def _single(name: str):
    return lambda spark, d: baselines.single_box_sort(string_set(spark, d, name))


# W1: strings per lane in three sizes, D/N 0.5, every method; W2: every D/N, the methods that its plots compare
for _size in ("dn050_hundredth", "dn050_tenth", "dn050"):
    for _k in (1, 2, 3):
        add(f"w1_{_size}_lms{_k}", _lms(_size, _k), ranked_sql(_size))
        add(f"w1_{_size}_pds{_k}", _pds(_size, _k), ranked_sql(_size, False))
    add(f"w1_{_size}_hc_plain", _hypercube(_size, False), ranked_sql(_size))
    add(f"w1_{_size}_hc_lcp", _hypercube(_size, True), ranked_sql(_size))
for _r in ("dn000", "dn025", "dn050", "dn075", "dn100"):
    for _k in (1, 2):
        if _r != "dn050":
            add(f"w2_{_r}_lms{_k}", _lms(_r, _k), ranked_sql(_r))
            add(f"w2_{_r}_pds{_k}", _pds(_r, _k), ranked_sql(_r, False))
    if _r != "dn050":
        add(f"w2_{_r}_hc_plain", _hypercube(_r, False), ranked_sql(_r))
        add(f"w2_{_r}_hc_lcp", _hypercube(_r, True), ranked_sql(_r))
    add(f"w2_{_r}_single_box", _single(_r), ranked_sql(_r))
for _w, _n in {"w3_crawl_lines": "lines", "w4_markup": "markup", "w5_plain": "plain"}.items():
    add(f"{_w}_lms2", _lms(_n, 2), ranked_sql(_n)) if _n != "lines" else None
    add(f"{_w}_pds2", _pds(_n, 2), ranked_sql(_n, False))

# --- sources ------------------------------------------------------------------------------------------------------
for _n in ("lines", "markup", "plain", "page_lines"):
    add(f"src_{_n}", lambda spark, d, n=_n: string_set(spark, d, n), SETS[_n][1])


# --- level plans --------------------------------------------------------------------------------------------------
def lane_counts(spark, d) -> DataFrame:
    """p, k, c, n: lane counts as large as the ordered quantities, how many orders want them, one row per number of levels."""
    wanted = load(spark, d, "lineitem", ["l_orderkey", "l_quantity"]).groupBy("l_orderkey").agg(F.sum("l_quantity").cast("int").alias("p")).where("p >= 1")
    node = F.when(F.col("p") % 48 == 0, 48).otherwise(4)
    return wanted.groupBy("p").agg(F.count("*").alias("n")).select("p", F.explode(F.array(*map(F.lit, (1, 2, 3)))).alias("k"), node.alias("c"), "n")


LANE_COUNTS = """(SELECT p, k, CASE WHEN p % 48 = 0 THEN 48 ELSE 4 END AS c, n FROM (SELECT p, count(*) AS n FROM (SELECT CAST(sum(l_quantity) AS INT) AS p FROM lineitem GROUP BY l_orderkey) WHERE p >= 1 GROUP BY p) CROSS JOIN (SELECT unnest([1, 2, 3]) AS k))"""


def _plans(kind: str):
    make = F.udf(lambda p, k, c: ",".join(map(str, (levels.plan_equal(p, k) if kind == "equal" else levels.plan_node_aligned(p, k, c)).factors)))
    return lambda spark, d: lane_counts(spark, d).select("p", "k", make("p", "k", "c").alias("factors"), "n")


def plans_sql(kind: str) -> str:
    """Plans worked out by search: near-equal divisors of p; or of p / c with c last, on as many levels as p allows."""
    grid = LANE_COUNTS
    divisor = lambda of, root: f"(SELECT max(d) FROM range(1, 257) x(d) WHERE d <= round({of} ** (1.0 / {root}), 9) AND {of} % d = 0)"
    if kind == "equal":
        levels_of = f"SELECT p, k, n, p AS body, k AS parts, '' AS tail FROM {grid}"
    else:
        fit = f"SELECT p, k, c, n, CASE WHEN k = 3 AND p >= 4 * c THEN 3 WHEN k >= 2 AND p >= 2 * c THEN 2 ELSE 1 END AS used FROM {grid}"
        levels_of = f"SELECT p, k, n, CASE WHEN used = 1 OR p % c <> 0 THEN p ELSE p // c END AS body, CASE WHEN used = 1 OR p % c <> 0 THEN 1 ELSE used - 1 END AS parts, CASE WHEN used = 1 OR p % c <> 0 THEN '' ELSE ',' || c END AS tail FROM ({fit})"
    first = f"SELECT *, CASE WHEN parts = 1 THEN body ELSE {divisor('body', 'parts')} END AS a FROM ({levels_of})"
    second = f"SELECT *, CASE WHEN parts = 1 THEN 1 WHEN parts = 2 THEN body // a ELSE {divisor('(body // a)', '2')} END AS b FROM ({first})"
    third = f"SELECT *, CASE WHEN parts < 3 THEN 1 ELSE body // a // b END AS e FROM ({second})"
    listed = "array_to_string(list_sort(CASE parts WHEN 1 THEN [a] WHEN 2 THEN [a, b] ELSE [a, b, e] END), ',')"
    return f"SELECT CAST(p AS INT) AS p, CAST(k AS INT) AS k, {listed} || tail AS factors, n FROM ({third})"


for _kind in ("equal", "node_aligned"):
    add(f"plan_{_kind}_grid", _plans(_kind), plans_sql(_kind))


# --- first level in SQL: lanes, sizes, samples, splitters, buckets, targets -----------------------------------------
def level_one_sql(name: str, r: int, by: str = "strings", p: int = P, v: int = V) -> str:
    w = "n" if by == "strings" else "chars"
    total = p * (v + 1)
    cap = "least(m1, n)" if by == "strings" else "CASE WHEN n = 0 THEN 0 ELSE m1 END"
    if by == "strings":
        draw = """want AS (SELECT lane, greatest(1, t * n // (m + 1)) AS lpos, count(*) AS mult FROM (SELECT lane, n, m, unnest(range(1, m + 1)) AS t FROM counts WHERE m > 0) GROUP BY 1, 2),
        v AS MATERIALIZED (SELECT r.lane, s, src_id, pos, CAST(mult AS BIGINT) AS mult FROM ranked r JOIN want USING (lane, lpos))"""
    else:
        draw = """want AS (SELECT lane, t * w // (m + 1) AS off FROM (SELECT lane, w, m, unnest(range(1, m + 1)) AS t FROM counts WHERE m > 0)),
        v AS MATERIALIZED (SELECT r.lane, s, src_id, pos, count(*) AS mult FROM ranked r JOIN want w ON r.lane = w.lane AND off >= c0 AND off < c1 GROUP BY ALL)"""
    return f"""WITH base AS (SELECT *, row_number() OVER (ORDER BY src_id, pos) - 1 AS idx, count(*) OVER () AS n_all FROM ({SETS[name][1]})),
        placed AS MATERIALIZED (SELECT CAST(idx * {p} // n_all AS INT) AS lane, src_id, pos, s FROM base),
        ranked AS MATERIALIZED (SELECT *, row_number() OVER o AS lpos, sum(length(s)) OVER (o ROWS UNBOUNDED PRECEDING) AS c1, sum(length(s)) OVER (o ROWS UNBOUNDED PRECEDING) - length(s) AS c0 FROM placed WINDOW o AS (PARTITION BY lane ORDER BY s, src_id, pos)),
        sizes AS (SELECT CAST(l AS INT) AS lane, count(s) AS n, CAST(coalesce(sum(length(s)), 0) AS BIGINT) AS chars FROM range({p}) t(l) LEFT JOIN placed ON lane = l GROUP BY l),
        drawn AS (SELECT *, {w} AS w, greatest(0, ({w} * {total} + sum({w}) OVER () - 1) // sum({w}) OVER () - 1) AS m0 FROM sizes),
        topped AS (SELECT *, m0 + CASE WHEN lane < {total} - sum(m0) OVER () THEN 1 ELSE 0 END AS m1 FROM drawn),
        counts AS MATERIALIZED (SELECT lane, n, chars, w, CAST({cap} AS BIGINT) AS m FROM topped),
        {draw},
        spread AS (SELECT *, sum(mult) OVER (ORDER BY s, src_id, pos) AS stop, sum(mult) OVER () AS size FROM v),
        f AS MATERIALIZED (SELECT CAST(j AS INT) AS j, s FROM (SELECT s, stop, mult, size, unnest(range(1, {r})) AS j FROM spread) WHERE greatest(0, j * size // {r} - 1) >= stop - mult AND greatest(0, j * size // {r} - 1) < stop),
        bucketed AS MATERIALIZED (SELECT p.lane, p.src_id, p.pos, p.s, CAST((SELECT count(*) FROM f WHERE f.s < p.s) AS INT) AS bucket FROM placed p),
        pieces AS MATERIALIZED (SELECT lane, bucket, count(*) AS n, CAST(sum(length(s)) AS BIGINT) AS chars FROM bucketed GROUP BY ALL),
        grid AS MATERIALIZED (SELECT lane, bucket, CAST(bucket * {p // r} + lane % {p // r} AS INT) AS target, n, chars FROM pieces) """


def levels_sql(name: str, factors: tuple[int, ...], p: int = P, v: int = V) -> str:
    """All levels of a run by string sampling and grid assignment: per level i ranked{i}, v{i}, f{i}, bucketed{i}, grid{i}."""
    ctes = [f"""base AS (SELECT *, row_number() OVER (ORDER BY src_id, pos) - 1 AS idx, count(*) OVER () AS n_all FROM ({SETS[name][1]}))""",
        f"placed1 AS MATERIALIZED (SELECT 0 AS grp, CAST(idx * {p} // n_all AS INT) AS lane, src_id, pos, s FROM base)"]
    p1 = p
    for i, r in enumerate(factors, 1):
        p2, total = p1 // r, p1 * (v + 1)
        ctes += [
            f"ranked{i} AS MATERIALIZED (SELECT *, row_number() OVER (PARTITION BY lane ORDER BY s, src_id, pos) AS lpos FROM placed{i})",
            f"sizes{i} AS (SELECT CAST(l // {p1} AS INT) AS grp, CAST(l AS INT) AS lane, count(s) AS n FROM range({p}) t(l) LEFT JOIN placed{i} ON lane = l GROUP BY l)",
            f"drawn{i} AS (SELECT *, greatest(0, (n * {total} + sum(n) OVER g - 1) // greatest(1, sum(n) OVER g) - 1) AS m0 FROM sizes{i} WINDOW g AS (PARTITION BY grp))",
            f"counts{i} AS (SELECT grp, lane, n, CAST(least(n, m0 + CASE WHEN lane - grp * {p1} < {total} - sum(m0) OVER (PARTITION BY grp) THEN 1 ELSE 0 END) AS BIGINT) AS m FROM drawn{i})",
            f"want{i} AS (SELECT lane, greatest(1, t * n // (m + 1)) AS lpos, count(*) AS mult FROM (SELECT lane, n, m, unnest(range(1, m + 1)) AS t FROM counts{i} WHERE m > 0) GROUP BY 1, 2)",
            f"v{i} AS MATERIALIZED (SELECT grp, r.lane, s, src_id, pos, CAST(mult AS BIGINT) AS mult FROM ranked{i} r JOIN want{i} USING (lane, lpos))",
            f"spread{i} AS (SELECT grp, s, mult, sum(mult) OVER (PARTITION BY grp ORDER BY s, src_id, pos) AS stop, sum(mult) OVER (PARTITION BY grp) AS size FROM v{i})",
            f"f{i} AS MATERIALIZED (SELECT grp, CAST(j AS INT) AS j, s FROM (SELECT *, unnest(range(1, {r})) AS j FROM spread{i}) WHERE greatest(0, j * size // {r} - 1) >= stop - mult AND greatest(0, j * size // {r} - 1) < stop)",
            f"bucketed{i} AS MATERIALIZED (SELECT x.*, CAST((SELECT count(*) FROM f{i} WHERE f{i}.grp = x.grp AND f{i}.s < x.s) AS INT) AS bucket FROM placed{i} x)",
            f"grid{i} AS MATERIALIZED (SELECT grp, lane, bucket, CAST(grp * {p1} + bucket * {p2} + (lane - grp * {p1}) % {p2} AS INT) AS target, count(*) AS n, CAST(sum(length(s)) AS BIGINT) AS chars FROM bucketed{i} GROUP BY ALL)",
            f"placed{i + 1} AS MATERIALIZED (SELECT CAST(target // {p2} AS INT) AS grp, target AS lane, src_id, pos, s FROM (SELECT *, CAST(grp * {p1} + bucket * {p2} + (lane - grp * {p1}) % {p2} AS INT) AS target FROM bucketed{i}))",
        ]
        p1 = p2
    return "WITH " + ",\n".join(ctes) + "\n"


def _state(spark, d, name):
    return cut(ms.place_blocks(string_set(spark, d, name), P).select(F.lit(0).alias("grp"), "lane", "src_id", "pos", "s"))


def _level_one(name: str, r: int, by: str = "strings"):
    """state, samples, splitters, bucketed of the first level."""

    def make(spark, d):
        state = _state(spark, d, name)
        v = ms.draw_samples(state, P, V, by)
        f = cut(ms.splitters(v, r))
        return state, v, f, ms.bucketize(state, f)

    return make


add("place_blocks_counts", lambda spark, d: _state(spark, d, "lines").groupBy("lane").agg(F.count("*").alias("n"), F.sum(F.length("s")).alias("chars")), level_one_sql("lines", 2) + "SELECT lane, n, chars FROM sizes WHERE n > 0")
add("local_sort_lanes", lambda spark, d: ms.local_sort(_state(spark, d, "url")).select("lane", F.col("lpos").cast("bigint").alias("lpos"), "src_id", "pos", "s"), level_one_sql("url", 2) + "SELECT lane, lpos, src_id, pos, s FROM ranked")
for _by in ("strings", "chars"):
    for _n in ("lines", "url"):
        one = _level_one(_n, 4, _by)
        sql = level_one_sql(_n, 4, _by)
        add(f"sample_{_by}_l1_{_n}", lambda spark, d, one=one: one(spark, d)[1].select("lane", "src_id", "pos", "s", F.col("mult").cast("bigint").alias("mult")), sql + "SELECT lane, src_id, pos, s, mult FROM v")
        add(f"splitters_{_by}_l1_{_n}", lambda spark, d, one=one: one(spark, d)[2].select(F.col("j").cast("int").alias("j"), "s"), sql + "SELECT j, s FROM f")
        add(f"bucket_sizes_{_by}_l1_{_n}", lambda spark, d, one=one: ms.bucket_counts(one(spark, d)[3]).select("lane", "bucket", "n", "chars"), sql + "SELECT lane, bucket, n, chars FROM pieces")
_one, _sql = _level_one("lines", 4), level_one_sql("lines", 4)
_drawn = F.udf(lambda p, k: (V + 1) * sum(levels.plan_equal(p, k).group_sizes), T.LongType())  # a type given as text needs a session on import
add("sample_count_by_k", lambda spark, d: lane_counts(spark, d).select("k", _drawn("p", "k").alias("samples"), "n").groupBy("k").agg(F.sum(F.col("samples") * F.col("n")).alias("samples")),
    f"SELECT k, CAST(sum(n * {V + 1} * (p + CASE WHEN k > 1 THEN p // f[1] ELSE 0 END + CASE WHEN k > 2 THEN p // f[1] // f[2] ELSE 0 END)) AS BIGINT) AS samples FROM (SELECT p, k, n, list_transform(string_split(factors, ','), lambda x: CAST(x AS INT)) AS f FROM ({plans_sql('equal')})) GROUP BY k")
add("sorted_samples_l1", lambda spark, d: _one(spark, d)[1].select(F.row_number().over(W.orderBy("s", "src_id", "pos")).cast("bigint").alias("at"), "s", "src_id", "pos"), _sql + "SELECT row_number() OVER (ORDER BY s, src_id, pos) AS at, s, src_id, pos FROM v")
add("bucket_join_variant", lambda spark, d: (lambda x: ms.bucket_counts(ms.bucketize_by_join(x[0], x[2])).select("lane", "bucket", "n", "chars"))(_one(spark, d)), _sql + "SELECT lane, bucket, n, chars FROM pieces")
_prefix_len = "(SELECT max(i) FROM (SELECT unnest(range(0, 400)) AS i) WHERE left(s, i) = left({0}, i) AND i <= least(length(s), length({0})))"
add("splitters_short", lambda spark, d: ms.truncate_splitters(_one(spark, d)[2]).select(F.col("j").cast("int").alias("j"), "s"),
    _sql + "SELECT j, left(s, CAST(1 + greatest(coalesce((SELECT max(i) FROM range(0, 400) t(i) WHERE i <= least(length(s), length(a)) AND left(s, i) = left(a, i)), 0), coalesce((SELECT max(i) FROM range(0, 400) t(i) WHERE i <= least(length(s), length(b)) AND left(s, i) = left(b, i)), 0)) AS INT)) AS s FROM (SELECT j, s, lag(s) OVER (ORDER BY s, j) AS a, lead(s) OVER (ORDER BY s, j) AS b FROM f)")
add("assign_grid_l1", lambda spark, d: _one(spark, d)[3].withColumn("target", ms.grid_target(P, 4)).groupBy("lane", "bucket", "target").agg(F.count("*").alias("n"), F.sum(F.length("s")).alias("chars")), _sql + "SELECT lane, bucket, target, n, chars FROM grid")


def _assigned(fn):
    return lambda spark, d: fn(cut(ms.bucket_counts(_one(spark, d)[3]))).select("lane", "bucket", F.col("lo").cast("bigint").alias("lo"), F.col("hi").cast("bigint").alias("hi"), "target")


def assign_prefix_sql(w: str, r: int = 4, p: int = P) -> str:
    p2 = p // r
    return f"""SELECT lane, bucket, CAST(greatest(start, t * total // {p2}) - start AS BIGINT) AS lo, CAST(least(start + w, (t + 1) * total // {p2}) - start AS BIGINT) AS hi, CAST(bucket * {p2} + t AS INT) AS target
        FROM (SELECT lane, bucket, {w} AS w, sum({w}) OVER (PARTITION BY bucket ORDER BY lane) - {w} AS start, sum({w}) OVER (PARTITION BY bucket) AS total, unnest(range({p2})) AS t FROM pieces)
        WHERE least(start + w, (t + 1) * total // {p2}) > greatest(start, t * total // {p2})"""


def assign_bounded_sql(w: str, r: int = 4, p: int = P) -> str:
    p2 = p // r
    return f""", pc AS MATERIALIZED (SELECT lane, bucket, {w} AS w, sum({w}) OVER (PARTITION BY bucket) AS total, 2 * {r} * {p2} * {w} <= sum({w}) OVER (PARTITION BY bucket) AS small FROM pieces),
        sm AS MATERIALIZED (SELECT *, least((row_number() OVER (PARTITION BY bucket ORDER BY lane) - 1) // {r}, {p2 - 1}) AS t FROM pc WHERE small),
        room AS (SELECT b.bucket, b.t, greatest(0, (b.t + 1) * total // {p2} - b.t * total // {p2} - coalesce(got, 0)) AS room FROM (SELECT DISTINCT bucket, total, t FROM pc, range({p2}) x(t)) b LEFT JOIN (SELECT bucket, t, sum(w) AS got FROM sm GROUP BY ALL) g ON g.bucket = b.bucket AND g.t = b.t),
        cum AS (SELECT *, sum(room) OVER (PARTITION BY bucket ORDER BY t) AS c1, sum(room) OVER (PARTITION BY bucket ORDER BY t) - room AS c0 FROM room),
        lg AS (SELECT *, sum(w) OVER (PARTITION BY bucket ORDER BY lane) AS o1, sum(w) OVER (PARTITION BY bucket ORDER BY lane) - w AS o0 FROM pc WHERE NOT small)
        SELECT lane, bucket, CAST(0 AS BIGINT) AS lo, CAST(w AS BIGINT) AS hi, CAST(bucket * {p2} + t AS INT) AS target FROM sm
        UNION ALL SELECT lane, lg.bucket, CAST(greatest(o0, c0) - o0 AS BIGINT), CAST(least(o1, CASE WHEN t = {p2 - 1} THEN greatest(c1, o1) ELSE c1 END) - o0 AS BIGINT), CAST(lg.bucket * {p2} + t AS INT)
        FROM lg JOIN cum ON lg.bucket = cum.bucket AND least(o1, CASE WHEN t = {p2 - 1} THEN greatest(c1, o1) ELSE c1 END) > greatest(o0, c0)"""


add("assign_prefix_l1", _assigned(lambda c: ms.assign_prefix(c, P, 4)), _sql + assign_prefix_sql("n"))
add("assign_bounded_strings", _assigned(lambda c: ms.assign_bounded(c, P, 4)), _sql.rstrip() + assign_bounded_sql("n"))
add("assign_bounded_chars", _assigned(lambda c: ms.assign_bounded(c, P, 4, "chars")), _sql.rstrip() + assign_bounded_sql("chars"))
add("assign_message_count", lambda spark, d: _assigned(lambda c: ms.assign_bounded(c, P, 4))(spark, d).select("lane", "target").distinct().groupBy("lane").agg(F.count("*").alias("sends")), f"SELECT lane, count(DISTINCT target) AS sends FROM ({_sql.rstrip() + assign_bounded_sql('n')}) GROUP BY lane")


# --- measures -----------------------------------------------------------------------------------------------------
def _cost_sql(name: str, r: int) -> str:
    return level_one_sql(name, r) + """SELECT CAST(1 AS INT) AS level, count(*) AS messages, (SELECT max(c) FROM (SELECT count(DISTINCT target) AS c FROM grid GROUP BY lane)) AS max_messages_per_lane,
        CAST(sum(chars) AS BIGINT) AS chars_total, CAST((SELECT max(c) FROM (SELECT sum(chars) AS c FROM grid GROUP BY target)) AS BIGINT) AS chars_max_lane FROM grid"""


def _placed_run(spark, d, name: str, k: int, **options) -> ms.Sorted:
    return ms.level_merge_sort(ms.place_blocks(string_set(spark, d, name), P), PLANS[k], **options)


def messages_sql(name: str, k: int) -> str:
    one = """SELECT CAST({0} AS INT) AS level, count(*) AS messages, (SELECT max(c) FROM (SELECT count(DISTINCT target) AS c FROM grid{0} GROUP BY lane)) AS max_messages_per_lane,
        CAST(sum(chars) AS BIGINT) AS chars_total, CAST((SELECT max(c) FROM (SELECT sum(chars) AS c FROM grid{0} GROUP BY target)) AS BIGINT) AS chars_max_lane FROM (SELECT lane, target, sum(chars) AS chars FROM grid{0} GROUP BY ALL)"""
    return levels_sql(name, PLANS[k].factors) + " UNION ALL ".join(one.format(i) for i in range(1, k + 1))


def imbalance_sql(name: str, k: int) -> str:
    one = "SELECT CAST({0} AS INT) AS level, round(max(n) * {1} / sum(n), 6) AS strings, round(max(c) * {1} / sum(c), 6) AS chars FROM (SELECT sum(n) AS n, sum(chars) AS c FROM grid{0} GROUP BY target)"
    return levels_sql(name, PLANS[k].factors) + " UNION ALL ".join(one.format(i, P) for i in range(1, k + 1))


for _k in (1, 2, 3):
    add(f"cost_messages_k{_k}", lambda spark, d, k=_k: cost.messages(_placed_run(spark, d, "lines", k).moves), messages_sql("lines", _k))
    add(f"imbalance_by_level_k{_k}", lambda spark, d, k=_k: cost.imbalance_by_level(_placed_run(spark, d, "lines", k).moves, P), imbalance_sql("lines", _k))
for _n, _k, _level in (("lines", 2, 2), ("lines", 3, 3), ("url", 3, 2)):
    _q = levels_sql(_n, PLANS[_k].factors)
    add(f"sample_strings_l{_level}_{_n}", lambda spark, d, n=_n, k=_k, i=_level: _placed_run(spark, d, n, k).samples[i - 1].select("grp", "lane", "src_id", "pos", "s", F.col("mult").cast("bigint").alias("mult")), _q + f"SELECT CAST(grp AS INT) AS grp, lane, src_id, pos, s, mult FROM v{_level}")
    add(f"splitters_l{_level}_{_n}", lambda spark, d, n=_n, k=_k, i=_level: _placed_run(spark, d, n, k).cuts[i - 1].select("grp", F.col("j").cast("int").alias("j"), "s"), _q + f"SELECT CAST(grp AS INT) AS grp, j, s FROM f{_level}")
    add(f"bucket_sizes_l{_level}_{_n}", lambda spark, d, n=_n, k=_k, i=_level: _placed_run(spark, d, n, k).moves[i - 1], _q + f"SELECT CAST(grp AS INT) AS grp, lane, bucket, target, n, chars FROM grid{_level}")
add("imbalance_lms1_lines", lambda spark, d: cost.imbalance(ms.level_merge_sort(ms.place_blocks(string_set(spark, d, "lines"), P), PLANS[1]).rows, P), level_one_sql("lines", 8) + f"SELECT round(max(n) * {P} / sum(n), 6) AS strings, round(max(c) * {P} / sum(c), 6) AS chars FROM (SELECT count(*) AS n, sum(length(s)) AS c FROM bucketed GROUP BY bucket)")
add("overloaded_lanes", lambda spark, d: cost.overloaded(ms.level_merge_sort(ms.place_blocks(string_set(spark, d, "lines"), P), PLANS[1]).rows, P), level_one_sql("lines", 8) + f"SELECT bucket AS lane, CAST(sum(length(s)) AS BIGINT) AS chars FROM bucketed GROUP BY bucket HAVING sum(length(s)) > 1.5 * (SELECT sum(length(s)) FROM bucketed) / {P}")
add("cost_sample_volume", lambda spark, d: _one(spark, d)[1].agg(F.count("*").alias("strings"), F.sum(F.length("s")).alias("chars")), _sql + "SELECT count(*) AS strings, CAST(sum(length(s)) AS BIGINT) AS chars FROM v")
add("bucket_bound_strings", lambda spark, d: (lambda b: b.groupBy("bucket").agg(F.count("*").alias("n")).agg(F.max("n").alias("largest"), F.sum("n").alias("n")).select("largest", (F.col("largest") <= (1 + 4 / V) * F.col("n") / 4).alias("holds")))(_level_one("url", 4)(spark, d)[3]), level_one_sql("url", 4) + f"SELECT max(n) AS largest, max(n) <= (1 + 4 / {V}) * sum(n) / 4 AS holds FROM (SELECT count(*) AS n FROM bucketed GROUP BY bucket)")
add("bucket_bound_chars", lambda spark, d: _level_one("url", 4, "chars")(spark, d)[3].groupBy("bucket").agg(F.sum(F.length("s")).alias("c")).agg(F.max("c").alias("largest")), level_one_sql("url", 4, "chars") + "SELECT CAST(max(c) AS BIGINT) AS largest FROM (SELECT sum(length(s)) AS c FROM bucketed GROUP BY bucket)")
add("grid_hops", lambda spark, d: lane_counts(spark, d).select("p", "k", F.udf(lambda p, k: list(cost.grid_hops(p, k)), "array<int>")("p", "k").alias("h"), "n").select("p", "k", F.col("h")[0].alias("messages"), F.col("h")[1].alias("moves"), "n"),
    f"SELECT p, k, CAST(k * (min(s) - 1) AS INT) AS messages, k AS moves, n FROM {LANE_COUNTS} JOIN range(1, 1000) x(s) ON s ** k >= p GROUP BY p, k, n")
add("fp_bits", lambda spark, d: string_set(spark, d, "lines").agg(F.round(F.log2(F.lit(float(1 << 40)) * P / F.count("*")), 6).alias("bits")), f"SELECT round(log2({float(1 << 40)} * {P} / count(*)), 6) AS bits FROM ({SETS['lines'][1]})")

# --- common prefixes ----------------------------------------------------------------------------------------------
def lcp_table_sql(name: str) -> str:
    inner = f"SELECT *, lag(s) OVER (ORDER BY s, src_id, pos) AS t, row_number() OVER (ORDER BY s, src_id, pos) AS rank FROM ({SETS[name][1]})"
    return f"SELECT rank, src_id, pos, s, h, lead(h) OVER (ORDER BY rank) AS h2 FROM ({lcp_sql(inner)})"


_DIST = "least(greatest(coalesce(h, 0), coalesce(h2, 0)) + 1, length(s){})"
for _n in ("url", "customer", "lines"):
    add(f"lcp_array_{_n}", lambda spark, d, n=_n: lcp.lcp_array(string_set(spark, d, n)).select("rank", "src_id", "pos", "h"), f"SELECT rank, src_id, pos, h FROM ({lcp_table_sql(_n)})")
for _n in ("url", "part", "lines"):
    add(f"dist_prefix_{_n}", lambda spark, d, n=_n: lcp.dist_prefix(lcp.lcp_array(string_set(spark, d, n))), f"SELECT src_id, pos, CAST(length(s) AS INT) AS len, CAST({_DIST.format(' + 1')} AS INT) AS dist FROM ({lcp_table_sql(_n)})")
for _n in ("lines", "page_lines", "plain", "markup", "url", "conv", "customer", "dn050"):
    add(f"stats_{_n}", lambda spark, d, n=_n: lcp.string_stats(cut(lcp.lcp_array(string_set(spark, d, n)))),
        f"""SELECT count(*) AS n, CAST(sum(length(s)) AS BIGINT) AS chars, round(sum(length(s)) / count(*), 6) AS avg_len, round(sum(coalesce(h, 0)) / count(*), 6) AS avg_lcp,
        round(sum({_DIST.format('')}) / sum(length(s)), 6) AS dn_ratio, CAST(max(length(s)) AS BIGINT) AS max_len, CAST(min(length(s)) AS BIGINT) AS min_len, CAST(max({_DIST.format('')}) AS BIGINT) AS max_dist FROM ({lcp_table_sql(_n)})""")
_enc = level_one_sql("url", 2) + ", n AS (SELECT *, lag(s) OVER (PARTITION BY lane ORDER BY s, src_id, pos) AS t FROM ranked), e AS MATERIALIZED (" + lcp_sql("SELECT lane, lpos, src_id, pos, s, t FROM n") + ") "
add("front_encode_url", lambda spark, d: lcp.front_encode(_state(spark, d, "url")).select("lane", F.col("lpos").cast("bigint").alias("lpos"), "src_id", "pos", "h", "tail"), _enc + "SELECT lane, lpos, src_id, pos, CAST(coalesce(h, 0) AS INT) AS h, substring(s, coalesce(h, 0) + 1) AS tail FROM e")
add("front_roundtrip_lines", lambda spark, d: lcp.front_decode(lcp.front_encode(_state(spark, d, "lines"))).select("src_id", "pos", "s"), SETS["lines"][1])
add("front_volume_by_lane", lambda spark, d: lcp.front_encode(_state(spark, d, "url")).groupBy("lane").agg(F.sum(F.length("tail")).alias("tail_chars"), F.count("*").alias("lcp_values")), _enc + "SELECT lane, CAST(sum(length(s) - coalesce(h, 0)) AS BIGINT) AS tail_chars, count(*) AS lcp_values FROM e GROUP BY lane")


def _arrived(spark, d):
    x = _level_one("url", 4)(spark, d)[3].withColumn("target", ms.grid_target(P, 4))
    return x.select(F.col("target").alias("lane"), F.col("lane").alias("run"), "src_id", "pos", "s")


_arrived_sql = level_one_sql("url", 4) + f", arr AS MATERIALIZED (SELECT CAST(bucket * {P // 4} + lane % {P // 4} AS INT) AS lane, src_id, pos, s FROM bucketed), n AS (SELECT *, row_number() OVER o AS lpos, lag(s) OVER o AS t FROM arr WINDOW o AS (PARTITION BY lane ORDER BY s, src_id, pos)), e AS MATERIALIZED (" + lcp_sql("SELECT lane, lpos, src_id, pos, s, t FROM n") + ") "
add("lcp_merge_lane", lambda spark, d: merge.merge_lanes(_arrived(spark, d)).select("lane", "lpos", "src_id", "pos", F.coalesce("h", F.lit(0)).alias("h")), _arrived_sql + "SELECT lane, lpos, src_id, pos, CAST(coalesce(h, 0) AS INT) AS h FROM e")
add("plain_merge_lane", lambda spark, d: merge.merge_lanes(_arrived(spark, d), False).select("lane", "lpos", "src_id", "pos"), _arrived_sql + "SELECT lane, lpos, src_id, pos FROM e")
add("merge_chars_looked_at", lambda spark, d: (lambda x: merge.merge_lanes(x).groupBy("lane").agg(F.max("looked").alias("with_lcp")).join(merge.merge_lanes(x, False).groupBy("lane").agg(F.max("looked").alias("plain")), "lane"))(_arrived(spark, d)))

# --- prefix doubling ----------------------------------------------------------------------------------------------
def rounds_sql(name: str, rounds: int, d0: int = 4) -> str:
    """Unrolled rounds: a0 all strings; r_i marks, a_{i+1} what stays active; ``done`` collects who retired with which length."""
    ctes = [f"a0 AS MATERIALIZED (SELECT src_id, pos, s FROM ({SETS[name][1]}))"]
    for i in range(rounds):
        d = d0 << i
        ctes.append(f"r{i} AS MATERIALIZED (SELECT *, count(*) OVER (PARTITION BY fp) = 1 OR length(s) < {d} AS done FROM (SELECT src_id, pos, s, {fingerprint_sql('s', str(d))} AS fp FROM a{i}))")
        ctes.append(f"a{i + 1} AS MATERIALIZED (SELECT src_id, pos, s FROM r{i} WHERE NOT done)")
    done = " UNION ALL ".join(f"SELECT src_id, pos, CAST(length(s) AS INT) AS len, CAST(least({d0 << i}, length(s) + 1) AS INT) AS dist_approx FROM r{i} WHERE done" for i in range(rounds))
    return "WITH " + ", ".join(ctes) + f", retired AS ({done}) "


for _n in ("url", "lines", "conv", "props"):
    add(f"pd_approx_{_n}", lambda spark, d, n=_n: doubling.approx_dist(string_set(spark, d, n))[0], rounds_sql(_n, 17) + "SELECT * FROM retired")
for _det in ("exact", "sort", "auto"):
    add(f"pd_{_det}_url", lambda spark, d, x=_det: doubling.approx_dist(string_set(spark, d, "url"), detector=x, threshold=100)[0], rounds_sql("url", 8) + "SELECT * FROM retired")
for _d in (8, 16):
    add(f"pd_round_d{_d}", lambda spark, d, x=_d: doubling.doubling_round(string_set(spark, d, "lines"), x).select("src_id", "pos", "done"), rounds_sql("lines", 1, _d) + "SELECT src_id, pos, done FROM r0")
add("pd_round_props", lambda spark, d: doubling.doubling_round(string_set(spark, d, "props"), 16).groupBy("done").agg(F.count("*").alias("n")), rounds_sql("props", 1, 16) + "SELECT done, count(*) AS n FROM r0 GROUP BY done")
add("pd_trace", lambda spark, d: spark.createDataFrame([(t["round"], t["d"], t["n_active"], t["n_retired"]) for t in doubling.approx_dist(string_set(spark, d, "lines"))[1]], "round int, d int, n_active bigint, n_retired bigint"),
    rounds_sql("lines", 17) + "SELECT * FROM (" + " UNION ALL ".join(f"SELECT CAST({i + 1} AS INT) AS round, CAST({4 << i} AS INT) AS d, count(*) AS n_active, count(*) FILTER (done) AS n_retired FROM r{i}" for i in range(17)) + ") WHERE n_active > 0")
add("pd_auto_trace", lambda spark, d: spark.createDataFrame([(t["round"], t["n_active"], t["detector"]) for t in doubling.approx_dist(string_set(spark, d, "url"), detector="auto", threshold=100)[1]], "round int, n_active bigint, detector string"),
    rounds_sql("url", 8) + "SELECT round, n_active, CASE WHEN n_active >= 100 THEN 'filter' ELSE 'sort' END AS detector FROM (" + " UNION ALL ".join(f"SELECT CAST({i + 1} AS INT) AS round, count(*) AS n_active FROM r{i}" for i in range(8)) + ") WHERE n_active > 0")
add("pd_quality", lambda spark, d: (lambda s: doubling.approx_dist(s)[0].join(lcp.dist_prefix(lcp.lcp_array(s)).select("src_id", "pos", "dist"), ["src_id", "pos"]).agg(F.round(F.sum("dist_approx") / F.sum("dist"), 6).alias("total_ratio"), F.sum((F.col("dist_approx") < F.col("dist")).cast("bigint")).alias("violations")))(string_set(spark, d, "lines")),
    rounds_sql("lines", 17) + f", ex AS ({lcp_table_sql('lines')}) SELECT round(sum(dist_approx) / sum({_DIST.format(' + 1')}), 6) AS total_ratio, CAST(sum(CASE WHEN dist_approx < {_DIST.format(' + 1')} THEN 1 ELSE 0 END) AS BIGINT) AS violations FROM retired JOIN ex USING (src_id, pos)")


def _fps(spark, d, m=1 << 40):
    return string_set(spark, d, "lines").select(F.pmod(F.col("src_id"), F.lit(64)).alias("lane"), fingerprint(F.col("s"), F.lit(16), m).alias("fp"))


for _k in (1, 2, 3, 6):
    add(f"fp_filter_k{_k if _k < 6 else 'log'}", lambda spark, d, k=_k: doubling.duplicate_counts(_fps(spark, d), k, 64)[-1].select("fp", "cnt"), f"SELECT {fingerprint_sql('s', '16')} AS fp, count(*) AS cnt FROM ({SETS['lines'][1]}) GROUP BY 1")
add("fp_filter_hop_volume", lambda spark, d: (lambda hops: hops[0].agg(F.count("*").alias("n")).select(F.lit(1).alias("hop"), "n").union(hops[1].agg(F.count("*").alias("n")).select(F.lit(2).alias("hop"), "n")))(doubling.duplicate_counts(_fps(spark, d), 2, 64)),
    f"WITH x AS (SELECT src_id % 64 AS lane, {fingerprint_sql('s', '16')} AS fp FROM ({SETS['lines'][1]})) SELECT CAST(1 AS INT) AS hop, count(*) AS n FROM (SELECT DISTINCT lane % 8 AS c, CAST(fp AS BIGINT) * 64 // {1 << 40} // 8 AS o, fp FROM x) UNION ALL SELECT CAST(2 AS INT), count(DISTINCT fp) FROM x")
add("fp_sort_detector", lambda spark, d: doubling.unique_by_sort(string_set(spark, d, "lines").withColumn("fp", fingerprint(F.col("s"), F.lit(16)))), f"SELECT src_id, pos, count(*) OVER (PARTITION BY fp) > 1 AS dup FROM (SELECT src_id, pos, {fingerprint_sql('s', '16')} AS fp FROM ({SETS['lines'][1]}))")
add("fp_false_positives", lambda spark, d: (lambda x: x.groupBy("fp").agg(F.countDistinct("pre").alias("c")).agg(F.sum(F.when(F.col("c") > 1, F.col("c")).otherwise(0)).alias("hit"), F.sum("c").alias("prefixes")))(string_set(spark, d, "lines").select(F.concat(F.least(F.length("s") + 1, F.lit(16)).cast("string"), F.lit(":"), F.left("s", F.lit(16))).alias("pre"), fingerprint(F.col("s"), F.lit(16), 40000).alias("fp"))),
    f"SELECT CAST(sum(CASE WHEN c > 1 THEN c ELSE 0 END) AS BIGINT) AS hit, CAST(sum(c) AS BIGINT) AS prefixes FROM (SELECT fp, count(DISTINCT pre) AS c FROM (SELECT CAST(least(length(s) + 1, 16) AS VARCHAR) || ':' || left(s, 16) AS pre, {fingerprint_sql('s', '16', 40000)} AS fp FROM ({SETS['lines'][1]})) GROUP BY fp)")

# --- suffixes and windows -----------------------------------------------------------------------------------------
_docs = lambda spark, d: spark.read.parquet(f"{d}/benchmark.parquet")
_suffix_sql = "SELECT item_id AS src_id, CAST(i - 1 AS INT) AS pos, substring(text, i) AS s FROM (SELECT item_id, text, CAST(unnest(range(1, length(text) + 1)) AS INT) AS i FROM benchmark)"
_window_sql = "SELECT item_id AS src_id, CAST(i - 1 AS INT) AS pos, substring(text, i, 8) AS s FROM (SELECT item_id, text, CAST(unnest(range(1, length(text) - 6)) AS INT) AS i FROM benchmark)"
add("suffix_order_benchmark", lambda spark, d: doubling.prefix_doubling_sort(doubling.suffixes(_docs(spark, d)), PLANS[2]), f"SELECT row_number() OVER (ORDER BY s, src_id, pos) AS rank, src_id, pos FROM ({_suffix_sql})")
add("window_order_benchmark", lambda spark, d: doubling.prefix_doubling_sort(doubling.windows(_docs(spark, d), 8), PLANS[2]), f"SELECT row_number() OVER (ORDER BY s, src_id, pos) AS rank, src_id, pos FROM ({_window_sql})")


# --- balance and duplicates ---------------------------------------------------------------------------------------
def heavy_hitters(s: DataFrame, least: int) -> DataFrame:
    return s.groupBy("s").agg(F.count("*").alias("copies")).where(F.col("copies") >= least)


add("dup_heavy_hitters", lambda spark, d: heavy_hitters(string_set(spark, d, "lines"), 10), f"SELECT s, count(*) AS copies FROM ({SETS['lines'][1]}) GROUP BY s HAVING count(*) >= 10")
