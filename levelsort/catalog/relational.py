"""Registered queries around the sorts: scans, joins, aggregates, windows, sets, functions, stream twins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from levelsort.functions.text import common_prefix
from levelsort.operators import surround as op
from levelsort.registry import add
from levelsort.sources.strings import SETS, as_key, load, string_set
from levelsort.streaming import events as ev

LINES = f"({SETS['lines'][1]})"


def sql(text: str):
    """The same statement on Spark, over views of the tables it names."""

    def run(spark, d) -> DataFrame:
        for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "pages", "labels"):
            if t in text:
                load(spark, d, t).createOrReplaceTempView(t)
        return spark.sql(text)

    return run


def both(name: str, text: str, spark_text: str | None = None) -> None:
    add(name, sql(spark_text or text), text)


D = lambda spark, d: load(spark, d, "documents")

# scans, projections, filters
both("scan_documents", "SELECT doc_id, lang, source, n_chars FROM documents")
both("scan_pages", "SELECT page_id, url FROM pages")
both("proj_lengths", "SELECT doc_id, CAST(length(text) AS BIGINT) AS chars, CAST(octet_length(encode(text)) AS BIGINT) AS bytes FROM documents", "SELECT doc_id, CAST(length(text) AS BIGINT) AS chars, CAST(octet_length(text) AS BIGINT) AS bytes FROM documents")
add("filter_prefix", lambda spark, d: op.filter_prefix(load(spark, d, "pages", ["page_id", "url"]), "url", "http://t"), "SELECT page_id, url FROM pages WHERE starts_with(url, 'http://t')")
add("filter_range_strings", lambda spark, d: op.filter_range(load(spark, d, "pages", ["page_id", "url"]), "url", "http://a", "http://n"), "SELECT page_id, url FROM pages WHERE url >= 'http://a' AND url < 'http://n'")
both("filter_lang", "SELECT doc_id FROM documents WHERE lang IN ('de', 'fr') AND n_chars > 1000")
both("filter_rlike", "SELECT doc_id FROM documents WHERE regexp_matches(text, 'Licen[sc]ed')", "SELECT doc_id FROM documents WHERE text RLIKE 'Licen[sc]ed'")
add("src_composite_key", lambda spark, d: (lambda e: e.select("event_id", as_key(e, ["user_id", "ts"]).alias("key")))(load(spark, d, "events")), "SELECT event_id, lpad(CAST(CAST(user_id AS HUGEINT) + 9223372036854775808 AS VARCHAR), 20, '0') || '|' || strftime(ts, '%Y-%m-%d %H:%M:%S.%f') AS key FROM events")

# joins
both("join_docs_labels", "SELECT d.doc_id, lang, quality, toxic FROM documents d JOIN labels l ON d.doc_id = l.doc_id")
add("join_orders_customer", lambda spark, d: op.join_on(load(spark, d, "orders", ["o_orderkey", "o_custkey"]).withColumnRenamed("o_custkey", "k"), load(spark, d, "customer", ["c_custkey", "c_mktsegment"]).withColumnRenamed("c_custkey", "k"), "k", strategy="shuffle_hash").groupBy("c_mktsegment").agg(F.count("*").alias("n")), "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1")
both("join_full_labels", "SELECT d.doc_id AS a, l.doc_id AS b FROM documents d FULL JOIN labels l ON d.doc_id = l.doc_id")
add("join_smj_lineitem_part", lambda spark, d: op.join_on(load(spark, d, "lineitem", ["l_partkey", "l_quantity"]).withColumnRenamed("l_partkey", "k"), load(spark, d, "part", ["p_partkey", "p_brand"]).withColumnRenamed("p_partkey", "k"), "k", strategy="merge").groupBy("p_brand").agg(F.round(F.sum("l_quantity"), 2).alias("q")), "SELECT p_brand, round(sum(l_quantity), 2) AS q FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1")
add("join_range_prices", lambda spark, d: op.range_assign(load(spark, d, "part", ["p_partkey", "p_retailprice"]), "p_retailprice", [1000.0, 1200.0, 1500.0]).groupBy("band").agg(F.count("*").alias("n")), "SELECT CAST((p_retailprice > 1000)::INT + (p_retailprice > 1200)::INT + (p_retailprice > 1500)::INT AS INT) AS band, count(*) AS n FROM part GROUP BY 1")
add("asof_events_purchase_click", lambda spark, d: (lambda e: op.asof(e.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), e.where("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", "ts"), "ts", "user_id", "click"))(load(spark, d, "events")).select("event_id", "click"),
    "SELECT p.event_id, (SELECT max_by(c.event_id, (c.ts, c.event_id)) FROM events c WHERE c.event_type = 'click' AND c.user_id = p.user_id AND c.ts <= p.ts) AS click FROM events p WHERE event_type = 'purchase'")
add("interval_join_events", lambda spark, d: (lambda e: op.within(e.where("event_type = 'click'").select(F.col("event_id").alias("a"), "user_id", "ts"), e.where("event_type = 'purchase'").select(F.col("event_id").alias("b"), "user_id", "ts"), "user_id", "ts", 600))(load(spark, d, "events")),
    "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 10 MINUTE WHERE a.event_type = 'click' AND b.event_type = 'purchase'")
add("semi_labeled_docs", lambda spark, d: D(spark, d).select("doc_id").join(load(spark, d, "labels"), "doc_id", "left_semi"), "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
add("anti_unlabeled_docs", lambda spark, d: D(spark, d).select("doc_id").join(load(spark, d, "labels"), "doc_id", "left_anti"), "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
both("cross_plan_grid", "SELECT k, p FROM (SELECT DISTINCT CAST(l_linenumber AS INT) AS k FROM lineitem) CROSS JOIN (SELECT DISTINCT CAST(l_quantity AS INT) AS p FROM lineitem)")
add("join_common_prefix", lambda spark, d: op.prefix_groups(load(spark, d, "pages", ["page_id", "url"]), "url", 12), "SELECT left(url, 12) AS prefix, count(*) AS n, min(page_id) AS first FROM pages GROUP BY 1 HAVING count(*) > 1")

# aggregates
both("agg_lang_source", "SELECT lang, source, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY lang, source")
add("agg_distinct_lines", lambda spark, d: string_set(spark, d, "lines").agg(F.countDistinct("s").alias("n")), f"SELECT count(DISTINCT s) AS n FROM {LINES}")
add("agg_approx_distinct_lines", lambda spark, d: string_set(spark, d, "lines").agg(F.approx_count_distinct("s").alias("n")))
both("agg_rollup_lang_source", "SELECT lang, source, count(*) AS n FROM documents GROUP BY ROLLUP (lang, source)")
both("agg_cube_orders", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
both("agg_grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
add("agg_pivot_events", lambda spark, d: load(spark, d, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).agg(F.count(F.lit(1))).fillna(0), "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view FROM events GROUP BY 1")
add("agg_string_minmax", lambda spark, d: string_set(spark, d, "lines").groupBy("src_id").agg(F.min("s").alias("lo"), F.max("s").alias("hi"), F.min_by("pos", F.struct("s", "pos")).alias("at")), f"SELECT src_id, min(s) AS lo, max(s) AS hi, min_by(pos, (s, pos)) AS at FROM {LINES} GROUP BY 1")
both("agg_median_length", "SELECT lang, quantile_cont(n_chars, 0.5) AS median FROM documents GROUP BY lang", "SELECT lang, percentile(n_chars, 0.5) AS median FROM documents GROUP BY lang")
add("udaf_common_prefix", lambda spark, d: load(spark, d, "pages").groupBy(F.left("url", F.lit(9)).alias("head")).agg(common_prefix("url").alias("prefix")),
    "SELECT head, left(lo, CAST((SELECT max(i) FROM range(0, 200) t(i) WHERE i <= least(length(lo), length(hi)) AND left(lo, i) = left(hi, i)) AS INT)) AS prefix FROM (SELECT left(url, 9) AS head, min(url) AS lo, max(url) AS hi FROM pages GROUP BY 1)")

# windows
both("win_rank_strings", "SELECT p_partkey, p_name, CAST(rank() OVER (PARTITION BY p_brand ORDER BY p_name) AS BIGINT) AS r FROM part")
both("win_dense_rank_names", "SELECT p_partkey, CAST(dense_rank() OVER (PARTITION BY p_brand ORDER BY p_name) AS BIGINT) AS r FROM part")
both("win_ntile_lanes", "SELECT c_custkey, CAST(ntile(4) OVER (PARTITION BY c_mktsegment ORDER BY c_name) AS BIGINT) AS lane FROM customer")
add("win_running_chars", lambda spark, d: op.running(string_set(spark, d, "lines").withColumn("len", F.length("s")), "src_id", "pos", "len").select("src_id", "pos", "total"), f"SELECT src_id, pos, CAST(sum(length(s)) OVER (PARTITION BY src_id ORDER BY pos) AS BIGINT) AS total FROM {LINES}")
both("win_moving_avg_orders", "SELECT o_orderkey, round(avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS a FROM orders")
both("win_lead_lag_urls", "SELECT page_id, lag(url) OVER w AS a, lead(url) OVER w AS b FROM pages WINDOW w AS (PARTITION BY left(url, 9) ORDER BY url, page_id)")
both("win_range_frame_events", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 DAY PRECEDING AND CURRENT ROW) AS n FROM events")

# order, limits, sets, duplicates
add("topk_longest_lines", lambda spark, d: string_set(spark, d, "lines").orderBy(F.length("s").desc(), "src_id", "pos").limit(20).select("src_id", "pos"), f"SELECT src_id, pos FROM {LINES} ORDER BY length(s) DESC, src_id, pos LIMIT 20")
both("topk_per_lang", "SELECT lang, doc_id FROM (SELECT lang, doc_id, row_number() OVER (PARTITION BY lang ORDER BY n_chars DESC, doc_id) AS r FROM documents) WHERE r <= 3")
add("select_median_string", lambda spark, d: op.median_string(string_set(spark, d, "lines")), f"SELECT src_id, pos, s FROM (SELECT *, row_number() OVER (ORDER BY s, src_id, pos) AS r, count(*) OVER () AS n FROM {LINES}) WHERE r = (n + 1) // 2")
add("select_ith_string", lambda spark, d: op.ith_string(string_set(spark, d, "lines"), 500), f"SELECT src_id, pos, s FROM {LINES} ORDER BY s, src_id, pos LIMIT 1 OFFSET 500")
both("order_desc_nulls", "SELECT doc_id, toxic FROM (SELECT d.doc_id, toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id) ORDER BY toxic DESC NULLS LAST, doc_id")
for _name, _kw, _all in (("union", "UNION", False), ("intersect", "INTERSECT", False), ("except", "EXCEPT", False), ("except_all", "EXCEPT ALL", True)):
    add(f"set_{_name}_lines", lambda spark, d, k=_name: op.set_op(op.lines_of(spark, d, "en"), op.lines_of(spark, d, "fr"), k), f"SELECT s FROM {LINES} JOIN documents ON src_id = doc_id WHERE lang = 'en' {_kw} SELECT s FROM {LINES} JOIN documents ON src_id = doc_id WHERE lang = 'fr'")
add("dedup_lines", lambda spark, d: op.dedup(string_set(spark, d, "lines"), "s"), f"SELECT s, min(src_id) AS src_id FROM {LINES} GROUP BY s")
add("op_regular_sample", lambda spark, d: op.regular_sample(load(spark, d, "part", ["p_partkey", "p_brand", "p_name"]), "p_brand", ["p_name", "p_partkey"], 3).select("p_partkey"), "SELECT p_partkey FROM (SELECT p_partkey, row_number() OVER w AS r, count(*) OVER (PARTITION BY p_brand) AS n FROM part WINDOW w AS (PARTITION BY p_brand ORDER BY p_name, p_partkey)) WHERE r IN (n // 4, 2 * n // 4, 3 * n // 4)")

# functions
both("fn_string_basic", "SELECT page_id, upper(left(url, 10)) AS a, reverse(url) AS b, CAST(length(url) AS INT) AS n, replace(url, 'http', 'x') AS c, lpad(CAST(page_id AS VARCHAR), 6, '0') AS e FROM pages", "SELECT page_id, upper(left(url, 10)) AS a, reverse(url) AS b, length(url) AS n, replace(url, 'http', 'x') AS c, lpad(CAST(page_id AS STRING), 6, '0') AS e FROM pages")
both("fn_string_regex", "SELECT page_id, regexp_extract(url, '/([a-z]+)/', 1) AS lang FROM pages")
both("fn_hash_md5", "SELECT doc_id, md5(text) AS h FROM documents")
both("fn_levenshtein_names", "SELECT a AS a, b AS b, CAST(levenshtein(a, b) AS INT) AS n, rows FROM (SELECT p_name AS a, p_brand AS b, count(*) AS rows FROM part GROUP BY p_name, p_brand) x")
both("fn_date_orders", "SELECT CAST(year(o_orderdate) AS INT) AS y, CAST(month(o_orderdate) AS INT) AS m, count(*) AS n FROM orders GROUP BY 1, 2")
both("fn_math_plan", "SELECT o_orderkey + 1 AS p, CAST(floor(log2(o_orderkey + 1)) AS BIGINT) AS d, CAST(ceil(sqrt(o_orderkey + 1)) AS BIGINT) AS side FROM orders")
both("fn_array_splitters", "SELECT doc_id, CAST(len(list_filter(string_split(text, ' '), lambda x: length(x) > 12)) AS INT) AS n FROM documents", "SELECT doc_id, size(filter(split(text, ' '), x -> length(x) > 12)) AS n FROM documents")
add("fn_array_embedding_norm", lambda spark, d: load(spark, d, "embeddings").select("vec_id", F.round(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))), 4).alias("norm")), "SELECT vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE))), 4) AS norm FROM embeddings")
both("fn_json_props", "SELECT CAST(json_extract_string(props, '$.k') AS INT) AS k, count(*) AS n FROM events GROUP BY 1", "SELECT CAST(get_json_object(props, '$.k') AS INT) AS k, count(*) AS n FROM events GROUP BY 1")
both("sql_exists_labels", "SELECT doc_id FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND toxic = 1)")
both("sql_scalar_avg_len", "SELECT doc_id FROM documents WHERE n_chars > (SELECT avg(n_chars) FROM documents)")
both("sql_recursive_doubling", "WITH RECURSIVE t(d, longest) AS (SELECT CAST(4 AS BIGINT), CAST(max(length(text)) AS BIGINT) FROM documents UNION ALL SELECT 2 * d, longest FROM t WHERE d < longest) SELECT d, longest FROM t")
both("star_pricing_summary", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS q, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, count(*) AS n FROM lineitem WHERE l_shipdate <= TIMESTAMP '1998-09-02 00:00:00' GROUP BY 1, 2")
both("star_nation_revenue", "SELECT n_name, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY 1")
both("star_top_customers", "SELECT c_custkey, round(sum(o_totalprice), 2) AS total FROM customer JOIN orders ON c_custkey = o_custkey GROUP BY 1 ORDER BY sum(o_totalprice) DESC, c_custkey LIMIT 10")
both("star_forecast_revenue", "SELECT round(sum(l_extendedprice * l_discount), 2) AS revenue FROM lineitem WHERE l_discount BETWEEN 0.05 AND 0.07 AND l_quantity < 24")
add("lookup_prefix_url", lambda spark, d: op.prefix_lookup(string_set(spark, d, "url"), "http://th"), "SELECT page_id AS src_id, 0 AS pos, url AS s FROM pages WHERE starts_with(url, 'http://th')")
add("udtf_doubling_prefixes", lambda spark, d: op.doubling_prefixes(string_set(spark, d, "url")), "SELECT page_id AS src_id, CAST(d AS INT) AS d, left(url, d) AS prefix FROM pages, (SELECT CAST(4 << i AS INT) AS d FROM range(0, 8) t(i)) WHERE d = 4 OR d // 2 <= length(url)")

# stream twins: the batch form of each streaming query
add("stream_tumbling_twin", lambda spark, d: ev.tumbling(load(spark, d, "events")), "SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
add("stream_sliding_twin", lambda spark, d: ev.sliding(load(spark, d, "events")), "SELECT time_bucket(INTERVAL 1 DAY, ts) - INTERVAL 1 DAY * k AS start, count(*) AS n FROM events, range(0, 2) t(k) GROUP BY 1")
add("stream_session_twin", lambda spark, d: ev.sessions(load(spark, d, "events")),
    "SELECT user_id, min(ts) AS start, count(*) AS n FROM (SELECT *, sum(CASE WHEN gap IS NULL OR gap >= INTERVAL 12 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS g FROM (SELECT *, ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS gap FROM events)) GROUP BY user_id, g")
add("stream_dedup_twin", lambda spark, d: ev.deduplicated(load(spark, d, "events")), "SELECT props, min(event_id) AS first FROM events GROUP BY props")
