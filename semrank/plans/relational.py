"""Relational, function and file-format queries over the given tables: the plain operations around semantic sorting."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import html_text, load, work_path
from .catalog import both, query
from .experiments import cosine


@query("SELECT l_orderkey, l_extendedprice, l_discount FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01' AND l_shipdate < TIMESTAMP '1996-01-01' AND l_discount BETWEEN 0.05 AND 0.07")
def scan_pruned_filtered(s, d):
    x = load(s, d, "lineitem").filter("l_shipdate >= '1995-01-01' and l_shipdate < '1996-01-01' and l_discount between 0.05 and 0.07")
    return x.select("l_orderkey", "l_extendedprice", "l_discount")


def _round_trip(s: SparkSession, df: DataFrame, kind: str, **options) -> DataFrame:
    path = work_path(s, kind)
    df.write.format(kind).options(**options).save(path)
    return s.read.format(kind).schema(df.schema).options(**options).load(path)


@query("SELECT * FROM region")
def io_csv_roundtrip(s, d):
    return _round_trip(s, load(s, d, "region"), "csv", header="true")


@query("SELECT * FROM nation")
def io_json_roundtrip(s, d):
    return _round_trip(s, load(s, d, "nation"), "json")


@query("SELECT p_partkey, p_name, p_retailprice FROM part")
def io_orc_roundtrip(s, d):
    return _round_trip(s, load(s, d, "part").select("p_partkey", "p_name", "p_retailprice"), "orc")


@query("SELECT o_orderkey, o_orderstatus FROM orders WHERE o_orderstatus = 'F'")
def io_partitioned_parquet(s, d):
    path = work_path(s, "partitioned")
    load(s, d, "orders").select("o_orderkey", "o_orderstatus").write.partitionBy("o_orderstatus").parquet(path)
    return s.read.schema("o_orderkey bigint, o_orderstatus string").parquet(path).filter("o_orderstatus = 'F'")


@query(r"""SELECT page_id, regexp_extract(html, '<title>([^<]*)</title>', 1) AS title, regexp_extract(html, '<html lang="([a-z]+)"', 1) AS lang, trim(regexp_replace(replace(replace(replace(replace(replace(
 regexp_replace(regexp_replace(regexp_replace(regexp_replace(html, '<script[^>]*>.*?</script>', ' ', 'gis'), '<style[^>]*>.*?</style>', ' ', 'gis'), '<!--.*?-->', ' ', 'gs'), '<[^>]*>', ' ', 'g'),
 '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', chr(39)), '&amp;', '&'), '\s+', ' ', 'g')) AS body FROM pages""")
def html_to_text(s, d):
    return load(s, d, "pages").select("page_id", F.regexp_extract("html", "<title>([^<]*)</title>", 1).alias("title"), F.regexp_extract("html", '<html lang="([a-z]+)"', 1).alias("lang"), html_text(F.col("html")).alias("body"))


both("filter_predicates", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice BETWEEN 1000 AND 50000 AND o_orderpriority IN ('1-URGENT', '2-HIGH') AND o_orderstatus <> 'P'")
both("filter_like_in_between", "SELECT p_partkey, p_name FROM part WHERE p_name LIKE '%e%' AND p_size BETWEEN 5 AND 30 AND p_partkey NOT IN (1, 2, 3)")
both("filter_null_safe", "SELECT d.doc_id FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.quality <=> NULL OR l.toxic = 1", "SELECT d.doc_id FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id WHERE l.quality IS NOT DISTINCT FROM NULL OR l.toxic = 1")
both("project_case_when", "SELECT o_orderkey, CASE WHEN o_totalprice > 200000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS band FROM orders")


@query("SELECT d.doc_id, d.lang, d.source FROM documents d JOIN (SELECT doc_id FROM documents ORDER BY n_chars DESC, doc_id LIMIT 10) t ON d.doc_id = t.doc_id")
def join_broadcast_winners(s, d):
    x = load(s, d, "documents")
    winners = x.orderBy(F.desc("n_chars"), "doc_id").limit(10).select("doc_id")
    return x.select("doc_id", "lang", "source").join(F.broadcast(winners), "doc_id")


both("join_merge_orders_lineitem", "SELECT /*+ MERGE(l) */ o_orderpriority, count(*) AS n, round(sum(l_extendedprice), 2) AS total FROM orders o JOIN lineitem l ON o_orderkey = l_orderkey GROUP BY o_orderpriority")
both("join_hash_customer_orders", "SELECT /*+ SHUFFLE_HASH(c) */ c_mktsegment, count(*) AS n FROM customer c JOIN orders o ON c_custkey = o_custkey GROUP BY c_mktsegment")
both("join_semi_labelled", "SELECT doc_id, lang FROM documents d LEFT SEMI JOIN labels l USING (doc_id)", "SELECT doc_id, lang FROM documents d SEMI JOIN labels l USING (doc_id)")
both("join_anti_unlabelled", "SELECT doc_id, lang FROM documents d LEFT ANTI JOIN labels l USING (doc_id)", "SELECT doc_id, lang FROM documents d ANTI JOIN labels l USING (doc_id)")
both("join_cross_scopes_all", "SELECT b.item_id AS scope, d.doc_id AS id FROM benchmark b CROSS JOIN documents d")
both("join_theta_pairs_all", "SELECT a.vec_id AS i, b.vec_id AS j FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id AND a.label = b.label")
both("join_left_labels", "SELECT d.doc_id, l.quality, l.toxic FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
both("join_full_methods", "SELECT a.id AS a_id, b.id AS b_id FROM (SELECT o_orderkey AS id FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 50) a FULL OUTER JOIN (SELECT o_orderkey AS id FROM orders ORDER BY o_orderdate DESC, o_orderkey LIMIT 50) b ON a.id = b.id")
# the time bucket makes the range join an equi-join: five-minute buckets, each event in its own and the next
both("join_range_events", """WITH e AS (SELECT event_id, user_id, ts, CAST(floor(unix_micros(CAST(ts AS TIMESTAMP)) / 300000000) AS BIGINT) AS b FROM events)
SELECT a.event_id AS i, c.event_id AS j FROM e a JOIN (SELECT *, explode(array(b - 1, b)) AS k FROM e) c ON a.user_id = c.user_id AND a.b = c.k AND c.ts >= a.ts AND c.ts <= a.ts + INTERVAL 5 MINUTES AND a.event_id <> c.event_id""",
     "SELECT a.event_id AS i, c.event_id AS j FROM events a JOIN events c ON a.user_id = c.user_id AND c.ts >= a.ts AND c.ts <= a.ts + INTERVAL 5 MINUTE AND a.event_id <> c.event_id")
both("join_asof_events", """SELECT event_id, view_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END) IGNORE NULLS OVER (PARTITION BY user_id ORDER BY ts, CASE WHEN event_type = 'view' THEN 0 ELSE 1 END, event_id ROWS UNBOUNDED PRECEDING) AS view_id FROM events) WHERE event_type = 'purchase'""",
     """SELECT event_id, view_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'view' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, CASE WHEN event_type = 'view' THEN 0 ELSE 1 END, event_id ROWS UNBOUNDED PRECEDING) AS view_id FROM events) WHERE event_type = 'purchase'""")  # fmt: skip
both("join_contains_qrels", "SELECT b.item_id, d.doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)")

_A, _B = "(SELECT o_custkey AS id FROM orders WHERE o_totalprice > 300000)", "(SELECT o_custkey AS id FROM orders WHERE o_orderpriority = '1-URGENT')"
for _name, _op in (("set_union", "UNION"), ("set_union_all", "UNION ALL"), ("set_intersect", "INTERSECT"), ("set_except", "EXCEPT"), ("set_intersect_all", "INTERSECT ALL"), ("set_except_all", "EXCEPT ALL")):
    both(_name, f"SELECT id FROM {_A} {_op} SELECT id FROM {_B}")

both("agg_group", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS qty, round(avg(l_extendedprice), 4) AS mean, min(l_discount) AS least, max(l_tax) AS most, round(stddev_samp(l_quantity), 6) AS sd FROM lineitem GROUP BY l_returnflag, l_linestatus")
both("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
both("agg_filter_clause", "SELECT user_id, count(*) FILTER (WHERE event_type = 'view') AS views, count(*) AS n FROM events GROUP BY user_id")
both("agg_having", "SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey HAVING count(*) > 12")
both("agg_cube", "SELECT lang, source, CAST(grouping_id(lang, source) AS BIGINT) AS g, count(*) AS n FROM documents GROUP BY CUBE (lang, source)", "SELECT lang, source, CAST(grouping_id(lang, source) AS BIGINT) AS g, count(*) AS n FROM documents GROUP BY CUBE (lang, source)")
both("agg_rollup", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
both("agg_grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
both("agg_unpivot", "SELECT doc_id, stack(2, 'quality', quality, 'toxic', toxic) AS (measure, value) FROM labels", "SELECT doc_id, unnest(['quality', 'toxic']) AS measure, unnest([quality, toxic]) AS value FROM labels")
both("agg_percentile", "SELECT lang, percentile(n_chars, 0.5) AS median, percentile(n_chars, 0.95) AS p95 FROM documents GROUP BY lang", "SELECT lang, CAST(quantile_cont(n_chars, 0.5) AS DOUBLE) AS median, CAST(quantile_cont(n_chars, 0.95) AS DOUBLE) AS p95 FROM documents GROUP BY lang")
both("agg_max_by", "SELECT o_custkey, max_by(o_orderkey, struct(o_totalprice, o_orderkey)) AS dearest, bool_or(o_orderstatus = 'F') AS done FROM orders GROUP BY o_custkey", "SELECT o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) AS dearest, bool_or(o_orderstatus = 'F') AS done FROM orders GROUP BY o_custkey")
both("agg_regression", "SELECT round(regr_slope(l_extendedprice, l_quantity), 6) AS slope, round(regr_intercept(l_extendedprice, l_quantity), 4) AS intercept, round(corr(l_extendedprice, l_quantity), 9) AS r FROM lineitem")
both("agg_width_bucket", "SELECT width_bucket(o_totalprice, 0, 500000, 10) AS b, count(*) AS n FROM orders GROUP BY 1", "SELECT CAST(least(floor(o_totalprice / 50000) + 1, 11) AS BIGINT) AS b, count(*) AS n FROM orders GROUP BY 1")


@query()
def agg_approx_distinct(s, d):
    return load(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"), F.approx_count_distinct("l_orderkey", 0.02).alias("orders"))


both("win_rank_family", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS rk, dense_rank() OVER w AS dr, round(percent_rank() OVER w, 9) AS pr FROM orders WINDOW w AS (PARTITION BY o_orderpriority ORDER BY o_custkey, o_orderkey)",
     "SELECT o_orderkey, CAST(row_number() OVER w AS INT) AS rn, CAST(rank() OVER w AS INT) AS rk, CAST(dense_rank() OVER w AS INT) AS dr, round(percent_rank() OVER w, 9) AS pr FROM orders WINDOW w AS (PARTITION BY o_orderpriority ORDER BY o_custkey, o_orderkey)")
both("win_ntile_cume", "SELECT o_orderkey, CAST(ntile(10) OVER w AS BIGINT) AS decile, round(cume_dist() OVER w, 9) AS cd FROM orders WINDOW w AS (PARTITION BY o_orderpriority ORDER BY o_totalprice, o_orderkey)")
both("win_running_bucket", "SELECT pos, CASE WHEN p = 0 THEN before END AS bucket FROM (SELECT pos, p, CAST(coalesce(sum(p) OVER (ORDER BY pos ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS BIGINT) AS before FROM (VALUES (1, 0), (2, 1), (3, 0), (4, 0), (5, 1), (6, 0)) t(pos, p))", tables=("region",))
both("win_range_moving_sum", "SELECT event_id, round(sum(value) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW), 4) AS total FROM events")
both("win_topk_per_group", "SELECT c_mktsegment, c_custkey, CAST(r AS BIGINT) AS r FROM (SELECT c_mktsegment, c_custkey, row_number() OVER (PARTITION BY c_mktsegment ORDER BY c_acctbal DESC, c_custkey) AS r FROM customer) WHERE r <= 5")
both("sort_multi_nulls", "SELECT CAST(row_number() OVER (ORDER BY l.quality DESC NULLS LAST, l.toxic ASC NULLS FIRST, d.doc_id) AS BIGINT) AS r, d.doc_id FROM documents d LEFT JOIN labels l ON d.doc_id = l.doc_id")
both("limit_offset", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10 OFFSET 20")
both("sample_hash", "SELECT doc_id FROM documents WHERE substring(md5(CAST(doc_id AS STRING)), 1, 1) IN ('0', '1')", "SELECT doc_id FROM documents WHERE substring(md5(CAST(doc_id AS VARCHAR)), 1, 1) IN ('0', '1')")

both("fn_string", "SELECT p_partkey, lower(p_name) AS lo, trim(p_type) AS tr, substring(p_name, 2, 5) AS sub, concat_ws('-', p_brand, p_type) AS joined, length(p_name) AS n, contains(p_name, 'a') AS has, md5(p_name) AS h, replace(p_name, 'e', '') AS gone, split(p_name, ' ')[0] AS head FROM part",
     "SELECT p_partkey, lower(p_name) AS lo, trim(p_type) AS tr, substring(p_name, 2, 5) AS sub, concat_ws('-', p_brand, p_type) AS joined, CAST(length(p_name) AS INT) AS n, contains(p_name, 'a') AS has, md5(p_name) AS h, replace(p_name, 'e', '') AS gone, split(p_name, ' ')[1] AS head FROM part")
both("fn_regex_tokens", "SELECT doc_id, size(regexp_extract_all(lower(text), '[a-z]+', 0)) AS n, regexp_extract(text, '([A-Z][a-z]+)', 1) AS first FROM documents", "SELECT doc_id, CAST(len(regexp_extract_all(lower(text), '[a-z]+')) AS INT) AS n, regexp_extract(text, '([A-Z][a-z]+)', 1) AS first FROM documents")
both("fn_levenshtein", "SELECT p_partkey, levenshtein(p_name, p_type) AS n FROM part", "SELECT p_partkey, CAST(levenshtein(p_name, p_type) AS INT) AS n FROM part")
both("fn_date", "SELECT o_orderkey, CAST(date_trunc('MONTH', o_orderdate) AS DATE) AS m, year(o_orderdate) AS y, extract(DAY FROM o_orderdate) AS dd, datediff(o_orderdate, DATE '1992-01-01') AS days FROM orders",
     "SELECT o_orderkey, CAST(date_trunc('month', o_orderdate) AS DATE) AS m, CAST(year(o_orderdate) AS INT) AS y, CAST(extract(day FROM o_orderdate) AS INT) AS dd, CAST(date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS INT) AS days FROM orders")
both("fn_interval", "SELECT event_id, CAST(ts + INTERVAL 90 MINUTES AS STRING) AS later, hour(ts) AS h FROM events", "SELECT event_id, strftime(ts + INTERVAL 90 MINUTE, '%Y-%m-%d %H:%M:%S') || CASE WHEN microsecond(ts) % 1000000 = 0 THEN '' ELSE '.' || rtrim(lpad(CAST(microsecond(ts) % 1000000 AS VARCHAR), 6, '0'), '0') END AS later, CAST(hour(ts) AS INT) AS h FROM events")
both("fn_math", "SELECT l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) AS a, round(log2(l_quantity), 6) AS b, round(pow(l_discount, 2), 6) AS c, CAST(pmod(l_orderkey, 7) AS BIGINT) AS d, greatest(l_tax, l_discount) AS e, round(sqrt(l_quantity), 6) AS f FROM lineitem",
     "SELECT l_orderkey, l_linenumber, round(ln(l_extendedprice), 6) AS a, round(log2(l_quantity), 6) AS b, round(pow(l_discount, 2), 6) AS c, CAST(l_orderkey % 7 AS BIGINT) AS d, greatest(l_tax, l_discount) AS e, round(sqrt(l_quantity), 6) AS f FROM lineitem")
both("fn_array_hof", "SELECT vec_id, round(aggregate(transform(embedding, x -> CAST(x AS DOUBLE) * x), CAST(0 AS DOUBLE), (a, x) -> a + x), 5) AS norm2, size(filter(embedding, x -> x > 0)) AS pos FROM embeddings", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * x)), 5) AS norm2, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INT) AS pos FROM embeddings")
both("arr_posexplode", "SELECT item_id, pos, word FROM (SELECT item_id, split(text, ' ') AS w FROM benchmark) LATERAL VIEW posexplode(w) t AS pos, word", "SELECT item_id, CAST(unnest(range(len(w))) AS INT) AS pos, unnest(w) AS word FROM (SELECT item_id, string_split(text, ' ') AS w FROM benchmark)")
both("fn_array_set", "SELECT item_id, size(array_distinct(w)) AS distinct_words, size(array_except(w, array('the', 'of'))) AS rest, array_contains(w, 'the') AS has FROM (SELECT item_id, split(text, ' ') AS w FROM benchmark)", "SELECT item_id, CAST(len(list_distinct(w)) AS INT) AS distinct_words, CAST(len(list_filter(list_distinct(w), lambda x: x NOT IN ('the', 'of'))) AS INT) AS rest, list_contains(w, 'the') AS has FROM (SELECT item_id, string_split(text, ' ') AS w FROM benchmark)")
both("fn_map", "SELECT item_id, k, v FROM (SELECT item_id, map_from_entries(transform(array_distinct(split(text, ' ')), x -> struct(x, length(x)))) AS m FROM benchmark) LATERAL VIEW explode(m) t AS k, v", "SELECT item_id, k, CAST(length(k) AS INT) AS v FROM (SELECT item_id, unnest(list_distinct(string_split(text, ' '))) AS k FROM benchmark)")
both("json_props", "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k, from_json(props, 'k BIGINT').k AS k2 FROM events", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k2 FROM events")

_COS0 = "round(list_cosine_similarity(CAST(embedding AS DOUBLE[]), (SELECT CAST(embedding AS DOUBLE[]) FROM embeddings WHERE vec_id = 0)), 6)"


@query(f"SELECT vec_id, {_COS0} AS cosine FROM embeddings ORDER BY cosine DESC, vec_id LIMIT 10")
def vec_cosine_topk(s, d):
    v = load(s, d, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("e"))
    q = v.filter("vec_id = 0").select(F.col("e").alias("q"))
    return v.crossJoin(F.broadcast(q)).select("vec_id", cosine("e", "q").alias("cosine")).orderBy(F.desc("cosine"), "vec_id").limit(10)


def salted_join(large: DataFrame, small: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """An inner join where one key may hold most rows of ``large``: its rows are dealt over ``salts`` parts, of which ``small`` has a copy each."""
    dealt = large.withColumn("_salt", F.pmod(F.monotonically_increasing_id(), F.lit(salts)))
    copies = small.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return dealt.join(copies.hint("merge"), [key, "_salt"]).drop("_salt")


@query("SELECT e.event_id, e.event_type, c.n FROM events e JOIN (SELECT event_type, count(*) AS n FROM events GROUP BY event_type) c ON e.event_type = c.event_type")
def join_skewed_salted(s, d):
    e = load(s, d, "events").select("event_id", "event_type")
    return salted_join(e, e.groupBy("event_type").agg(F.count("*").alias("n")), "event_type")
