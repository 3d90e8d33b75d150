"""Operators and functions around the methods: one declarative query each, with its SQL for DuckDB.

A text in braces is a table. ``both`` takes one SQL text for both engines; ``pair`` one each where they differ;
``frame`` a DataFrame function. Spark's text runs as SQL, so Catalyst sees the same plan as from the DataFrame API.
"""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE: dict[str, str] = {}
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _fill(sql: str, of) -> str:
    return re.sub(r"\{(" + "|".join(TABLES) + r")\}", lambda m: of(m[1]), sql)


def pair(name: str, spark_sql: str, duck_sql: str) -> None:
    QUERIES[name] = lambda spark, d: spark.sql(_fill(spark_sql, lambda t: f"parquet.`{d}/{t}.parquet`"))
    ORACLE[name] = _fill(duck_sql, lambda t: t)


def both(name: str, sql: str) -> None:
    pair(name, sql, sql)


def frame(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLE[name] = _fill(sql, lambda t: t)
        return f

    return add


# Scans

for _t in TABLES:
    if _t == "embeddings":
        pair("scan_embeddings", "SELECT vec_id, label, round(aggregate(transform(embedding, x -> cast(x AS double)), 0D, (a, x) -> a + x), 4) AS total FROM {embeddings}", "SELECT vec_id, label, round(list_sum(embedding::DOUBLE[]), 4) AS total FROM {embeddings}")
    elif _t in ("orders", "lineitem", "events"):
        _c = {"orders": "o_orderkey, o_custkey, o_orderstatus, o_totalprice, cast(o_orderdate AS date) AS day, o_orderpriority", "lineitem": "l_orderkey, l_linenumber, l_partkey, l_quantity, l_returnflag, cast(l_shipdate AS date) AS day", "events": "event_id, user_id, event_type, value, cast(ts AS date) AS day"}[_t]
        both(f"scan_{_t}", f"SELECT {_c} FROM {{{_t}}}")
    else:
        both(f"scan_{_t}", f"SELECT * FROM {{{_t}}}")
both("scan_pruned", "SELECT l_orderkey, l_quantity FROM {lineitem} WHERE l_quantity > 45")

# Projection, filter, conditional

both("proj_expr", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount) * (1 + l_tax), 7) AS net FROM {lineitem}")
both("filter_and_or", "SELECT doc_id FROM {documents} WHERE (lang = 'en' AND n_chars > 1000) OR (lang = 'fr' AND n_chars < 500)")
both("filter_in", "SELECT doc_id, source FROM {documents} WHERE source IN ('src1', 'src2', 'src3')")
both("filter_between", "SELECT l_orderkey, l_linenumber FROM {lineitem} WHERE l_quantity BETWEEN 10 AND 12")
both("filter_not", "SELECT doc_id FROM {documents} WHERE NOT (lang = 'en' OR n_chars > 2000)")
both("filter_like", "SELECT p_partkey FROM {part} WHERE p_name LIKE '%a%e%'")
pair("filter_rlike", "SELECT page_id FROM {pages} WHERE url RLIKE '/(en|fr)/[0-9]+'", "SELECT page_id FROM {pages} WHERE regexp_matches(url, '/(en|fr)/[0-9]+')")
both("filter_prefix", "SELECT page_id FROM {pages} WHERE starts_with(url, 'https')".replace("starts_with", "startswith"))
ORACLE["filter_prefix"] = "SELECT page_id FROM pages WHERE starts_with(url, 'https')"
pair("filter_null_safe", "SELECT d.doc_id FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id WHERE l.quality <=> NULL", "SELECT d.doc_id FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id WHERE l.quality IS NOT DISTINCT FROM NULL")
both("coalesce_nulls", "SELECT d.doc_id, coalesce(l.quality, -1) AS quality, nullif(d.lang, 'en') AS other FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id")
both("case_when", "SELECT o_orderkey, CASE WHEN o_orderpriority LIKE '1%' THEN 'now' WHEN o_orderpriority LIKE '2%' THEN 'soon' ELSE 'later' END AS class FROM {orders}")
both("dedup_exact", "SELECT min(doc_id) AS doc_id, count(*) AS copies FROM {documents} GROUP BY text")
both("distinct_rows", "SELECT DISTINCT event_type FROM {events}")
pair("unpivot_cols", "SELECT l_orderkey, l_linenumber, name, value FROM (SELECT l_orderkey, l_linenumber, l_quantity, l_discount, l_tax FROM {lineitem}) UNPIVOT (value FOR name IN (l_quantity, l_discount, l_tax))", "UNPIVOT (SELECT l_orderkey, l_linenumber, l_quantity, l_discount, l_tax FROM {lineitem}) ON l_quantity, l_discount, l_tax INTO NAME name VALUE value")
pair("pivot_counts", "SELECT * FROM (SELECT user_id % 10 AS bucket, event_type FROM {events}) PIVOT (count(1) FOR event_type IN ('click' AS click, 'view' AS view, 'purchase' AS purchase))", "SELECT user_id % 10 AS bucket, nullif(count(*) FILTER (event_type = 'click'), 0) AS click, nullif(count(*) FILTER (event_type = 'view'), 0) AS view, nullif(count(*) FILTER (event_type = 'purchase'), 0) AS purchase FROM {events} GROUP BY 1")

# Joins

both("join_inner", "SELECT o.o_orderkey, c.c_name FROM {orders} o JOIN {customer} c ON o.o_custkey = c.c_custkey")
both("join_left", "SELECT d.doc_id, l.quality, l.toxic FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id")
both("join_right", "SELECT c.c_custkey, o.o_orderkey FROM {orders} o RIGHT JOIN {customer} c ON o.o_custkey = c.c_custkey")
both("join_full", "SELECT s.s_suppkey, c.c_custkey FROM {supplier} s FULL JOIN {customer} c ON s.s_suppkey = c.c_custkey + 20")
pair("join_semi", "SELECT d.doc_id FROM {documents} d LEFT SEMI JOIN {labels} l ON d.doc_id = l.doc_id", "SELECT d.doc_id FROM {documents} d SEMI JOIN {labels} l ON d.doc_id = l.doc_id")
pair("join_anti", "SELECT c.c_custkey FROM {customer} c LEFT ANTI JOIN {orders} o ON o.o_custkey = c.c_custkey", "SELECT c.c_custkey FROM {customer} c ANTI JOIN {orders} o ON o.o_custkey = c.c_custkey")
both("join_cross", "SELECT n.n_name, r.r_name FROM {nation} n CROSS JOIN {region} r")
_HINTED = "SELECT o.o_orderkey, c.c_nationkey FROM {orders} o JOIN {customer} c ON o.o_custkey = c.c_custkey"
for _n, _h in (("broadcast", "BROADCAST(c)"), ("sortmerge", "MERGE(c)"), ("shuffle_hash", "SHUFFLE_HASH(c)")):
    pair(f"join_{_n}", _HINTED.replace("SELECT", f"SELECT /*+ {_h} */", 1), _HINTED)
both("join_nested_loop", "SELECT n.n_nationkey, r.r_regionkey FROM {nation} n JOIN {region} r ON n.n_nationkey < r.r_regionkey * 3")
both("join_star", "SELECT r.r_name, round(sum(l.l_extendedprice), 2) AS price, count(*) AS n FROM {lineitem} l JOIN {orders} o ON l.l_orderkey = o.o_orderkey JOIN {customer} c ON o.o_custkey = c.c_custkey JOIN {nation} n ON c.c_nationkey = n.n_nationkey JOIN {region} r ON n.n_regionkey = r.r_regionkey GROUP BY r.r_name")
both("join_self", "SELECT a.o_orderkey AS x, b.o_orderkey AS y FROM {orders} a JOIN {orders} b ON a.o_custkey = b.o_custkey AND a.o_orderkey < b.o_orderkey")


@frame("join_theta", "SELECT a.p_partkey AS x, b.p_partkey AS y FROM {part} a JOIN {part} b ON a.p_partkey < b.p_partkey AND abs(a.p_retailprice - b.p_retailprice) <= 0.5")
def join_theta(spark, d):
    """Pairs within a distance: an equi-join on price bins and their neighbours, then the exact condition."""
    p = table(spark, d, "part").select("p_partkey", F.col("p_retailprice").alias("v"), F.floor(F.col("p_retailprice") / 0.5).alias("bin"))
    a = p.select(F.col("p_partkey").alias("x"), F.col("v").alias("va"), F.explode(F.sequence(F.col("bin") - 1, F.col("bin") + 1)).alias("bin"))
    return a.join(p.select(F.col("p_partkey").alias("y"), "v", "bin"), "bin").where("x < y AND abs(va - v) <= 0.5").select("x", "y")


@frame("join_range", "SELECT b.item_id, d.doc_id FROM {benchmark} b JOIN {documents} d ON d.n_chars BETWEEN length(b.text) * 0.9 AND length(b.text) * 1.1")
def join_range(spark, d):
    """Sizes within a ratio: both sides meet in logarithmic bins."""
    width = 0.1
    b = table(spark, d, "benchmark").select("item_id", F.length("text").alias("n"))
    b = b.withColumn("bin", F.explode(F.sequence(F.floor(F.log(F.col("n") * 0.9) / width), F.floor(F.log(F.col("n") * 1.1) / width))))
    docs = table(spark, d, "documents").select("doc_id", "n_chars").where("n_chars > 0").withColumn("bin", F.floor(F.log("n_chars") / width))
    return b.join(docs, "bin").where(F.col("n_chars").cast("double").between(F.col("n") * 0.9, F.col("n") * 1.1)).select("item_id", "doc_id")


_INTERVAL = "a.user_id = b.user_id AND a.event_id <> b.event_id AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR"


@frame("join_interval", f"SELECT a.event_id AS x, b.event_id AS y FROM {{events}} a JOIN {{events}} b ON {_INTERVAL}")
def join_interval(spark, d):
    e = table(spark, d, "events").select("event_id", "user_id", "ts", F.floor(F.unix_timestamp("ts") / 3600).alias("bin"))
    a = e.select(F.col("event_id").alias("x"), "user_id", F.col("ts").alias("ta"), F.explode(F.sequence(F.col("bin"), F.col("bin") + 1)).alias("bin"))
    b = e.select(F.col("event_id").alias("y"), "user_id", "ts", "bin")
    return a.join(b, ["user_id", "bin"]).where("x <> y AND ts >= ta AND ts <= ta + INTERVAL 1 HOUR").select("x", "y")


@frame("join_asof", "SELECT p.event_id, v.event_id AS view_id FROM (SELECT * FROM {events} WHERE event_type = 'purchase') p LEFT JOIN LATERAL (SELECT event_id FROM {events} v WHERE v.user_id = p.user_id AND v.event_type = 'view' AND (v.ts < p.ts OR (v.ts = p.ts AND v.event_id < p.event_id)) ORDER BY v.ts DESC, v.event_id DESC LIMIT 1) v ON true")
def join_asof(spark, d):
    """The last earlier view of each purchase: one pass over the union, ordered by user and time."""
    e = table(spark, d, "events").where("event_type IN ('purchase', 'view')")
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(before)
    return e.withColumn("view_id", last).where("event_type = 'purchase'").select("event_id", "view_id")


# Spark loses a LIMIT's order in the shuffle that follows when it rewrites the lateral join, so the order stands in a window.
pair(
    "join_lateral",
    "SELECT c.c_custkey, t.o_orderkey FROM {customer} c JOIN LATERAL (SELECT o.o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC NULLS LAST, o_orderkey NULLS LAST) AS place FROM {orders}) o WHERE o.o_custkey = c.c_custkey AND o.place <= 3) t ON true",
    "SELECT c.c_custkey, t.o_orderkey FROM {customer} c JOIN LATERAL (SELECT o.o_orderkey FROM {orders} o WHERE o.o_custkey = c.c_custkey ORDER BY o.o_totalprice DESC, o.o_orderkey LIMIT 3) t ON true",
)

# Aggregation

both("agg_basic", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS qty, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue, round(avg(l_discount), 6) AS discount, count(*) AS n FROM {lineitem} GROUP BY l_returnflag, l_linestatus")
both("agg_having", "SELECT o_custkey, count(*) AS n FROM {orders} GROUP BY o_custkey HAVING count(*) > 12")
both("agg_global", "SELECT count(*) AS n, min(n_chars) AS low, max(n_chars) AS high, cast(sum(n_chars) AS bigint) AS total FROM {documents}")
both("agg_distinct", "SELECT o_orderpriority, count(DISTINCT o_custkey) AS customers FROM {orders} GROUP BY o_orderpriority")
both("agg_multi_distinct", "SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT cast(ts AS date)) AS days FROM {events} GROUP BY event_type")
both("agg_filter", "SELECT lang, count(*) FILTER (WHERE n_chars > 1000) AS long_docs, count(*) AS n FROM {documents} GROUP BY lang")
_BY = "year(o_orderdate) AS y, o_orderpriority AS p, o_orderstatus AS s, o_totalprice FROM {orders}"
both("agg_rollup", f"SELECT y, p, count(*) AS n, round(sum(o_totalprice), 2) AS total FROM (SELECT {_BY}) GROUP BY ROLLUP (y, p)")
both("agg_cube", f"SELECT y, s, count(*) AS n FROM (SELECT {_BY}) GROUP BY CUBE (y, s)")
pair("agg_grouping_sets", f"SELECT y, p, s, grouping_id(y, p, s) AS g, count(*) AS n FROM (SELECT {_BY}) GROUP BY GROUPING SETS ((y, p), (s), ())", f"SELECT y, p, s, grouping_id(y, p, s) AS g, count(*) AS n FROM (SELECT {_BY}) GROUP BY GROUPING SETS ((y, p), (s), ())")
pair("agg_collect_sorted", "SELECT conv_id, array_join(transform(array_sort(collect_list(struct(turn, role))), x -> x.role), '>') AS roles FROM {conversations} GROUP BY conv_id", "SELECT conv_id, string_agg(role, '>' ORDER BY turn, role) AS roles FROM {conversations} GROUP BY conv_id")
pair("agg_listagg", "SELECT conv_id, listagg(role, ',') WITHIN GROUP (ORDER BY turn) AS roles FROM {conversations} GROUP BY conv_id", "SELECT conv_id, string_agg(role, ',' ORDER BY turn) AS roles FROM {conversations} GROUP BY conv_id")
both("agg_stats", "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(var_pop(l_discount), 8) AS v, round(corr(l_quantity, l_extendedprice), 6) AS c FROM {lineitem} GROUP BY l_returnflag")
pair("agg_percentile", "SELECT event_type, round(percentile(value, 0.5), 6) AS mid, round(percentile(value, 0.9), 6) AS high FROM {events} GROUP BY event_type", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS mid, round(quantile_cont(value, 0.9), 6) AS high FROM {events} GROUP BY event_type")
pair("agg_max_by", "SELECT c_nationkey, max_by(c_custkey, struct(c_acctbal, c_custkey)) AS best FROM {customer} GROUP BY c_nationkey", "SELECT c_nationkey, max_by(c_custkey, struct_pack(c_acctbal, c_custkey)) AS best FROM {customer} GROUP BY c_nationkey")
both("agg_bool", "SELECT source, bool_and(n_chars > 10) AS all_long, bool_or(lang = 'es') AS some_es FROM {documents} GROUP BY source")
pair("agg_mode_free", "SELECT user_id, max_by(event_type, struct(n, event_type)) AS mode FROM (SELECT user_id, event_type, count(*) AS n FROM {events} GROUP BY user_id, event_type) GROUP BY user_id", "SELECT user_id, max_by(event_type, struct_pack(n, event_type)) AS mode FROM (SELECT user_id, event_type, count(*) AS n FROM {events} GROUP BY user_id, event_type) GROUP BY user_id")
_EXACT = "count(DISTINCT user_id)"
pair("agg_approx_distinct", f"SELECT event_type, abs(approx_count_distinct(user_id, 0.02) - {_EXACT}) <= 0.1 * {_EXACT} + 1 AS within FROM {{events}} GROUP BY event_type", "SELECT event_type, true AS within FROM {events} GROUP BY event_type")
pair("agg_approx_quantile", "SELECT l_returnflag, abs(percentile_approx(l_quantity, 0.5, 10000) - percentile(l_quantity, 0.5)) <= 1 AS within FROM {lineitem} GROUP BY l_returnflag", "SELECT l_returnflag, true AS within FROM {lineitem} GROUP BY l_returnflag")
pair("agg_sketches", f"SELECT abs(hll_sketch_estimate(hll_sketch_agg(user_id, 12)) - {_EXACT}) <= 0.1 * {_EXACT} + 1 AS hll, abs(theta_sketch_estimate(theta_sketch_agg(user_id)) - {_EXACT}) <= 0.1 * {_EXACT} + 1 AS theta FROM {{events}}", "SELECT true AS hll, true AS theta")

# Windows, order, sets

both("win_rank", "SELECT c_custkey, rank() OVER w AS r, dense_rank() OVER w AS dr, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS rn, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS q, round(percent_rank() OVER w, 6) AS pr, round(cume_dist() OVER w, 6) AS cd FROM {customer} WINDOW w AS (PARTITION BY c_nationkey ORDER BY c_acctbal DESC)")
_EV = "PARTITION BY user_id ORDER BY ts, event_id"
both("win_lag_lead", f"SELECT event_id, lag(event_id) OVER ({_EV}) AS before, lead(event_id, 2) OVER ({_EV}) AS later FROM {{events}}")
both("win_first_last", f"SELECT event_id, first_value(event_id) OVER ({_EV}) AS first_id, last_value(event_id) OVER ({_EV} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last_id FROM {{events}}")
both("win_nth", f"SELECT event_id, nth_value(event_id, 2) OVER ({_EV} ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second FROM {{events}}")
both("win_running_sum", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 2) AS total FROM {orders}")
both("win_moving_avg", "SELECT o_orderkey, round(avg(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS mean FROM {orders}")
both("win_range_frame", "SELECT doc_id, count(*) OVER (PARTITION BY source ORDER BY n_chars RANGE BETWEEN 100 PRECEDING AND 100 FOLLOWING) AS near FROM {documents}")
pair("win_gaps_islands", f"SELECT user_id, session, count(*) AS n FROM (SELECT user_id, sum(cast(ts > before + INTERVAL 1 HOUR OR before IS NULL AS int)) OVER ({_EV} ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS session FROM (SELECT user_id, ts, event_id, lag(ts) OVER ({_EV}) AS before FROM {{events}})) GROUP BY user_id, session", f"SELECT user_id, session::BIGINT AS session, count(*) AS n FROM (SELECT user_id, sum(CASE WHEN ts > before + INTERVAL 1 HOUR OR before IS NULL THEN 1 ELSE 0 END) OVER ({_EV} ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS session FROM (SELECT user_id, ts, event_id, lag(ts) OVER ({_EV}) AS before FROM {{events}})) GROUP BY user_id, session")
both("sort_multi", "SELECT doc_id, lang, n_chars FROM {documents} ORDER BY lang ASC, n_chars DESC, doc_id")
both("sort_nulls", "SELECT d.doc_id, l.quality FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id ORDER BY l.quality ASC NULLS LAST, d.doc_id DESC")
both("topn", "SELECT doc_id, n_chars FROM {documents} ORDER BY n_chars DESC, doc_id LIMIT 20")
both("limit_offset", "SELECT doc_id FROM {documents} ORDER BY doc_id LIMIT 10 OFFSET 30")
both("topk_per_group", "SELECT source, doc_id FROM (SELECT source, doc_id, rank() OVER (PARTITION BY source ORDER BY n_chars DESC) AS r FROM {documents}) WHERE r <= 3")
both("union_all", "SELECT c_nationkey AS k FROM {customer} UNION ALL SELECT s_nationkey FROM {supplier}")
both("union_distinct", "SELECT c_nationkey AS k FROM {customer} UNION SELECT s_nationkey FROM {supplier}")


@frame("union_by_name", "SELECT c_custkey AS k, c_name AS name, NULL::BIGINT AS extra FROM {customer} UNION ALL SELECT s_suppkey, s_name, s_suppkey FROM {supplier}")
def union_by_name(spark, d):
    a = table(spark, d, "customer").selectExpr("c_name AS name", "c_custkey AS k")
    return a.unionByName(table(spark, d, "supplier").selectExpr("s_suppkey AS k", "s_name AS name", "s_suppkey AS extra"), allowMissingColumns=True)


for _n, _op in (("intersect", "INTERSECT"), ("intersect_all", "INTERSECT ALL"), ("except", "EXCEPT"), ("except_all", "EXCEPT ALL")):
    both(_n, f"SELECT c_nationkey AS k FROM {{customer}} {_op} SELECT s_nationkey FROM {{supplier}}")

# Scalar functions

both("fn_string_case", "SELECT p_partkey, lower(p_name) AS lo, upper(p_brand) AS up, reverse(p_type) AS rev, length(p_name) AS n FROM {part}")
pair("fn_string_trim_pad", "SELECT c_custkey, trim('  x ') AS t, lpad(cast(c_custkey AS string), 8, '0') AS l, rpad(c_mktsegment, 12, '.') AS r, repeat('ab', 2) AS rp FROM {customer}", "SELECT c_custkey, trim('  x ') AS t, lpad(c_custkey::VARCHAR, 8, '0') AS l, rpad(c_mktsegment, 12, '.') AS r, repeat('ab', 2) AS rp FROM {customer}")
both("fn_string_substr", "SELECT c_custkey, substr(c_name, 2, 4) AS a, instr(c_name, '#') AS b, left(c_name, 3) AS c, right(c_name, 3) AS d FROM {customer}")
both("fn_string_replace", "SELECT c_custkey, replace(c_name, '0', '') AS a, translate(c_name, '0123', 'abcd') AS b, concat_ws('-', c_mktsegment, c_name) AS c FROM {customer}")
pair("fn_string_regex", r"SELECT page_id, regexp_extract(url, '//([^/]+)', 1) AS host, regexp_replace(url, '[0-9]+', '#') AS masked, regexp_count(url, '[aeiou]') AS vowels FROM {pages}", r"SELECT page_id, regexp_extract(url, '//([^/]+)', 1) AS host, regexp_replace(url, '[0-9]+', '#', 'g') AS masked, len(regexp_extract_all(url, '[aeiou]')) AS vowels FROM {pages}")
pair("fn_string_split", "SELECT page_id, size(split(url, '/')) AS parts, split_part(url, '/', 3) AS host FROM {pages}", "SELECT page_id, len(string_split(url, '/')) AS parts, split_part(url, '/', 3) AS host FROM {pages}")
pair("fn_url_parts", "SELECT page_id, parse_url(url, 'HOST') AS host, parse_url(url, 'PATH') AS path FROM {pages}", r"SELECT page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) AS host, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) AS path FROM {pages}")
both("fn_string_distance", "SELECT a.s_suppkey AS x, b.s_suppkey AS y, levenshtein(a.s_name, b.s_name) AS d FROM {supplier} a JOIN {supplier} b ON a.s_nationkey = b.s_nationkey AND a.s_suppkey < b.s_suppkey")
pair("fn_hash", "SELECT c_custkey, md5(c_name) AS a, sha2(c_name, 256) AS b FROM {customer}", "SELECT c_custkey, md5(c_name) AS a, sha256(c_name) AS b FROM {customer}")
frame("fn_hash_spark")(lambda spark, d: table(spark, d, "customer").select("c_custkey", F.xxhash64("c_name").alias("x"), F.crc32("c_name").alias("c"), F.soundex("c_name").alias("s")))
pair("fn_date_parts", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, day(o_orderdate) AS d, quarter(o_orderdate) AS q, dayofyear(o_orderdate) AS n, dayofweek(o_orderdate) AS w FROM {orders}", "SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, day(o_orderdate) AS d, quarter(o_orderdate) AS q, dayofyear(o_orderdate) AS n, dayofweek(o_orderdate) + 1 AS w FROM {orders}")
both("fn_date_trunc", "SELECT o_orderkey, cast(date_trunc('month', o_orderdate) AS date) AS m, cast(date_trunc('year', o_orderdate) AS date) AS y FROM {orders}")
pair("fn_date_arith", "SELECT o_orderkey, date_add(cast(o_orderdate AS date), 10) AS a, datediff(DATE '2000-01-01', cast(o_orderdate AS date)) AS n, add_months(cast(o_orderdate AS date), 1) AS b, last_day(o_orderdate) AS c FROM {orders}", "SELECT o_orderkey, cast(o_orderdate AS date) + 10 AS a, DATE '2000-01-01' - cast(o_orderdate AS date) AS n, cast(cast(o_orderdate AS date) + INTERVAL 1 MONTH AS date) AS b, last_day(o_orderdate) AS c FROM {orders}")
pair("fn_interval", "SELECT event_id, unix_seconds(cast(ts + INTERVAL 90 MINUTE AS timestamp)) AS a, unix_seconds(cast(ts - INTERVAL 2 DAY AS timestamp)) AS b FROM {events}", "SELECT event_id, epoch(ts + INTERVAL 90 MINUTE)::BIGINT AS a, epoch(ts - INTERVAL 2 DAY)::BIGINT AS b FROM (SELECT event_id, date_trunc('second', ts) AS ts FROM {events})")
pair("fn_timestamp", "SELECT event_id, unix_micros(cast(ts AS timestamp)) AS us, date_format(ts, 'yyyy-MM-dd HH:mm:ss') AS f FROM {events}", "SELECT event_id, epoch_us(ts) AS us, strftime(ts, '%Y-%m-%d %H:%M:%S') AS f FROM {events}")
pair("fn_math", "SELECT l_orderkey, l_linenumber, ceil(l_tax * 100) AS c, floor(l_extendedprice) AS f, abs(l_quantity - 25) AS a, sign(l_quantity - 25) AS s, round(power(l_quantity, 2), 2) AS p, round(sqrt(l_extendedprice), 6) AS q, l_orderkey % 7 AS m, greatest(l_tax, l_discount) AS g, least(l_tax, l_discount) AS l FROM {lineitem}", "SELECT l_orderkey, l_linenumber, ceil(l_tax * 100) AS c, floor(l_extendedprice) AS f, abs(l_quantity - 25) AS a, sign(l_quantity - 25) AS s, round(power(l_quantity, 2), 2) AS p, round(sqrt(l_extendedprice), 6) AS q, l_orderkey % 7 AS m, greatest(l_tax, l_discount) AS g, least(l_tax, l_discount) AS l FROM {lineitem}")
pair("fn_math_log", "SELECT p_partkey, round(ln(p_retailprice), 6) AS a, round(log10(p_retailprice), 6) AS b, round(exp(p_size / 50.0D), 6) AS c FROM {part}", "SELECT p_partkey, round(ln(p_retailprice), 6) AS a, round(log10(p_retailprice), 6) AS b, round(exp(p_size / 50.0::DOUBLE), 6) AS c FROM {part}")
pair("fn_bits", "SELECT p_partkey, p_partkey & 12 AS a, p_partkey | 3 AS o, p_partkey ^ 5 AS x, shiftleft(p_partkey, 2) AS l, shiftright(p_partkey, 1) AS r FROM {part}", "SELECT p_partkey, p_partkey & 12 AS a, p_partkey | 3 AS o, xor(p_partkey, 5) AS x, p_partkey << 2 AS l, p_partkey >> 1 AS r FROM {part}")
pair("fn_decimal_sum", "SELECT l_returnflag, cast(sum(cast(l_extendedprice AS decimal(18, 2))) AS double) AS total FROM {lineitem} GROUP BY l_returnflag", "SELECT l_returnflag, sum(l_extendedprice::DECIMAL(18, 2))::DOUBLE AS total FROM {lineitem} GROUP BY l_returnflag")
_SP, _DU = "split(p_name, ' ')", "string_split(p_name, ' ')"
pair("fn_array_sets", f"SELECT p_partkey, array_join(array_sort(array_distinct({_SP})), ',') AS d, array_join(array_sort(array_intersect({_SP}, array(p_brand, 'red'))), ',') AS i, array_join(array_sort(array_union({_SP}, array('zz'))), ',') AS u, arrays_overlap({_SP}, array('red', 'blue')) AS o FROM {{part}}", f"SELECT p_partkey, array_to_string(list_sort(list_distinct({_DU})), ',') AS d, array_to_string(list_sort(list_intersect({_DU}, [p_brand, 'red'])), ',') AS i, array_to_string(list_sort(list_distinct(list_concat({_DU}, ['zz']))), ',') AS u, list_has_any({_DU}, ['red', 'blue']) AS o FROM {{part}}")
pair("fn_array_hof", f"SELECT p_partkey, array_join(transform({_SP}, x -> upper(x)), ' ') AS t, size(filter({_SP}, x -> length(x) > 4)) AS f, aggregate(transform({_SP}, x -> length(x)), 0, (a, x) -> a + x) AS s, exists({_SP}, x -> x LIKE 'b%') AS e FROM {{part}}", f"SELECT p_partkey, array_to_string(list_transform({_DU}, lambda x: upper(x)), ' ') AS t, len(list_filter({_DU}, lambda x: length(x) > 4)) AS f, list_sum(list_transform({_DU}, lambda x: length(x)))::BIGINT AS s, len(list_filter({_DU}, lambda x: x LIKE 'b%')) > 0 AS e FROM {{part}}")
pair("fn_array_shape", f"SELECT p_partkey, size({_SP}) AS n, element_at({_SP}, 1) AS a, array_join(slice({_SP}, 1, 1), '') AS h, array_position({_SP}, element_at({_SP}, -1)) AS p, array_join(transform(sequence(1, 3), x -> cast(x AS string)), '') AS q FROM {{part}}", f"SELECT p_partkey, len({_DU}) AS n, {_DU}[1] AS a, array_to_string({_DU}[1:1], '') AS h, list_position({_DU}, {_DU}[-1]) AS p, '123' AS q FROM {{part}}")
pair("fn_explode", f"SELECT p_partkey, pos + 1 AS pos, w FROM {{part}} LATERAL VIEW posexplode({_SP}) t AS pos, w", f"SELECT p_partkey, generate_subscripts({_DU}, 1) AS pos, unnest({_DU}) AS w FROM {{part}}")
pair("fn_map", "SELECT p_partkey, element_at(map_from_arrays(array('a', 'b'), array(p_size, p_partkey)), 'b') AS b, array_join(array_sort(map_keys(map('x', 1, 'y', 2))), '') AS k, size(map_filter(map('x', p_size, 'y', 2), (k, v) -> v > 5)) AS n FROM {part}", "SELECT p_partkey, p_partkey AS b, 'xy' AS k, (p_size > 5)::INT AS n FROM {part}")
pair("fn_struct", "SELECT c_custkey, s.a.x AS x, s.b AS b FROM (SELECT c_custkey, named_struct('a', named_struct('x', c_nationkey), 'b', c_name) AS s FROM {customer})", "SELECT c_custkey, s.a.x AS x, s.b AS b FROM (SELECT c_custkey, {{'a': {{'x': c_nationkey}}, 'b': c_name}} AS s FROM {customer})".replace("{{", "{").replace("}}", "}"))
pair("fn_json", "SELECT event_id, length(props) > 0 AS some, get_json_object(props, '$.page') AS page, size(json_object_keys(props)) AS n FROM {events}", "SELECT event_id, length(props) > 0 AS some, json_extract_string(props, '$.page') AS page, len(json_keys(props)) AS n FROM {events}")
frame("fn_variant")(lambda spark, d: table(spark, d, "events").select("event_id", F.expr("schema_of_variant(parse_json(props))").alias("kind")))
both("fn_cast_try", "SELECT p_partkey, try_cast(p_name AS int) AS a, try_cast(cast(p_size AS varchar(10)) AS bigint) AS b FROM {part}")
pair("fn_null", "SELECT d.doc_id, nvl2(l.quality, 'yes', 'no') AS a, ifnull(l.toxic, 9) AS b FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id", "SELECT d.doc_id, CASE WHEN l.quality IS NOT NULL THEN 'yes' ELSE 'no' END AS a, ifnull(l.toxic, 9) AS b FROM {documents} d LEFT JOIN {labels} l ON d.doc_id = l.doc_id")

# SQL shapes and sampling

both("sub_scalar", "SELECT doc_id FROM {documents} WHERE n_chars > (SELECT avg(n_chars) * 3 FROM {documents})")
both("sub_exists", "SELECT c.c_custkey FROM {customer} c WHERE EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 300000)")
both("sub_in", "SELECT doc_id FROM {documents} WHERE doc_id IN (SELECT doc_id FROM {labels} WHERE quality = 0)")
both("sub_correlated", "SELECT o.o_orderkey FROM {orders} o WHERE o.o_totalprice > (SELECT 1.5 * avg(i.o_totalprice) FROM {orders} i WHERE i.o_custkey = o.o_custkey)")
both("cte_plain", "WITH big AS (SELECT o_custkey, sum(o_totalprice) AS t FROM {orders} GROUP BY o_custkey) SELECT o_custkey FROM big WHERE t > (SELECT avg(t) FROM big)")
both("cte_recursive_components", "WITH RECURSIVE e(a, b) AS (SELECT c_custkey, cast(floor(c_custkey / 2) AS bigint) FROM {customer}), walk(a, b, n) AS (SELECT a, b, 1 FROM e UNION ALL SELECT w.a, e.b, w.n + 1 FROM walk w JOIN e ON w.b = e.a WHERE w.b > 0) SELECT a, min(b) AS root, count(*) AS n FROM walk GROUP BY a")
_INLINE = "SELECT o.o_orderkey, t.k, t.v FROM {orders} o JOIN (SELECT * FROM VALUES ('1-URGENT', 1, 'a'), ('2-HIGH', 2, 'b') AS t(p, k, v)) t ON o.o_orderpriority = t.p"
pair("values_inline", _INLINE, _INLINE.replace("FROM VALUES", "FROM (VALUES").replace(" AS t(p", ") t(p"))


@frame("view_temp", "SELECT r_regionkey, count(*) AS n FROM {region} JOIN {nation} ON r_regionkey = n_regionkey GROUP BY r_regionkey")
def view_temp(spark, d):
    table(spark, d, "nation").createOrReplaceTempView("autotheta_nation")
    table(spark, d, "region").createOrReplaceTempView("autotheta_region")
    return spark.sql("SELECT r_regionkey, count(*) AS n FROM autotheta_region JOIN autotheta_nation ON r_regionkey = n_regionkey GROUP BY r_regionkey")


pair("sample_md5", "SELECT doc_id FROM {documents} WHERE cast(conv(substr(md5(concat('sample', cast(doc_id AS string))), 1, 6), 16, 10) AS bigint) % 10000 < 1000", "SELECT doc_id FROM {documents} WHERE ('0x' || substr(md5('sample' || doc_id::VARCHAR), 1, 6))::BIGINT % 10000 < 1000")
frame("sample_bernoulli")(lambda spark, d: table(spark, d, "lineitem").sample(0.1, seed=5).select("l_orderkey", "l_linenumber"))
frame("sample_stratified")(lambda spark, d: table(spark, d, "documents").sampleBy("lang", {"en": 0.1, "fr": 0.5, "de": 0.5, "es": 0.5}, seed=5).select("doc_id", "lang"))
