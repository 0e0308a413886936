"""Queries that a user of a skipping lake runs around it: joins, aggregates, windows, functions, UDFs, streams."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import functions as F


from sift import workloads as W
from sift.cases import lake_sql, query
from sift.operators.joins import as_of_join, range_join
from sift.runtime import table
from sift.streaming import windows

# -- scan, project, filter
lake_sql("scan_parquet", "ev", "SELECT event_id, event_type, value FROM ev")
lake_sql("project_computed", "ev", "SELECT event_id, round(value * 2 + 1, 6) AS twice FROM ev WHERE value > 150")
lake_sql("filter_case_when", "od", "SELECT o_orderkey, CASE WHEN o_totalprice > 300000 THEN 'high' WHEN o_totalprice > 100000 THEN 'mid' ELSE 'low' END AS band FROM od")
lake_sql("filter_isin_subquery", "od", "SELECT o_orderkey FROM od WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_acctbal > 9000) AND o_orderdate < CAST('1996-01-01' AS TIMESTAMP_NTZ)")
lake_sql("filter_exists", "od", "SELECT o_orderkey FROM od WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 48)")
lake_sql("filter_not_in_null", "od", "SELECT o_orderkey FROM od WHERE o_orderpriority NOT IN ('1-URGENT', '2-HIGH')")
lake_sql("filter_ilike", "parts", "SELECT p_partkey FROM parts WHERE p_name ILIKE 'RED%'")


@query("project_nested_field", "SELECT event_id, value AS v FROM events WHERE value > 250")
def project_nested_field(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.struct("value", "user_id").alias("m")).where("m.value > 250").select("event_id", F.col("m.value").alias("v"))


# -- joins
lake_sql("join_broadcast", "od", "SELECT /*+ BROADCAST(n) */ n.n_name, count(*) AS n FROM od JOIN customer c ON o_custkey = c_custkey JOIN nation n ON c_nationkey = n_nationkey WHERE o_totalprice > 200000 GROUP BY n.n_name")
lake_sql("join_sortmerge", "od li", "SELECT /*+ MERGE(li) */ o_orderkey, l_linenumber FROM od JOIN li ON o_orderkey = l_orderkey")
lake_sql("join_shuffle_hash", "od li", "SELECT /*+ SHUFFLE_HASH(od) */ o_orderstatus, count(*) AS n FROM od JOIN li ON o_orderkey = l_orderkey GROUP BY o_orderstatus")
lake_sql("join_left", "od", "SELECT c_custkey, o_orderkey FROM customer LEFT JOIN od ON c_custkey = o_custkey AND o_totalprice > 400000")
lake_sql("join_right", "od", "SELECT o_orderkey, c_name FROM (SELECT * FROM customer WHERE c_acctbal > 5000) c RIGHT JOIN od ON c_custkey = o_custkey")
lake_sql("join_full", "od", "SELECT a.o_orderkey AS x, b.o_orderkey AS y FROM (SELECT * FROM od WHERE o_totalprice < 300000) a FULL OUTER JOIN (SELECT * FROM od WHERE o_totalprice > 100000) b ON a.o_orderkey = b.o_orderkey")
lake_sql("join_semi", "od", "SELECT c_custkey FROM customer LEFT SEMI JOIN od ON c_custkey = o_custkey AND o_totalprice > 450000", "SELECT c_custkey FROM customer SEMI JOIN od ON c_custkey = o_custkey AND o_totalprice > 450000")
lake_sql("join_anti", "od", "SELECT c_custkey FROM customer LEFT ANTI JOIN (SELECT o_custkey FROM od WHERE o_totalprice > 200000) o ON c_custkey = o_custkey", "SELECT c_custkey FROM customer ANTI JOIN (SELECT o_custkey FROM od WHERE o_totalprice > 200000) o ON c_custkey = o_custkey")
lake_sql("join_cross", "", "SELECT r_name, n_name FROM region CROSS JOIN nation")
lake_sql("join_theta", "od", "SELECT count(*) AS n FROM od JOIN customer ON o_totalprice > c_acctbal * 40")
lake_sql("join_interval", "ev", "SELECT a.event_id AS x, b.event_id AS y FROM ev a JOIN ev b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR WHERE a.ts < CAST('2024-01-10' AS TIMESTAMP_NTZ)")


@query("join_range", "SELECT e.event_id, w.k FROM events e JOIN (SELECT k, k * 700 AS lo, k * 700 + 50 AS hi FROM (SELECT unnest(range(0, (SELECT max(event_id) // 700 + 1 FROM events))) AS k)) w ON e.event_id BETWEEN w.lo AND w.hi")
def join_range(spark, sf_dir):
    """Points in ranges through buckets, the ranges being spread over all ids."""
    events = table(spark, sf_dir, "events").select("event_id")
    ranges = events.agg(F.max("event_id").alias("top")).selectExpr("explode(sequence(0L, top div 700)) AS k").selectExpr("k", "k * 700 AS lo", "k * 700 + 50 AS hi")
    return range_join(events, ranges, "event_id", "lo", "hi", 500).select("event_id", "k")


@query("join_asof", "SELECT o.o_orderkey, e.event_id AS last_event FROM (SELECT o_orderkey, o_custkey AS user_id, o_orderdate + INTERVAL 9 YEAR AS ts FROM orders) o ASOF LEFT JOIN (SELECT user_id, ts, max(event_id) AS event_id FROM events GROUP BY 1, 2) e ON o.user_id = e.user_id AND o.ts >= e.ts")
def join_asof(spark, sf_dir):
    """The latest event of the order's user by a shifted order date."""
    left = table(spark, sf_dir, "orders").select("o_orderkey", F.col("o_custkey").alias("user_id"), F.expr("o_orderdate + INTERVAL 9 YEAR").alias("ts"))
    return as_of_join(left, table(spark, sf_dir, "events").select("user_id", "ts", "event_id"), "user_id", "ts", ["event_id"]).select("o_orderkey", F.col("event_id").alias("last_event"))


# -- aggregates
lake_sql("agg_hash", "ev", "SELECT event_type, count(*) AS n, round(sum(value), 4) AS total FROM ev GROUP BY event_type")
lake_sql("agg_sort", "od", "SELECT o_orderstatus, max(o_orderpriority) AS top, min(o_orderpriority) AS low FROM od GROUP BY o_orderstatus")
lake_sql("agg_distinct", "ev", "SELECT event_type, count(DISTINCT user_id) AS users FROM ev GROUP BY event_type")
lake_sql("agg_rollup", "od", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM od GROUP BY ROLLUP (o_orderstatus, o_orderpriority)")
lake_sql("agg_cube", "od", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM od GROUP BY CUBE (o_orderstatus, o_orderpriority)")
lake_sql("agg_grouping_sets", "li", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM li GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
lake_sql("agg_pivot", "li", "SELECT * FROM (SELECT l_returnflag, l_linestatus FROM li) PIVOT (count(*) FOR l_linestatus IN ('F' AS f, 'O' AS o))", "SELECT l_returnflag, count(*) FILTER (WHERE l_linestatus = 'F') AS f, count(*) FILTER (WHERE l_linestatus = 'O') AS o FROM li GROUP BY l_returnflag")
lake_sql("agg_percentile", "ev", "SELECT event_type, round(percentile(value, 0.5), 6) AS median FROM ev GROUP BY event_type", "SELECT event_type, round(quantile_cont(value, 0.5), 6) AS median FROM ev GROUP BY event_type")
lake_sql("agg_max_by", "ev", "SELECT event_type, max_by(event_id, CAST(value * 1000000 AS BIGINT) * 10000000 + event_id) AS top_id, min(ts) AS first_ts FROM ev GROUP BY event_type")
lake_sql("agg_having", "ev", "SELECT user_id, count(*) AS n FROM ev GROUP BY user_id HAVING count(*) > 14")
lake_sql("agg_bool", "ev", "SELECT event_type, bool_or(value > 400) AS any_high, bool_and(value >= 0) AS all_positive FROM ev GROUP BY event_type")


@query("agg_approx_distinct")
def agg_approx_distinct(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"))


# -- windows
_ROWS = "SELECT event_id, user_id, "
lake_sql("win_rank", "ev", _ROWS + "rank() OVER (PARTITION BY user_id ORDER BY value DESC, event_id) AS r FROM ev")
lake_sql("win_dense_rank", "ev", _ROWS + "dense_rank() OVER (PARTITION BY user_id ORDER BY event_type) AS r FROM ev")
lake_sql("win_row_number", "ev", _ROWS + "row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS r FROM ev")
lake_sql("win_ntile", "ev", _ROWS + "ntile(4) OVER (PARTITION BY event_type ORDER BY event_id) AS r FROM ev")
lake_sql("win_lag_lead", "ev", _ROWS + "lag(value) OVER (PARTITION BY user_id ORDER BY event_id) AS before, lead(value) OVER (PARTITION BY user_id ORDER BY event_id) AS after FROM ev")
lake_sql("win_running_sum", "ev", _ROWS + "round(sum(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 4) AS total FROM ev")
lake_sql("win_moving_avg_rows", "ev", _ROWS + "round(avg(value) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 4) AS mean FROM ev")
lake_sql("win_range_frame", "ev", _ROWS + "count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 500 PRECEDING AND CURRENT ROW) AS n FROM ev")
lake_sql("win_first_last", "ev", _ROWS + "first_value(event_id) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS a, last_value(event_id) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS b FROM ev")

# -- order, limit, sets
lake_sql("sort_multi", "od", "SELECT o_orderkey, o_orderpriority, o_totalprice FROM od ORDER BY o_orderpriority, o_totalprice DESC, o_orderkey")
lake_sql("topk_global", "od", "SELECT o_orderkey, o_totalprice FROM od ORDER BY o_totalprice DESC, o_orderkey LIMIT 20")
lake_sql("topk_per_group", "od", "SELECT o_orderpriority, o_orderkey FROM (SELECT o_orderpriority, o_orderkey, row_number() OVER (PARTITION BY o_orderpriority ORDER BY o_totalprice DESC, o_orderkey) AS r FROM od) t WHERE r <= 3")
lake_sql("limit_offset", "od", "SELECT o_orderkey FROM od ORDER BY o_orderkey LIMIT 10 OFFSET 15")
lake_sql("union_all", "", "SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier")
lake_sql("union_distinct", "", "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier")
lake_sql("intersect", "", "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier")
lake_sql("except", "", "SELECT n_nationkey AS k FROM nation EXCEPT SELECT s_nationkey FROM supplier")
lake_sql("except_all", "", "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier")
lake_sql("intersect_all", "", "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier")

# -- functions
lake_sql("str_case_trim", "parts", "SELECT p_partkey, upper(p_name) AS u, trim(concat('  ', p_name, ' ')) AS t, left(p_name, 3) AS a, right(p_name, 3) AS z FROM parts")
lake_sql("str_regex", "web", "SELECT page_id, regexp_extract(url, '^(https?)://', 1) AS scheme, regexp_replace(url, '[0-9]+', '#') AS masked FROM web", "SELECT page_id, regexp_extract(url, '^(https?)://', 1) AS scheme, regexp_replace(url, '[0-9]+', '#', 'g') AS masked FROM web")
lake_sql("str_split", "web", "SELECT page_id, split(url, '/')[2] AS host FROM web", "SELECT page_id, string_split(url, '/')[3] AS host FROM web")
lake_sql("str_levenshtein", "parts", "SELECT p_partkey, levenshtein(p_name, 'red widget') AS d FROM parts")
lake_sql("str_url", "web", "SELECT page_id, parse_url(url, 'HOST') AS host FROM web", "SELECT page_id, regexp_extract(url, '^https?://([^/?#]+)', 1) AS host FROM web")
lake_sql("date_trunc_month", "od", "SELECT CAST(date_trunc('month', o_orderdate) AS DATE) AS m, count(*) AS n FROM od GROUP BY 1")
lake_sql("date_add_months", "od", "SELECT o_orderkey, CAST(o_orderdate + INTERVAL 2 MONTH AS DATE) AS later FROM od")
lake_sql("date_diff", "od", "SELECT o_orderkey, datediff(DAY, CAST('1995-01-01' AS DATE), CAST(o_orderdate AS DATE)) AS days FROM od", "SELECT o_orderkey, date_diff('day', CAST('1995-01-01' AS DATE), CAST(o_orderdate AS DATE)) AS days FROM od")
lake_sql("date_extract", "ev", "SELECT event_id, EXTRACT(YEAR FROM ts) AS y, EXTRACT(MONTH FROM ts) AS m, EXTRACT(DAY FROM ts) AS d, EXTRACT(HOUR FROM ts) AS h FROM ev")
lake_sql("math_mod_floor", "ev", "SELECT event_id, event_id % 7 AS m, CAST(floor(value) AS BIGINT) AS f, CAST(ceil(value) AS BIGINT) AS c FROM ev")
lake_sql("math_bits", "ev", "SELECT event_id, event_id & 12 AS a, event_id | 3 AS o, xor(event_id, 5) AS x FROM ev".replace("xor(event_id, 5)", "event_id ^ 5"), "SELECT event_id, event_id & 12 AS a, event_id | 3 AS o, xor(event_id, 5) AS x FROM ev")
lake_sql("math_geo_mean", "ev", "SELECT event_type, round(exp(avg(ln(value + 1))), 6) AS gm FROM ev GROUP BY event_type")


@query("math_hash")
def math_hash(spark, sf_dir):
    return table(spark, sf_dir, "events").select("event_id", F.xxhash64("event_id", "event_type").alias("h"))


lake_sql("arr_transform", "vectors", "SELECT vec_id, round(aggregate(transform(embedding, x -> CAST(x AS DOUBLE) * 2), 0D, (s, x) -> s + x), 4) AS total FROM vectors", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * 2)), 4) AS total FROM vectors")
lake_sql("arr_exists", "vectors", "SELECT vec_id FROM vectors WHERE exists(embedding, x -> x > 0.4)", "SELECT vec_id FROM vectors WHERE list_max(embedding) > CAST(0.4 AS DOUBLE)")
lake_sql("arr_aggregate", "vectors", "SELECT vec_id, round(aggregate(embedding, 0D, (s, x) -> s + CAST(x AS DOUBLE) * x), 3) AS norm FROM vectors", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: CAST(x AS DOUBLE) * CAST(x AS DOUBLE))), 3) AS norm FROM vectors")
lake_sql("arr_zip_diff", "vectors", "SELECT vec_id, round(CAST(embedding[1] AS DOUBLE) - embedding[0], 5) AS d FROM vectors", "SELECT vec_id, round(CAST(embedding[2] AS DOUBLE) - CAST(embedding[1] AS DOUBLE), 5) AS d FROM vectors")
lake_sql("arr_explode", "texts", "SELECT w, count(*) AS n FROM (SELECT explode(split(text, ' ')) AS w FROM texts) t GROUP BY w", "SELECT w, count(*) AS n FROM (SELECT unnest(string_split(text, ' ')) AS w FROM texts) t GROUP BY w")
lake_sql("map_build", "ev", "SELECT event_id, element_at(map_from_arrays(array('a', 'b'), array(user_id, event_id)), 'a') AS v FROM ev", "SELECT event_id, user_id AS v FROM ev")
lake_sql("json_extract", "ev", "SELECT event_id, CAST(get_json_object(props, '$.k') AS BIGINT) AS k FROM ev", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM ev")
lake_sql("json_schema", "ev", "SELECT event_id, from_json(props, 'k INT').k AS k FROM ev", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM ev")

# -- user-defined functions
_PLUS = "SELECT event_id, round(value * 1.5 + 2, 6) AS v FROM ev"


@query("udf_scalar", _PLUS, "ev")
def udf_scalar(spark, sf_dir):
    f = F.udf(lambda x: x * 1.5 + 2, "double")
    return W.session(spark, sf_dir, "ev").frame("ev", lambda df: df.select("event_id", F.round(f("value"), 6).alias("v")))


@query("udf_pandas", _PLUS, "ev")
def udf_pandas(spark, sf_dir):
    @F.pandas_udf("double")
    def f(x: pd.Series) -> pd.Series:
        return x * 1.5 + 2

    return W.session(spark, sf_dir, "ev").frame("ev", lambda df: df.select("event_id", F.round(f("value"), 6).alias("v")))


@query("udaf_pandas", "SELECT event_type, round(max(value) - min(value), 6) AS spread FROM ev GROUP BY 1", "ev")
def udaf_pandas(spark, sf_dir):
    @F.pandas_udf("double")
    def spread(x: pd.Series) -> float:
        return float(x.max() - x.min())

    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.round(spread("value"), 6).alias("spread"))


@query("sql_udf", _PLUS, "ev")
def sql_udf(spark, sf_dir):
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION half_more(x DOUBLE) RETURNS DOUBLE RETURN x * 1.5 + 2")
    return W.session(spark, sf_dir, "ev").sql("SELECT event_id, round(half_more(value), 6) AS v FROM ev")


@query("udtf_explain", "SELECT strftime(ts, '%Y-%m-%d') AS obj, max(value) > 300 AS keep FROM ev GROUP BY 1", "ev")
def udtf_explain(spark, sf_dir):
    """A table function that lists the decision for every object."""

    @F.udtf(returnType="obj string, keep boolean")
    class ExplainSkip:
        def eval(self, keys: list, kept: list):
            held = set(kept)
            for k in keys:
                yield k.split("obj=")[1].split("/")[0], k in held

    s = W.session(spark, sf_dir, "ev")
    s.add("ev", s.lakes["ev"].source, s.lakes["ev"].store, [k for k in s.lakes["ev"].kinds if k.index == "minmax__value"])
    s.frame("ev", lambda df: df.where("value > 300"))
    d = s.history[-1]
    spark.udtf.register("explain_skip", ExplainSkip)
    strings = lambda xs: F.array(*map(F.lit, xs)).cast("array<string>")
    return ExplainSkip(strings(d.kept + d.skipped), strings(d.kept))


# -- streams, run to their end and read back
def _streamed(key: str, oracle: str | None, build):
    @query(key, oracle)
    def run(spark, sf_dir):
        events = spark.readStream.schema(table(spark, sf_dir, "events").schema).parquet(f"{sf_dir}/events.parquet*")
        return windows.to_end(spark, build(spark, sf_dir, events))


_BUCKET = "CAST(time_bucket(INTERVAL '{w}', ts, TIMESTAMP '1970-01-01 00:00:00') AS TIMESTAMP)"
_streamed("st_tumbling", f"SELECT {_BUCKET.format(w='6 hours')} AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2", lambda spark, d, e: windows.tumbling(e, "6 hours"))
_streamed("st_sliding", "SELECT s AS start, count(*) AS n FROM (SELECT unnest([" + _BUCKET.format(w="12 hours") + ", " + "CAST(time_bucket(INTERVAL '12 hours', ts - INTERVAL '6 hours', TIMESTAMP '1970-01-01 00:00:00') + INTERVAL '6 hours' AS TIMESTAMP)]) AS s FROM events) GROUP BY 1", lambda spark, d, e: windows.sliding(e, "12 hours", "6 hours"))
_streamed("st_session", "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL '8 hours' THEN 0 ELSE 1 END AS fresh FROM events), k AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM k GROUP BY user_id, k", lambda spark, d, e: windows.sessions(e, "8 hours"))
_streamed("st_dedupe", "SELECT DISTINCT user_id, event_type FROM events", lambda spark, d, e: windows.deduplicated(e))
_streamed("st_stream_static_join", "SELECT c_mktsegment, count(*) AS n FROM events JOIN customer ON user_id = c_custkey GROUP BY 1", lambda spark, d, e: windows.with_static(e, table(spark, d, "customer")))
_streamed("st_minmax_per_window", f"SELECT {_BUCKET.format(w='1 day')} AS start, min(value) AS lo, max(value) AS hi FROM events GROUP BY 1", lambda spark, d, e: windows.bounds(e, "1 day"))


@query("st_watermark_late", f"SELECT {_BUCKET.format(w='1 day')} AS start, count(*) AS n FROM events WHERE ts >= TIMESTAMP '2024-01-10' GROUP BY 1 HAVING start + INTERVAL '1 day' <= (SELECT max(ts) FROM events) - INTERVAL '6 hours'")
def st_watermark_late(spark, sf_dir):
    """Events that come after the watermark has passed them are dropped."""
    events = table(spark, sf_dir, "events")
    cut = "ts >= timestamp_ntz'2024-01-10'"
    return windows.late_dropped(spark, events.where(cut), events.where(f"NOT ({cut})"), "1 day", "6 hours")


_streamed("st_stateful", "SELECT user_id, count(*) AS n, max(value) AS top FROM events GROUP BY 1", lambda spark, d, e: windows.running_top(e))

# -- star-schema queries
lake_sql("tpch_q1", "li", "SELECT l_returnflag, l_linestatus, round(sum(l_quantity), 2) AS sum_qty, round(CAST(sum(CAST(l_extendedprice * (1 - l_discount) AS DECIMAL(18,4))) AS DOUBLE), 4) AS revenue, count(*) AS n FROM li WHERE l_shipdate <= CAST('1998-09-02' AS TIMESTAMP_NTZ) GROUP BY l_returnflag, l_linestatus")
lake_sql("tpch_q3", "od li", "SELECT l_orderkey, round(CAST(sum(CAST(l_extendedprice * (1 - l_discount) AS DECIMAL(18,4))) AS DOUBLE), 4) AS revenue FROM customer JOIN od ON c_custkey = o_custkey JOIN li ON l_orderkey = o_orderkey WHERE c_mktsegment = 'BUILDING' AND o_orderdate < CAST('1995-03-15' AS TIMESTAMP_NTZ) AND l_shipdate > CAST('1995-03-15' AS TIMESTAMP_NTZ) GROUP BY l_orderkey ORDER BY revenue DESC, l_orderkey LIMIT 10")
lake_sql("tpch_q5", "od", "SELECT n_name, round(CAST(sum(CAST(o_totalprice AS DECIMAL(18,4))) AS DOUBLE), 4) AS total FROM od JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_regionkey = 2 AND o_orderdate >= CAST('1996-01-01' AS TIMESTAMP_NTZ) AND o_orderdate < CAST('1997-01-01' AS TIMESTAMP_NTZ) GROUP BY n_name")
lake_sql("tpch_q6", "li", "SELECT round(CAST(sum(CAST(l_extendedprice * l_discount AS DECIMAL(18,4))) AS DOUBLE), 4) AS revenue FROM li WHERE l_shipdate >= CAST('1996-01-01' AS TIMESTAMP_NTZ) AND l_shipdate < CAST('1997-01-01' AS TIMESTAMP_NTZ) AND l_discount BETWEEN 0.03 AND 0.07 AND l_quantity < 24")
lake_sql("tpch_q10", "od li", "SELECT c_custkey, round(CAST(sum(CAST(l_extendedprice * (1 - l_discount) AS DECIMAL(18,4))) AS DOUBLE), 4) AS revenue FROM customer JOIN od ON c_custkey = o_custkey JOIN li ON l_orderkey = o_orderkey WHERE o_orderdate >= CAST('1996-01-01' AS TIMESTAMP_NTZ) AND o_orderdate < CAST('1996-04-01' AS TIMESTAMP_NTZ) AND l_returnflag = 'R' GROUP BY c_custkey ORDER BY revenue DESC, c_custkey LIMIT 20")
lake_sql("tpch_q14", "li", "SELECT round(100.0 * sum(CASE WHEN p_type LIKE 'PROMO%' THEN l_extendedprice * (1 - l_discount) ELSE 0.0 END) / sum(l_extendedprice * (1 - l_discount)), 6) AS promo FROM li JOIN part ON l_partkey = p_partkey WHERE l_shipdate >= CAST('1996-09-01' AS TIMESTAMP_NTZ) AND l_shipdate < CAST('1996-10-01' AS TIMESTAMP_NTZ)")

