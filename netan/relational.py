"""The relational surface around the networks: each query is one operator on the given tables."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "labels", "conversations")

#: Statements that Spark and DuckDB both take, or (Spark's, DuckDB's).
SQL: dict[str, str | tuple[str, str]] = {
    "rel_scan_filter_project": "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem WHERE l_shipdate >= TIMESTAMP '1995-01-01 00:00:00' AND l_shipdate < TIMESTAMP '1996-01-01 00:00:00'",
    "rel_join_inner": "SELECT n_name, count(*) AS customers, round(sum(c_acctbal), 2) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name",
    "rel_join_multi": "SELECT r_name, n_name, round(sum(l_extendedprice * (1 - l_discount)), 2) AS revenue FROM region JOIN nation ON n_regionkey = r_regionkey JOIN customer ON c_nationkey = n_nationkey JOIN orders ON o_custkey = c_custkey JOIN lineitem ON l_orderkey = o_orderkey GROUP BY r_name, n_name",
    "rel_join_left": "SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN (SELECT * FROM orders WHERE o_orderstatus = 'F') o ON o_custkey = c_custkey GROUP BY c_custkey",
    "rel_join_right": "SELECT c_custkey, count(o_orderkey) AS orders FROM (SELECT * FROM orders WHERE o_orderpriority LIKE '1%') o RIGHT JOIN customer ON o_custkey = c_custkey GROUP BY c_custkey",
    "rel_join_full": "SELECT coalesce(a.k, b.k) AS nationkey, a.c AS customers, b.c AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS c FROM customer WHERE c_acctbal < 0 GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS c FROM supplier WHERE s_acctbal < 0 GROUP BY 1) b ON a.k = b.k",
    "rel_join_semi": ("SELECT c_custkey FROM customer LEFT SEMI JOIN (SELECT o_custkey FROM orders WHERE o_orderpriority LIKE '1%') ON o_custkey = c_custkey", "SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderpriority LIKE '1%')"),
    "rel_join_anti": ("SELECT c_custkey FROM customer LEFT ANTI JOIN (SELECT o_custkey FROM orders WHERE o_orderpriority LIKE '1%') ON o_custkey = c_custkey", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders WHERE o_orderpriority LIKE '1%')"),
    "rel_join_self": "SELECT a.l_partkey AS p, b.l_partkey AS q, count(*) AS c FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey GROUP BY 1, 2 HAVING count(*) > 1",
    "rel_join_cross": "SELECT r_name, count(*) AS pairs FROM region CROSS JOIN nation GROUP BY r_name",
    "rel_join_theta": "SELECT a.p_brand, count(*) AS pairs FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_size < b.p_size GROUP BY a.p_brand",
    "rel_join_broadcast": ("SELECT /*+ BROADCAST(s) */ s_nationkey, count(*) AS lines FROM lineitem JOIN supplier s ON l_suppkey = s_suppkey GROUP BY 1", "SELECT s_nationkey, count(*) AS lines FROM lineitem JOIN supplier s ON l_suppkey = s_suppkey GROUP BY 1"),
    "rel_join_merge": ("SELECT /*+ MERGE(s) */ s_nationkey, count(*) AS lines FROM lineitem JOIN supplier s ON l_suppkey = s_suppkey GROUP BY 1", "SELECT s_nationkey, count(*) AS lines FROM lineitem JOIN supplier s ON l_suppkey = s_suppkey GROUP BY 1"),
    "rel_join_hash": ("SELECT /*+ SHUFFLE_HASH(s) */ s_nationkey, count(*) AS lines FROM lineitem JOIN supplier s ON l_suppkey = s_suppkey GROUP BY 1", "SELECT s_nationkey, count(*) AS lines FROM lineitem JOIN supplier s ON l_suppkey = s_suppkey GROUP BY 1"),
    "rel_join_lateral": "SELECT n_name, t.c_custkey, t.c_acctbal FROM nation, LATERAL (SELECT c_custkey, c_acctbal FROM customer WHERE c_nationkey = n_nationkey ORDER BY c_acctbal DESC, c_custkey LIMIT 3) t",
    "rel_join_interval": "SELECT a.user_id, count(*) AS pairs FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'click' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL '1' HOUR GROUP BY 1",
    "rel_agg_hash": "SELECT l_returnflag, l_linestatus, count(*) AS lines, round(sum(l_quantity), 2) AS quantity, round(avg(l_discount), 6) AS discount, max(l_tax) AS tax FROM lineitem GROUP BY 1, 2",
    "rel_agg_distinct": "SELECT l_suppkey, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY 1",
    "rel_agg_filter": "SELECT o_custkey, count(*) FILTER (WHERE o_orderstatus = 'F') AS done, count(*) FILTER (WHERE o_orderstatus <> 'F') AS others FROM orders GROUP BY 1",
    "rel_agg_having": "SELECT o_custkey, count(*) AS orders FROM orders GROUP BY 1 HAVING count(*) > 12",
    "rel_agg_percentile": ("SELECT o_orderpriority, round(percentile(o_totalprice, 0.5), 4) AS med FROM orders GROUP BY 1", "SELECT o_orderpriority, round(quantile_cont(o_totalprice, 0.5), 4) AS med FROM orders GROUP BY 1"),
    "rel_agg_rollup": "SELECT r_name, n_name, count(*) AS c FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)",
    "rel_agg_cube": "SELECT c_mktsegment, r_name, count(*) AS c FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY CUBE (c_mktsegment, r_name)",
    "rel_agg_grouping_sets": "SELECT c_mktsegment, c_nationkey, count(*) AS c FROM customer GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())",
    "rel_agg_corr": "SELECT round(corr(l_quantity, l_extendedprice), 6) AS r, round(stddev_samp(l_discount), 6) AS s FROM lineitem",
    "rel_win_rank": "SELECT o_orderkey, rank() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC) AS r, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS k FROM orders",
    "rel_win_lead_lag": "SELECT event_id, lag(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, lead(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS after FROM events",
    "rel_win_running": "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW), 2) AS total FROM orders",
    "rel_win_range": "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL '1' HOUR PRECEDING AND CURRENT ROW) AS c FROM events",
    "rel_win_first_last": "SELECT event_id, first_value(event_type) OVER w AS a, last_value(event_type) OVER w AS b FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)",
    "rel_win_ntile": "SELECT c_custkey, ntile(4) OVER (PARTITION BY c_nationkey ORDER BY c_acctbal, c_custkey) AS q FROM customer",
    "rel_sort": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey",
    "rel_topk": "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10",
    "rel_topk_group": "SELECT o_custkey, o_orderkey FROM (SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) t WHERE r <= 2",
    "rel_offset": "SELECT c_custkey FROM customer ORDER BY c_acctbal, c_custkey LIMIT 20 OFFSET 10",
    "rel_union": "SELECT c_nationkey AS k FROM customer UNION ALL SELECT s_nationkey FROM supplier",
    "rel_union_distinct": "SELECT c_nationkey AS k FROM customer UNION SELECT s_nationkey FROM supplier",
    "rel_intersect": "SELECT c_nationkey AS k FROM customer INTERSECT SELECT s_nationkey FROM supplier",
    "rel_except": "SELECT n_nationkey AS k FROM nation EXCEPT SELECT s_nationkey FROM supplier WHERE s_acctbal > 5000",
    "rel_intersect_all": "SELECT c_nationkey AS k FROM customer INTERSECT ALL SELECT s_nationkey FROM supplier",
    "rel_except_all": "SELECT c_nationkey AS k FROM customer EXCEPT ALL SELECT s_nationkey FROM supplier",
    "rel_subquery_scalar": "SELECT o_orderkey FROM orders WHERE o_totalprice > 1.5 * (SELECT avg(o_totalprice) FROM orders)",
    "rel_subquery_exists": "SELECT p_partkey FROM part WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_partkey = p_partkey AND l_quantity > 45)",
    "rel_subquery_in": "SELECT s_suppkey FROM supplier WHERE s_nationkey IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 1)",
    "rel_subquery_correlated": "SELECT o_orderkey FROM orders o WHERE o_totalprice > (SELECT 1.8 * avg(i.o_totalprice) FROM orders i WHERE i.o_custkey = o.o_custkey)",
    "rel_cte": "WITH big AS (SELECT o_custkey, sum(o_totalprice) AS t FROM orders GROUP BY 1) SELECT c_mktsegment, count(*) AS c FROM big JOIN customer ON c_custkey = o_custkey WHERE t > 1000000 GROUP BY 1",
    "rel_recursive": "WITH RECURSIVE tree(id, depth) AS (SELECT r_regionkey + 0, 0 FROM region UNION ALL SELECT n_nationkey + 1000, depth + 1 FROM tree JOIN nation ON n_regionkey = id WHERE depth = 0) SELECT depth, count(*) AS c FROM tree GROUP BY depth",
    "rel_string": ("SELECT doc_id, size(split(text, '\\n')) AS n_lines, length(text) AS n, upper(lang) AS lang FROM documents", "SELECT doc_id, len(string_split(text, chr(10)))::INT AS n_lines, length(text)::INT AS n, upper(lang) AS lang FROM documents"),
    "rel_regex": ("SELECT page_id, regexp_extract(url, '^https?://([^/]*)', 1) AS host, size(regexp_extract_all(html, 'href=', 0)) AS links FROM pages", "SELECT page_id, regexp_extract(url, '^https?://([^/]*)', 1) AS host, len(regexp_extract_all(html, 'href='))::INT AS links FROM pages"),
    "rel_date": "SELECT date_trunc('month', o_orderdate) AS m, count(*) AS c FROM orders GROUP BY 1",
    "rel_math": "SELECT p_partkey, round(sqrt(p_retailprice), 6) AS s, p_size % 7 AS m, floor(p_retailprice / 100) * 1.0 AS f, greatest(p_size, 10) AS g FROM part",
    "rel_null": "SELECT c_custkey, nullif(c_mktsegment, 'BUILDING') AS seg, coalesce(nullif(c_nationkey, 3), -1) AS k FROM customer",
    "rel_case": "SELECT CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS kind, count(*) AS c FROM part GROUP BY 1",
    "rel_cast": "SELECT s_suppkey, cast(s_nationkey AS DOUBLE) AS d, cast(s_suppkey AS VARCHAR(20)) AS t FROM supplier",
    "rel_array": ("SELECT doc_id, array_join(array_sort(array_distinct(split(text, ' '))), ' ') AS words FROM documents", "SELECT doc_id, array_to_string(list_sort(list_distinct(string_split(text, ' '))), ' ') AS words FROM documents"),
    "rel_agg_approx_distinct": ("SELECT count(*) AS suppliers, count_if(abs(approx - exact) <= 0.2 * exact) AS within FROM (SELECT l_suppkey, approx_count_distinct(l_partkey, 0.02) AS approx, count(DISTINCT l_partkey) AS exact FROM lineitem GROUP BY 1)", "SELECT count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_suppkey) AS within FROM lineitem"),
    "rel_agg_approx_percentile": ("SELECT a.o_orderpriority, abs(a.p - b.p) <= 0.02 * b.p AS within FROM (SELECT o_orderpriority, percentile_approx(o_totalprice, 0.5, 10000) AS p FROM orders GROUP BY 1) a JOIN (SELECT o_orderpriority, percentile(o_totalprice, 0.5) AS p FROM orders GROUP BY 1) b ON a.o_orderpriority = b.o_orderpriority", "SELECT DISTINCT o_orderpriority, true AS within FROM orders"),
    "rel_join_skewed": ("SELECT /*+ MERGE(c) */ e.event_type, count(*) AS pairs, sum(c.n) AS weight FROM events e JOIN (SELECT event_type, user_id % 7 AS g, count(*) AS n FROM events GROUP BY 1, 2) c ON e.event_type = c.event_type GROUP BY 1", "SELECT e.event_type, count(*) AS pairs, sum(c.n)::BIGINT AS weight FROM events e JOIN (SELECT event_type, user_id % 7 AS g, count(*) AS n FROM events GROUP BY 1, 2) c ON e.event_type = c.event_type GROUP BY 1"),
    "rel_map": ("SELECT l_orderkey, size(map_from_entries(collect_list(struct(l_partkey, c)))) AS parts FROM (SELECT l_orderkey, l_partkey, count(*) AS c FROM lineitem GROUP BY 1, 2) GROUP BY 1", "SELECT l_orderkey, count(DISTINCT l_partkey)::INT AS parts FROM lineitem GROUP BY 1"),
    "rel_struct": ("SELECT o_custkey, max(struct(o_totalprice, o_orderkey)).o_orderkey AS best FROM orders GROUP BY 1", "SELECT o_custkey, arg_max(o_orderkey, struct_pack(a := o_totalprice, b := o_orderkey)) AS best FROM orders GROUP BY 1"),
    "rel_explode": ("SELECT w, count(*) AS c FROM (SELECT explode(split(text, ' ')) AS w FROM documents) GROUP BY 1 HAVING count(*) > 200", "SELECT w, count(*) AS c FROM (SELECT unnest(string_split(text, ' ')) AS w FROM documents) GROUP BY 1 HAVING count(*) > 200"),
    "rel_json": ("SELECT from_json(props, 'k INT').k AS k, count(*) AS c FROM events GROUP BY 1", "SELECT (props->>'$.k')::INT AS k, count(*) AS c FROM events GROUP BY 1"),
    "rel_vector": ("SELECT label, i, round(avg(x), 5) AS c FROM (SELECT label, posexplode(embedding) AS (i, x) FROM embeddings) GROUP BY 1, 2", "SELECT label, i::INT AS i, round(avg(x), 5) AS c FROM (SELECT label, unnest(embedding)::DOUBLE AS x, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings) GROUP BY 1, 2"),
    "rel_sample": ("SELECT o_orderkey FROM orders WHERE conv(substr(md5(concat('7:', o_orderkey)), 1, 8), 16, 10) % 10 = 0", "SELECT o_orderkey FROM orders WHERE ('0x' || substr(md5('7:' || o_orderkey), 1, 8))::BIGINT % 10 = 0"),
    "rel_pivot": ("SELECT * FROM (SELECT c_mktsegment, c_nationkey % 3 AS g FROM customer) PIVOT (count(*) FOR g IN (0 AS g0, 1 AS g1, 2 AS g2))", "SELECT c_mktsegment, count(*) FILTER (c_nationkey % 3 = 0) AS g0, count(*) FILTER (c_nationkey % 3 = 1) AS g1, count(*) FILTER (c_nationkey % 3 = 2) AS g2 FROM customer GROUP BY 1"),
    "rel_unpivot": ("SELECT s_suppkey, kind, v FROM (SELECT s_suppkey, s_acctbal AS balance, cast(s_nationkey AS DOUBLE) AS nation FROM supplier) UNPIVOT (v FOR kind IN (balance, nation))", "SELECT s_suppkey, 'balance' AS kind, s_acctbal AS v FROM supplier UNION ALL SELECT s_suppkey, 'nation', s_nationkey::DOUBLE FROM supplier"),
}


def _views(spark: SparkSession, sf_dir: str, statement: str) -> dict[str, DataFrame]:
    return {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in TABLES if t in statement}


def _run(statement: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    for name, df in _views(spark, sf_dir, statement).items():
        df.createOrReplaceTempView(name)
    return spark.sql(statement)


def range_join(spark, sf_dir):
    """Price band of each order: orders and bands meet by buckets of the price, the small side exploded over its buckets."""
    orders = spark.read.parquet(f"{sf_dir}/orders.parquet").select("o_orderkey", "o_totalprice")
    bands = spark.range(40).select((F.col("id") * 15_000.0).alias("lo"), ((F.col("id") + 1) * 15_000.0).alias("hi"), F.col("id").alias("band"))
    width = 10_000.0
    bands = bands.withColumn("bucket", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))))
    rows = orders.withColumn("bucket", F.floor(F.col("o_totalprice") / width)).join(F.broadcast(bands), "bucket")
    return rows.where("o_totalprice >= lo AND o_totalprice < hi").select("o_orderkey", "band")


def asof_join(spark, sf_dir):
    """The latest purchase of the user before each error, by one union and a running last value."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet").where("event_type IN ('purchase', 'error')")
    over = Window.partitionBy("user_id").orderBy("ts", F.col("event_type") == "error", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    bought = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(over)
    return events.withColumn("purchase", bought).where("event_type = 'error'").select("event_id", "purchase")


def udf_scalar(spark, sf_dir):
    """An Arrow function on columns: cents of a price."""

    @F.arrow_udf("long")
    def cents(price: pa.Array) -> pa.Array:
        return pa.compute.cast(pa.compute.round(pa.compute.multiply(price, 100.0)), pa.int64())

    return spark.read.parquet(f"{sf_dir}/lineitem.parquet").select("l_orderkey", "l_linenumber", cents("l_extendedprice").alias("cents"))


def udf_pandas(spark, sf_dir):
    def lengths(url):
        return url.str.split("/").str[2].str.len()

    host_length = F.pandas_udf(lengths, "long", F.PandasUDFType.SCALAR)
    return spark.read.parquet(f"{sf_dir}/pages.parquet").select("page_id", host_length("url").alias("n"))


def udf_grouped(spark, sf_dir):
    def spread(rows: pa.Table) -> pa.Table:
        v = rows.column("value").to_numpy()
        return pa.table({"event_type": rows.column("event_type")[:1].combine_chunks(), "spread": pa.array([round(float(v.max() - v.min()), 6)])})

    return spark.read.parquet(f"{sf_dir}/events.parquet").select("event_type", "value").groupBy("event_type").applyInArrow(spread, "event_type string, spread double")


def udf_cogrouped(spark, sf_dir):
    def both(a: pa.Table, b: pa.Table) -> pa.Table:
        key = (a if a.num_rows else b).column(0)[0].as_py()
        return pa.table({"k": pa.array([key], pa.int32()), "customers": [a.num_rows], "suppliers": [b.num_rows]})

    a = spark.read.parquet(f"{sf_dir}/customer.parquet").select(F.col("c_nationkey").alias("k"))
    b = spark.read.parquet(f"{sf_dir}/supplier.parquet").select(F.col("s_nationkey").alias("k"))
    return a.groupBy("k").cogroup(b.groupBy("k")).applyInArrow(both, "k int, customers long, suppliers long")


def udf_table(spark, sf_dir):
    """A table function with partitioned input: lengths of runs of one event type per user."""

    class Runs:
        def __init__(self):
            self.user, self.type, self.n, self.longest = None, None, 0, 0

        def eval(self, row):
            self.user = row["user_id"]
            self.n = self.n + 1 if row["event_type"] == self.type else 1
            self.type = row["event_type"]
            self.longest = max(self.longest, self.n)

        def terminate(self):
            if self.user is not None:
                yield self.user, self.longest

    spark.udtf.register("netan_runs", F.udtf(Runs, returnType="user_id: long, longest: int"))
    spark.read.parquet(f"{sf_dir}/events.parquet").createOrReplaceTempView("events")
    return spark.sql("SELECT * FROM netan_runs(TABLE(SELECT user_id, event_type, ts, event_id FROM events) PARTITION BY user_id ORDER BY (ts, event_id))")


def udf_grouped_aggregate(spark, sf_dir):
    """A grouped aggregate in Arrow: the spread of a user's values."""

    @F.arrow_udf("double")
    def spread(values: pa.Array) -> float:
        return pa.compute.max(values).as_py() - pa.compute.min(values).as_py()

    rows = spark.read.parquet(f"{sf_dir}/events.parquet").groupBy("user_id").agg(spread("value").alias("s"))
    return rows.select("user_id", F.round("s", 6).alias("spread"))


def salted_join(spark, sf_dir):
    """Events with their type's number of events: a type may hold a third of all rows, so its rows are dealt over salts, and the
    small side is there once for each."""
    events = spark.read.parquet(f"{sf_dir}/events.parquet").select("event_id", "event_type")
    counts = events.groupBy("event_type").agg(F.count("*").alias("n"))
    many = counts.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(15))))
    rows = events.withColumn("salt", F.pmod(F.xxhash64("event_id"), F.lit(16)).cast("int")).join(many.hint("merge"), ["event_type", "salt"])
    return rows.select("event_id", "n")


def udf_sql(spark, sf_dir):
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION netan_share(a DOUBLE, b DOUBLE) RETURNS DOUBLE RETURN CASE WHEN b = 0 THEN 0 ELSE a / b END")
    spark.read.parquet(f"{sf_dir}/lineitem.parquet").createOrReplaceTempView("lineitem")
    return spark.sql("SELECT l_suppkey, round(s, 6) AS s FROM (SELECT l_suppkey, netan_share(d, t) AS s FROM (SELECT l_suppkey, sum(l_discount) AS d, sum(l_tax) AS t FROM lineitem GROUP BY 1))")


OTHERS = {
    "rel_join_range": (range_join, "SELECT o_orderkey, floor(o_totalprice / 15000)::BIGINT AS band FROM orders WHERE o_totalprice < 600000"),
    "rel_join_asof": (asof_join, "SELECT e.event_id, (SELECT arg_max(p.event_id, struct_pack(t := p.ts, i := p.event_id)) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts <= e.ts) AS purchase FROM events e WHERE e.event_type = 'error'"),
    "udf_scalar": (udf_scalar, "SELECT l_orderkey, l_linenumber, round(l_extendedprice * 100)::BIGINT AS cents FROM lineitem"),
    "udf_pandas": (udf_pandas, "SELECT page_id, length(string_split(url, '/')[3]) AS n FROM pages"),
    "udf_grouped": (udf_grouped, "SELECT event_type, round(max(value) - min(value), 6) AS spread FROM events GROUP BY 1"),
    "udf_cogrouped": (udf_cogrouped, "SELECT k, sum(c)::BIGINT AS customers, sum(s)::BIGINT AS suppliers FROM (SELECT c_nationkey AS k, 1 AS c, 0 AS s FROM customer UNION ALL SELECT s_nationkey, 0, 1 FROM supplier) GROUP BY 1"),
    "udf_table": (udf_table, "WITH a AS (SELECT user_id, event_type, ts, event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - row_number() OVER (PARTITION BY user_id, event_type ORDER BY ts, event_id) AS g FROM events) SELECT user_id, max(c)::INT AS longest FROM (SELECT user_id, event_type, g, count(*) AS c FROM a GROUP BY 1, 2, 3) GROUP BY 1"),
    "udf_grouped_aggregate": (udf_grouped_aggregate, "SELECT user_id, round(max(value) - min(value), 6) AS spread FROM events GROUP BY 1"),
    "rel_join_salted": (salted_join, "SELECT event_id, count(*) OVER (PARTITION BY event_type) AS n FROM events"),
    "udf_sql": (udf_sql, "SELECT l_suppkey, round(sum(l_discount) / sum(l_tax), 6) AS s FROM lineitem GROUP BY 1"),
}


def queries() -> dict:
    found = {n: (lambda spark, sf_dir, s=s: _run(s if isinstance(s, str) else s[0], spark, sf_dir)) for n, s in SQL.items()}
    return found | {n: f for n, (f, _) in OTHERS.items()}


def oracle_sql() -> dict:
    found = {n: s if isinstance(s, str) else s[1] for n, s in SQL.items()} | {n: s for n, (_, s) in OTHERS.items()}
    return {n: s for n, s in found.items() if s}
