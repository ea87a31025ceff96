"""Queries of the operators around the methods: filters, joins, aggregations, windows, sets, sorts and functions.

The Spark side uses the DataFrame API, or hints and syntax of Spark's SQL; the oracle text is plain SQL.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from devicelens.functions import codec
from devicelens.operators import linking
from devicelens.plans.inputs import Inputs
from devicelens.plans.registry import query


def same(key: str, text: str, spark_text: str | None = None) -> None:
    """A query whose text both engines understand; {table} in the Spark text is a given table or relation."""
    import re

    names = re.findall(r"\{(\w+)\}", spark_text or text)

    @query(key, re.sub(r"\{(\w+)\}", r"\1", text))
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        x = Inputs(spark, sf_dir)
        return spark.sql(spark_text or text, **{n: getattr(x, n) for n in names})


# scans and filters
@query("scan_parquet_pruned", "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice > 200000")
def scan_parquet_pruned(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).orders.filter(F.col("o_totalprice") > 200000).select("o_orderkey", "o_totalprice")


same("filter_conjunctive", "SELECT o_orderkey FROM {orders} WHERE (o_orderstatus IN ('F', 'O') AND o_totalprice BETWEEN 50000 AND 150000 AND NOT o_orderpriority LIKE '1%') OR o_custkey = 7")
same("filter_in_subquery", "SELECT o_orderkey FROM {orders} WHERE o_custkey IN (SELECT c_custkey FROM {customer} WHERE c_mktsegment = 'BUILDING')")
same("filter_exists", "SELECT c_custkey FROM {customer} c WHERE EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey AND o.o_totalprice > 300000)")
same("filter_not_in_null", "SELECT c_custkey FROM {customer} c WHERE NOT EXISTS (SELECT 1 FROM {orders} o WHERE o.o_custkey = c.c_custkey)")
same("filter_scalar_subquery", "SELECT o_custkey, n FROM (SELECT o_custkey, count(*) AS n FROM {orders} GROUP BY o_custkey) x WHERE n > (SELECT count(*) / count(DISTINCT o_custkey) FROM {orders})")
same("case_bucket", "SELECT CASE WHEN n = 1 THEN '1' WHEN n <= 10 THEN '2-10' WHEN n <= 100 THEN '11-100' ELSE '>100' END AS bucket, count(*) AS sets FROM (SELECT o_custkey, count(*) AS n FROM {orders} GROUP BY o_custkey) x GROUP BY 1")


@query("filter_ipv4_blocks", "SELECT a.addr, s.reason FROM (SELECT addr, v4 FROM address WHERE family = 4 UNION ALL SELECT '10.1.2.3', 167838211) a JOIN special_v4 s ON a.v4 BETWEEN s.lo AND s.hi")
def filter_ipv4_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    rows = x.address.filter("family = 4").select("addr", "v4").union(spark.sql("SELECT '10.1.2.3', 167838211L"))
    return rows.join(F.broadcast(x.special_v4), F.col("v4").between(F.col("lo"), F.col("hi"))).select("addr", "reason")


@query("filter_ipv6_prefix", "SELECT addr FROM address WHERE family = 6 AND starts_with(addr, '2001:0db8:000')")
def filter_ipv6_prefix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).address.filter((F.col("family") == 6) & F.col("addr").startswith("2001:0db8:000")).select("addr")


@query("sample_hash", "SELECT o_orderkey FROM orders WHERE ('0x' || substr(md5(concat(o_orderkey, '|sample')), 1, 8))::BIGINT % 10 = 0")
def sample_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    draw = F.conv(F.substring(F.md5(F.concat(F.col("o_orderkey").cast("string"), F.lit("|sample"))), 1, 8), 16, 10).cast("bigint")
    return Inputs(spark, sf_dir).orders.filter(draw % 10 == 0).select("o_orderkey")


# joins
_JOIN = "SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON c_custkey = o_custkey"
for _key, _hint in (("join_broadcast_hash", "broadcast"), ("join_sort_merge", "merge"), ("join_shuffle_hash", "shuffle_hash")):

    def _hinted(key: str = _key, hint: str = _hint) -> None:
        @query(key, _JOIN)
        def run(spark: SparkSession, sf_dir: str) -> DataFrame:
            x = Inputs(spark, sf_dir)
            return x.orders.join(x.customer.hint(hint), F.col("c_custkey") == F.col("o_custkey")).select("o_orderkey", "c_mktsegment")

    _hinted()
for _key, _how in (("join_left", "LEFT"), ("join_right", "RIGHT"), ("join_full", "FULL")):
    same(_key, f"SELECT c.c_custkey, o.o_orderkey FROM {{customer}} c {_how} JOIN (SELECT * FROM {{orders}} WHERE o_totalprice > 200000) o ON c.c_custkey = o.o_custkey")
same("join_cross", "SELECT r.r_name, n.n_name FROM {region} r CROSS JOIN {nation} n")
same("join_semi", "SELECT s_suppkey FROM {supplier} WHERE s_suppkey IN (SELECT l_suppkey FROM {lineitem})", "SELECT s_suppkey FROM {supplier} LEFT SEMI JOIN {lineitem} ON l_suppkey = s_suppkey")
same("join_anti", "SELECT o_orderkey FROM {orders} WHERE o_orderkey NOT IN (SELECT l_orderkey FROM {lineitem})", "SELECT o_orderkey FROM {orders} LEFT ANTI JOIN {lineitem} ON l_orderkey = o_orderkey")
same("join_nested_loop_theta", "SELECT s.s_suppkey, n.n_name FROM {supplier} s JOIN {nation} n ON s.s_acctbal > n.n_nationkey * 400 AND n.n_nationkey < 3")
same("join_lateral", "SELECT c.c_custkey, o.o_orderkey FROM {customer} c JOIN LATERAL (SELECT o_orderkey FROM {orders} WHERE o_custkey = c.c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) o ON true",
     "SELECT c.c_custkey, o.o_orderkey FROM {customer} c JOIN LATERAL (SELECT o_orderkey FROM {orders} WHERE o_custkey = c.c_custkey ORDER BY o_totalprice DESC, o_orderkey LIMIT 2) o")


@query("join_asof", "SELECT e.event_id, (SELECT max(p.event_id) FROM events p WHERE p.user_id = e.user_id AND p.event_type = 'purchase' AND p.ts = (SELECT max(q.ts) FROM events q WHERE q.user_id = e.user_id AND q.event_type = 'purchase' AND q.ts <= e.ts)) AS last_purchase FROM events e WHERE e.event_type = 'click'")
def join_asof(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last purchase at or before each click: one window over the union, no range join."""
    order = W.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "purchase", 0).otherwise(1), "event_id").rowsBetween(W.unboundedPreceding, 0)
    rows = Inputs(spark, sf_dir).events.filter("event_type IN ('click', 'purchase')")
    return rows.withColumn("last_purchase", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(order)).filter("event_type = 'click'").select("event_id", "last_purchase")


@query("join_interval_overlap", "SELECT count(*) AS overlapping FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND abs(epoch_us(a.ts) - epoch_us(b.ts)) < 1800000000")
def join_interval_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bursts of half an hour that overlap: equi join on hour bins, then the exact test."""
    rows = Inputs(spark, sf_dir).events.select("event_id", "user_id", F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    bin_us = 1_800_000_000
    a = rows.select("user_id", F.col("event_id").alias("ea"), F.col("t").alias("ta"), F.expr(f"t div {bin_us}").alias("bin"))
    b = rows.select("user_id", F.col("event_id").alias("eb"), F.col("t").alias("tb"), F.explode(F.array(*(F.expr(f"t div {bin_us}") + k for k in (-1, 0, 1)))).alias("bin"))
    return a.join(b, ["user_id", "bin"]).filter((F.col("ea") < F.col("eb")) & (F.abs(F.col("ta") - F.col("tb")) < bin_us)).agg(F.count("*").alias("overlapping"))


@query("join_self_pairs", "SELECT m.set_id, m.addr_key AS a, n.addr_key AS b FROM (SELECT *, row_number() OVER (PARTITION BY set_id ORDER BY addr_key) AS k FROM members) m JOIN (SELECT *, row_number() OVER (PARTITION BY set_id ORDER BY addr_key) AS k FROM members) n ON m.set_id = n.set_id AND m.k < n.k WHERE m.k <= 12 AND n.k <= 12")
def join_self_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of the first 12 addresses of every set."""
    return linking.capped_pairs(Inputs(spark, sf_dir).members, 12)


@query("join_salted", _JOIN)
def join_salted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The many rows of a hot key are spread over 8 copies of the other side."""
    x = Inputs(spark, sf_dir)
    left = x.orders.withColumn("salt", F.pmod(F.xxhash64("o_orderkey"), F.lit(8)))
    right = x.customer.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(7).cast("long"))))
    return left.join(right.hint("merge"), (F.col("c_custkey") == F.col("o_custkey")) & (left.salt == right.salt)).select("o_orderkey", "c_mktsegment")


# aggregations
same("agg_hash", "SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum(l_quantity), 2) AS quantity, round(avg(l_discount), 6) AS discount FROM {lineitem} GROUP BY l_returnflag, l_linestatus")
same("agg_distinct", "SELECT count(DISTINCT l_suppkey) AS suppliers FROM {lineitem}")
same("agg_multi_distinct", "SELECT l_returnflag, count(DISTINCT l_suppkey) AS suppliers, count(DISTINCT l_partkey) AS parts FROM {lineitem} GROUP BY l_returnflag")
same("agg_filter_clause", "SELECT event_type, count(*) FILTER (WHERE value > 50) AS over_50, count(*) AS n FROM {events} GROUP BY event_type")
same("agg_grouping_sets", "SELECT n_regionkey, c_mktsegment, count(*) AS n FROM {customer} JOIN {nation} ON n_nationkey = c_nationkey GROUP BY GROUPING SETS ((n_regionkey, c_mktsegment), (n_regionkey), ())")
same("agg_rollup", "SELECT n_regionkey, c_mktsegment, count(*) AS n FROM {customer} JOIN {nation} ON n_nationkey = c_nationkey GROUP BY ROLLUP (n_regionkey, c_mktsegment)")
same("agg_cube", "SELECT n_regionkey, c_mktsegment, count(*) AS n FROM {customer} JOIN {nation} ON n_nationkey = c_nationkey GROUP BY CUBE (n_regionkey, c_mktsegment)")
same("agg_bool", "SELECT user_id, bool_or(value > 90) AS some_high, bool_and(value >= 0) AS all_positive FROM {events} GROUP BY user_id")
same("agg_histogram", "SELECT cast(floor(l_quantity / 10) AS bigint) AS bin, count(*) AS n FROM {lineitem} GROUP BY 1")
same("agg_listagg", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS nations FROM {nation} GROUP BY n_regionkey", "SELECT n_regionkey, listagg(n_name, ',') WITHIN GROUP (ORDER BY n_name) AS nations FROM {nation} GROUP BY n_regionkey")


@query("agg_pivot", "SELECT event_type, count(*) FILTER (user_id % 2 = 0) AS even, count(*) FILTER (user_id % 2 = 1) AS odd FROM events GROUP BY event_type")
def agg_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    side = F.when(F.col("user_id") % 2 == 0, "even").otherwise("odd").alias("side")
    return Inputs(spark, sf_dir).events.select("event_type", side).groupBy("event_type").pivot("side", ["even", "odd"]).count()


@query("agg_collect_sorted", "SELECT set_id, string_agg(addr, ',' ORDER BY addr) AS addresses FROM members GROUP BY set_id")
def agg_collect_sorted(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).members.groupBy("set_id").agg(F.concat_ws(",", F.array_sort(F.collect_list("addr"))).alias("addresses"))


@query("agg_percentile_exact", "SELECT l_returnflag, quantile_cont(l_quantity, 0.5) AS median, quantile_cont(l_quantity, 0.9) AS p90 FROM lineitem GROUP BY 1")
def agg_percentile_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).lineitem.groupBy("l_returnflag").agg(F.percentile("l_quantity", F.lit(0.5)).alias("median"), F.percentile("l_quantity", F.lit(0.9)).alias("p90"))


# windows, sorts, sets
same("win_rank_family", "SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER w AS r, dense_rank() OVER w AS dr, ntile(4) OVER w AS q FROM {orders} WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey)")
same("win_lag_lead", "SELECT event_id, lag(value) OVER w AS before, lead(value) OVER w AS after FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
same("win_first_last_nth", "SELECT event_id, first_value(event_id) OVER w AS first_id, last_value(event_id) OVER w AS last_id, nth_value(event_id, 2) OVER w AS second_id FROM {events} WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING)")
same("win_running_share", "SELECT o_orderkey, round(sum(o_totalprice) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) / sum(o_totalprice) OVER (PARTITION BY o_custkey), 6) AS share FROM {orders}")
same("win_total_share", "SELECT s_nationkey, s_suppkey, round(s_acctbal / sum(abs(s_acctbal)) OVER (PARTITION BY s_nationkey), 6) AS share FROM {supplier}")
same("win_range_frame", "SELECT event_id, count(*) OVER (PARTITION BY addr ORDER BY recv_s RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS last_hour FROM {event_replies}")
same("win_topk_per_group", "SELECT n_nationkey, s_suppkey FROM (SELECT n_nationkey, s_suppkey, row_number() OVER (PARTITION BY n_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS k FROM {supplier} JOIN {nation} ON n_nationkey = s_nationkey) x WHERE k <= 2")
same("topk_heap", "SELECT o_orderkey, o_totalprice FROM {orders} ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
same("topk_ties", "SELECT p_partkey, p_size FROM (SELECT p_partkey, p_size, rank() OVER (ORDER BY p_size DESC) AS r FROM {part}) x WHERE r <= 3")
same("limit_offset", "SELECT o_orderkey FROM {orders} ORDER BY o_orderkey LIMIT 10 OFFSET 5")
same("sort_nulls", "SELECT c_custkey, place FROM (SELECT c_custkey, row_number() OVER (ORDER BY nullif(c_nationkey, 3) DESC NULLS LAST, c_custkey) AS place FROM {customer}) x WHERE place <= 20")
for _key, _op in (("set_union_all", "UNION ALL"), ("set_union_distinct", "UNION"), ("set_intersect", "INTERSECT"), ("set_intersect_all", "INTERSECT ALL"), ("set_except", "EXCEPT"), ("set_except_all", "EXCEPT ALL")):
    same(_key, f"SELECT o_custkey AS k FROM {{orders}} WHERE o_orderstatus = 'F' {_op} SELECT o_custkey FROM {{orders}} WHERE o_totalprice > 200000")


# functions
@query("fn_bits", "SELECT o_orderkey, bit_count(o_orderkey)::INTEGER AS ones, o_orderkey & 255 AS low, xor(o_orderkey, 85) AS flipped, lower(hex(o_orderkey)) AS hexed, md5(o_orderkey::VARCHAR) AS digest FROM orders")
def fn_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    k = F.col("o_orderkey")
    return Inputs(spark, sf_dir).orders.select("o_orderkey", F.bit_count(k).alias("ones"), k.bitwiseAND(255).alias("low"), k.bitwiseXOR(85).alias("flipped"), F.lower(F.hex(k)).alias("hexed"), F.md5(k.cast("string")).alias("digest"))


same("fn_string", "SELECT c_custkey, upper(substr(c_name, 1, 8)) AS head, lpad(cast(c_custkey AS varchar(20)), 8, '0') AS padded, replace(c_mktsegment, 'I', '1') AS swapped, length(c_name) AS n, split_part(c_name, '#', 2) AS tail FROM {customer}",
     "SELECT c_custkey, upper(substr(c_name, 1, 8)) AS head, lpad(cast(c_custkey AS string), 8, '0') AS padded, replace(c_mktsegment, 'I', '1') AS swapped, length(c_name) AS n, split_part(c_name, '#', 2) AS tail FROM {customer}")
same("fn_regex_hosts", "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) AS host FROM {pages}")
same("fn_date", "SELECT o_orderkey, extract(year FROM o_orderdate) AS y, extract(month FROM o_orderdate) AS m, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month FROM {orders}",
     "SELECT o_orderkey, extract(year FROM o_orderdate) AS y, extract(month FROM o_orderdate) AS m, date_format(date_trunc('month', o_orderdate), 'yyyy-MM-dd') AS month FROM {orders}")
same("fn_math", "SELECT l_orderkey, l_linenumber, l_partkey, floor(l_extendedprice) AS lo, ceil(l_extendedprice) AS hi, round(ln(l_extendedprice), 6) AS ln, greatest(l_quantity, 25) AS g, abs(l_quantity - 25) AS d FROM {lineitem}")
same("fn_null", "SELECT event_id, coalesce(nullif(event_type, 'click'), 'none') AS kind FROM {events}")


@query("fn_json", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def fn_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).events.select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("fn_json_variant", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def fn_json_variant(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).events.select("event_id", F.variant_get(F.parse_json("props"), "$.k", "bigint").alias("k"))


@query("fn_array", "SELECT vec_id, len(list_filter(embedding, lambda x: x > 0))::INTEGER AS positive, round(list_max(embedding)::DOUBLE, 6) AS most, round(list_dot_product(embedding, embedding)::DOUBLE, 4) AS squared FROM embeddings")
def fn_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    squared = F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))
    return Inputs(spark, sf_dir).embeddings.select("vec_id", F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.round(F.array_max("embedding").cast("double"), 6).alias("most"), F.round(squared, 4).alias("squared"))


@query("fn_network", "SELECT addr, v4 AS n, v4 - v4 % 256 AS net24 FROM address WHERE family = 4")
def fn_network(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = codec.ip4_to_long(F.col("addr"))
    return Inputs(spark, sf_dir).address.filter("family = 4").select("addr", n.alias("n"), codec.prefix_of(n, 24).alias("net24"))


# sketches: tested by their error bounds
@query("approx_id_counts")
def approx_id_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ids of each scan and of both, from sketches that can be kept and joined later."""
    sketches = Inputs(spark, sf_dir).responses.filter("engine_id IS NOT NULL").groupBy("scan").agg(F.theta_sketch_agg("engine_id").alias("s"))
    one = sketches.agg(F.max(F.when(F.col("scan") == 1, F.col("s"))).alias("a"), F.max(F.when(F.col("scan") == 2, F.col("s"))).alias("b"))
    return one.select(F.theta_sketch_estimate("a").alias("scan_1"), F.theta_sketch_estimate("b").alias("scan_2"), F.theta_sketch_estimate(F.theta_intersection("a", "b")).alias("both"))


@query("approx_heavy_ids")
def approx_heavy_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = Inputs(spark, sf_dir).responses.filter("engine_id IS NOT NULL AND scan = 1")
    return rows.agg(F.expr("approx_top_k(engine_id, 10, 10000)").alias("top")).select(F.explode("top").alias("x")).select(F.col("x.item").alias("engine_id"), F.col("x.count").alias("n"))


@query("approx_ecdf")
def approx_ecdf(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = Inputs(spark, sf_dir).merged.select(F.abs(F.col("r1") - F.col("r2")).alias("gap"))
    return rows.agg(F.percentile_approx("gap", [0.25, 0.5, 0.75, 0.9], 10_000).alias("q")).select(F.posexplode("q").alias("place", "gap_s"))
