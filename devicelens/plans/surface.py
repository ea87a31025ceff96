"""Queries of what surrounds the methods for their users: storage, sources and sinks, functions for SQL and Python, sets from pairs, and the
remaining aggregations and sorts."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from devicelens.functions import codec, udfs
from devicelens.operators import baselines, distrib, linking
from devicelens.plans.deployment import _near_counter_sql
from devicelens.plans.inputs import Inputs
from devicelens.plans.methods import _WEIGHTS, SETS, _delta
from devicelens.plans.oracle import decoded
from devicelens.plans.registry import ORACLE_SQL, query
from devicelens.plans.surrounding import same
from devicelens.sources import capture
from devicelens.sources.fixture import stored
from devicelens.sources.stored import new_folder
from devicelens.streaming import live

# --- sets from pairs


def _components_sql(pairs: str) -> str:
    """(n, root) of the nodes of pairs."""
    return f"""(WITH RECURSIVE p AS MATERIALIZED ({pairs}), both_ways AS MATERIALIZED (SELECT a, b FROM p UNION SELECT b, a FROM p),
        reach AS (SELECT a AS n, a AS r FROM both_ways UNION SELECT w.b, reach.r FROM reach JOIN both_ways w ON w.a = reach.n) SELECT n, min(r) AS root FROM reach GROUP BY n)"""


_GRIDS = """(SELECT family, addr, addr_key, min(addr_key) OVER (PARTITION BY id1, boots1, boots2, r1 // 20, r2 // 20) AS s0,
    min(addr_key) OVER (PARTITION BY id1, boots1, boots2, (r1 + 10) // 20, (r2 + 10) // 20) AS s1 FROM valid)"""


@query("alias_two_offset_bins", f"SELECT g.family, g.addr, g.addr_key, coalesce(c.root, g.s0) AS set_id FROM {_GRIDS} g LEFT JOIN {_components_sql(f'SELECT DISTINCT s0 AS a, s1 AS b FROM {_GRIDS} h WHERE s0 <> s1')} c ON c.n = g.s0")
def alias_two_offset_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linking.two_grids(Inputs(spark, sf_dir).valid)


_V4 = _near_counter_sql("(SELECT * FROM ipid_samples WHERE addr_key IN (SELECT a FROM address WHERE family = 4))", 65536, 60, 1)
_V6 = _near_counter_sql("fragid_samples", 1 << 32, 1_000_000, 1_000)


def _four(x: Inputs) -> DataFrame:
    return x.ipid_samples.join(x.address.filter("family = 4").select(F.col("a").alias("addr_key")), "addr_key", "left_semi")


@query("ipid_sets_v4", f"SELECT n AS addr_key, root AS set_id FROM {_components_sql(_V4)} c")
def ipid_sets_v4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sets of IPv4 addresses that hang together by shared counters."""
    return linking.connected(baselines.counter_pairs(_four(Inputs(spark, sf_dir)), width=1)).select(F.col("node").alias("addr_key"), F.col("root").alias("set_id"))


@query("fragid_sets_v6_computed", f"SELECT n AS addr_key, root AS set_id FROM {_components_sql(_V6)} c")
def fragid_sets_v6_computed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sets of IPv6 addresses that hang together by shared fragment counters."""
    return linking.connected(baselines.counter_pairs(Inputs(spark, sf_dir).fragid_samples, 1 << 32, 1_000_000, width=1_000)).select(F.col("node").alias("addr_key"), F.col("root").alias("set_id"))


@query("grouped_map_pair_test", _V4)
def grouped_map_pair_test(spark: SparkSession, sf_dir: str) -> DataFrame:
    samples = _four(Inputs(spark, sf_dir))
    return udfs.counter_test(baselines.velocities(samples, 65536, 3), samples, 65536, 60, 1)


@query("tests_per_target", """SELECT 'one probe' AS method, count(*) AS targets, 1 AS tests_per_target, count(*) AS tests FROM address WHERE family = 4
    UNION ALL SELECT 'active tool', count(DISTINCT set_id), 16, 16 * count(DISTINCT set_id) FROM members WHERE family = 4 AND set_id IN (SELECT set_id FROM router_two)""")
def tests_per_target(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    tried = x.members.filter("family = 4").join(x.router_two, "set_id", "left_semi").select("set_id").distinct()
    return linking.tests_per_target(x.address.filter("family = 4"), tried, 1, 16)


# --- storage, sources, sinks


@query("scan_partitioned", "SELECT addr, addr_key, engine_id FROM responses WHERE family = 6 AND scan = 1")
def scan_partitioned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Replies stored by family and scan, bucketed and sorted by address; a scan reads its own partition, joins by address need no shuffle."""
    return partitioned(Inputs(spark, sf_dir).responses).filter("family = 6 AND scan = 1").select("addr", "addr_key", "engine_id")


def partitioned(responses: DataFrame, buckets: int = 8) -> DataFrame:
    spark, name = responses.sparkSession, f"replies_{uuid.uuid4().hex}"
    responses.write.partitionBy("family", "scan").bucketBy(buckets, "addr").sortBy("addr").option("path", new_folder(spark, name)).saveAsTable(name)
    return spark.table(name)


@query("scan_csv_json_orc_roundtrip", "SELECT 'csv' AS format, count(*) AS found, 0::BIGINT AS malformed FROM enterprise_registry UNION ALL SELECT 'json', count(*), 3 FROM packets UNION ALL SELECT 'orc', count(*), 0 FROM mac_registry")
def scan_csv_json_orc_roundtrip(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Registries as CSV and ORC, packets as lines of JSON; lines that don't parse are kept and counted."""
    x = Inputs(spark, sf_dir)
    csv, lines, orc = (new_folder(spark, k) for k in ("csv", "json", "orc"))
    x.enterprise_registry.write.csv(csv, header=True)
    x.packets.write.json(lines)
    spark.createDataFrame([("{",), ("[1]",), ("not json",)], "value string").coalesce(1).write.mode("append").text(lines)
    x.mac_registry.write.orc(orc)
    bad = F.count("_corrupt_record").alias("malformed")
    from_csv = spark.read.csv(csv, header=True, schema="enterprise long, vendor string, _corrupt_record string", mode="PERMISSIVE")
    from_json = spark.read.json(lines, schema="req long, recv_s long, bytes long, _corrupt_record string", mode="PERMISSIVE")
    return (
        from_csv.agg(F.lit("csv").alias("format"), F.count("enterprise").alias("found"), bad)
        .union(from_json.agg(F.lit("json"), F.count("req"), bad))
        .union(spark.read.orc(orc).agg(F.lit("orc"), F.count("prefix"), F.lit(0).cast("long")))
    )


@query("scan_binary_engine_id", "SELECT scan, addr, (length(engine_id) // 2)::INTEGER AS n_bytes, engine_id FROM responses WHERE length(engine_id) % 2 = 0")
def scan_binary_engine_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Identifiers as raw bytes, stored and decoded on reading."""
    folder = new_folder(spark, "binary")
    Inputs(spark, sf_dir).responses.filter("length(engine_id) % 2 = 0").select("scan", "addr", F.unhex("engine_id").alias("payload")).write.parquet(folder)
    return spark.read.parquet(folder).select("scan", "addr", F.octet_length("payload").alias("n_bytes"), F.lower(F.hex("payload")).alias("engine_id"))


def capture_folder(responses: DataFrame) -> str:
    """Replies as lines of text."""
    folder = new_folder(responses.sparkSession, "capture")
    fields = [F.coalesce(F.col(c).cast("string"), F.lit("")) for c in capture.FIELDS]
    responses.select(F.concat_ws("\t", *fields).alias("value")).write.text(folder)
    return folder


_CAPTURED = "SELECT scan, family, addr, addr_key, recv_s, engine_id, boots, engine_time FROM responses"


@query("source_python_capture", _CAPTURED)
def source_python_capture(spark: SparkSession, sf_dir: str) -> DataFrame:
    capture.register(spark)
    return spark.read.format("capture_lines").load(capture_folder(Inputs(spark, sf_dir).responses)).filter("malformed IS NULL").drop("malformed")


@query("source_python_capture_stream", _CAPTURED)
def source_python_capture_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    capture.register(spark)
    stream = spark.readStream.format("capture_lines").load(capture_folder(Inputs(spark, sf_dir).responses))
    return live.final_state(stream.filter("malformed IS NULL").drop("malformed"), "append")


@query("sink_sets", "SELECT * FROM sets")
def sink_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sets stored by class; writing one class again replaces its own partition only."""
    folder, sets = new_folder(spark, "sets"), Inputs(spark, sf_dir).sets.select(*SETS)
    write = lambda df: df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("class").parquet(folder)
    write(sets)
    write(sets.filter("class = 'v6'"))
    return spark.read.parquet(folder).select(*SETS)


@query("sink_stream", "SELECT event_id, user_id FROM events")
def sink_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    return live.to_files(live.events(spark, sf_dir).select("event_id", "user_id"), new_folder(spark, "sink"))


@query("catalog_views", "SELECT class, count(*) AS sets, sum(n)::BIGINT AS addresses, sum((vendor = 'unknown')::INT)::BIGINT AS unknown FROM vendors GROUP BY class")
def catalog_views(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Relations and results of the methods as views, used from SQL alone."""
    x = Inputs(spark, sf_dir)
    udfs.views(spark, {k: getattr(x, k) for k in ("responses", "merged", "valid", "sets", "members", "vendors", "routers", "addr_as")})
    return spark.sql("SELECT class, count(*) AS sets, sum(n) AS addresses, count_if(vendor = 'unknown') AS unknown FROM dl_vendors GROUP BY class")


# --- functions


@query("proj_decoded", f"SELECT scan, addr, coalesce(substr(engine_id, 1, 1) >= '8', false) AS conforming, {decoded('engine_id')}, coalesce(length(engine_id) // 2, 0)::INTEGER AS n_bytes FROM responses")
def proj_decoded(spark: SparkSession, sf_dir: str) -> DataFrame:
    return codec.with_decoded(Inputs(spark, sf_dir).responses).select("scan", "addr", "id.*")


@query("udf_engine_id_arrow", f"SELECT engine_id, format FROM (SELECT engine_id, {decoded('engine_id')} FROM (SELECT DISTINCT engine_id FROM responses) x) y")
def udf_engine_id_arrow(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).responses.select("engine_id").distinct().select("engine_id", udfs.engine_id_format("engine_id").alias("format"))


@query("udaf_knee", f"SELECT value::DOUBLE AS knee FROM ({ORACLE_SQL['knee_threshold']}) k")
def udaf_knee(spark: SparkSession, sf_dir: str) -> DataFrame:
    curve = distrib.ecdf(_delta(spark, sf_dir).filter("family = 4 AND is_router AND delta <= 240"), "delta")
    return curve.agg(udfs.knee_of("value", "frac").alias("knee"))


_FIELDS = f"(SELECT engine_id, substr(engine_id, 1, 1) >= '8' AS conforming, {decoded('engine_id')} FROM (SELECT DISTINCT engine_id FROM responses WHERE engine_id <> '') x)"


@query("udtf_decode", f"""SELECT engine_id, 'conforming' AS field, CASE WHEN conforming THEN 'true' ELSE 'false' END AS value FROM {_FIELDS} a
    UNION ALL SELECT engine_id, 'enterprise', enterprise::VARCHAR FROM {_FIELDS} b WHERE enterprise IS NOT NULL UNION ALL SELECT engine_id, 'data', data FROM {_FIELDS} c""")
def udtf_decode(spark: SparkSession, sf_dir: str) -> DataFrame:
    udfs.register(spark)
    ids = Inputs(spark, sf_dir).responses.select("engine_id").distinct()
    return spark.sql("SELECT i.engine_id, f.field, f.value FROM {ids} i, LATERAL decode_engine_id(i.engine_id) f", ids=ids)


@query("udtf_expand_prefix", """SELECT asn, concat(x // 16777216, '.', (x // 65536) % 256, '.', (x // 256) % 256, '.', x % 256) AS addr FROM (SELECT asn, base + k AS x FROM prefixes CROSS JOIN range(4) r(k) WHERE family = 4) y""")
def udtf_expand_prefix(spark: SparkSession, sf_dir: str) -> DataFrame:
    udfs.register(spark)
    four = Inputs(spark, sf_dir).prefixes.filter("family = 4").selectExpr("asn", "cast(base AS bigint) AS base", "cast(length AS bigint) AS length")
    return spark.sql("SELECT p.asn, t.addr FROM {p} p, LATERAL expand_prefix(p.base, p.length, 4L) t", p=four)


@query("sql_udf_rel_hamming", f"SELECT engine_id, round(ones / (4.0 * length(data)), 6)::DOUBLE AS weight FROM {_WEIGHTS} w")
def sql_udf_rel_hamming(spark: SparkSession, sf_dir: str) -> DataFrame:
    udfs.register(spark)
    ids = Inputs(spark, sf_dir).responses.select("engine_id").distinct().withColumn("id", codec.decode(F.col("engine_id"))).filter("id.format IN ('octets', 'nonconforming') AND id.data <> ''")
    return spark.sql("SELECT engine_id, round(rel_hamming(data), 6) AS weight FROM {ids}", ids=ids.select("engine_id", "id.data"))


@query("fn_map", "SELECT asn, count(*)::INTEGER AS vendors, max(n) AS most, string_agg(vendor, ',' ORDER BY vendor) AS names, string_agg(vendor, ',' ORDER BY vendor) FILTER (n > 1) AS repeated FROM as_vendor GROUP BY asn")
def fn_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The vendors of each network as a map; a network has no more of them than the registries hold."""
    per = Inputs(spark, sf_dir).as_vendor.groupBy("asn").agg(F.map_from_entries(F.collect_list(F.struct("vendor", "n"))).alias("m"))
    joined = lambda m: F.array_join(F.array_sort(F.map_keys(m)), ",")
    repeated = F.map_filter("m", lambda _, n: n > 1)
    return per.select("asn", F.size("m").alias("vendors"), F.array_max(F.map_values("m")).alias("most"), joined(F.col("m")).alias("names"), F.when(F.size(repeated) > 0, joined(repeated)).alias("repeated"))


_DOTTED = "[0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}"


@query("fn_ipv4_in_text", f"SELECT doc_id, len(regexp_extract_all(text, '{_DOTTED}'))::INTEGER AS n, regexp_extract_all(text, '{_DOTTED}')[1] AS first_addr FROM documents WHERE regexp_matches(text, '{_DOTTED}')")
def fn_ipv4_in_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = F.regexp_extract_all("text", F.lit(f"({_DOTTED})"), F.lit(1))
    return Inputs(spark, sf_dir).documents.filter(F.col("text").rlike(_DOTTED)).select("doc_id", F.size(found).alias("n"), F.get(found, F.lit(0)).alias("first_addr"))


# --- aggregations and sorts
same("agg_sort", "SELECT c_nationkey, min(c_name) AS first_name, max(c_name) AS last_name FROM {customer} GROUP BY c_nationkey")
same("agg_any_value", "SELECT n_name, any_value(n_regionkey) AS region, count(*) AS customers FROM {customer} JOIN {nation} ON n_nationkey = c_nationkey GROUP BY n_name")


@query("agg_unpivot", "SELECT event_type, 'even' AS side, count(*) FILTER (user_id % 2 = 0) AS n FROM events GROUP BY 1 UNION ALL SELECT event_type, 'odd', count(*) FILTER (user_id % 2 = 1) FROM events GROUP BY 1")
def agg_unpivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    of = lambda k: F.count(F.when(F.col("user_id") % 2 == k, 1))
    return Inputs(spark, sf_dir).events.groupBy("event_type").agg(of(0).alias("even"), of(1).alias("odd")).unpivot("event_type", ["even", "odd"], "side", "n")


@query("agg_mode", "SELECT c_nationkey, c_mktsegment AS segment, n FROM (SELECT c_nationkey, c_mktsegment, count(*) AS n, row_number() OVER (PARTITION BY c_nationkey ORDER BY count(*) DESC, c_mktsegment) AS k FROM customer GROUP BY 1, 2) x WHERE k = 1")
def agg_mode(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The most frequent value of each group, the first on ties: two partial aggregations, no window."""
    counts = Inputs(spark, sf_dir).customer.groupBy("c_nationkey", "c_mktsegment").agg(F.count("*").alias("n"))
    return counts.groupBy("c_nationkey").agg(F.min_by(F.struct("c_mktsegment", "n"), F.struct(-F.col("n"), F.col("c_mktsegment"))).alias("x")).select("c_nationkey", F.col("x.c_mktsegment").alias("segment"), "x.n")


@query("sort_global", "SELECT o_orderkey, o_totalprice FROM orders")
def sort_global(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A total order by ranges: as many sorted partitions as the session has."""
    return Inputs(spark, sf_dir).orders.select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey")


@query("sort_within_partitions", "SELECT o_custkey, o_orderkey FROM orders")
def sort_within_partitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).orders.select("o_custkey", "o_orderkey").repartition("o_custkey").sortWithinPartitions("o_custkey", "o_orderkey")


# --- streams


@query("st_scan_join", "SELECT a.addr, a.engine_id AS id1, b.engine_id AS id2, a.recv_s AS recv_s1, b.recv_s AS recv_s2 FROM responses a JOIN responses b ON a.addr = b.addr AND a.scan = 1 AND b.scan = 2 AND b.recv_s BETWEEN a.recv_s AND a.recv_s + 1209600")
def st_scan_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = stored(spark, sf_dir, "responses")
    of = lambda k: live.stored_stream(spark, path, "recv_s", "1 day").filter(F.col("scan") == k)
    with live.state_on_disk(spark):
        return live.final_state(live.scan_join(of(1), of(2)), "append")


@query("join_stream_stream", "SELECT c.event_id AS click, p.event_id AS purchase FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts BETWEEN c.ts AND c.ts + INTERVAL 1 HOUR")
def join_stream_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    of = lambda kind, name: live.events(spark, sf_dir).filter(F.col("event_type") == kind).select(F.col("user_id").alias(f"{name}_user"), F.col("event_id").alias(name), F.col("ts").alias(f"{name}_ts"))
    near = F.expr("click_user = purchase_user AND purchase_ts BETWEEN click_ts AND click_ts + INTERVAL 1 HOUR")
    return live.final_state(of("click", "click").join(of("purchase", "purchase"), near).select("click", "purchase"), "append")


@query("st_reboot_detector", """SELECT addr, event_id, change FROM (SELECT addr, event_id, CASE WHEN engine_id <> lag(engine_id) OVER w THEN 'id' WHEN boots > lag(boots) OVER w THEN 'reboot'
    WHEN abs(recv_s - engine_time - lag(recv_s - engine_time) OVER w) > 10 THEN 'clock' END AS change FROM event_replies WINDOW w AS (PARTITION BY addr ORDER BY recv_s, event_id)) x WHERE change IS NOT NULL""")
def st_reboot_detector(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = stored(spark, sf_dir, "event_replies")
    stream = live.stored_stream(spark, path, "recv_s", "2 hours").select("ts", "addr", "event_id", "recv_s", "engine_id", "boots", "engine_time")
    return live.final_state(live.changes(stream), "append")


@query("st_late_data", "SELECT count(*) FILTER (ts >= m - INTERVAL 1 DAY) AS accepted, count(*) FILTER (ts < m - INTERVAL 1 DAY) AS late FROM events CROSS JOIN (SELECT max(ts) AS m FROM events) x")
def st_late_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last hours' events come first, the rest of the last day next, and all others after the watermark has passed them: a batch drops what is behind
    the watermark of the batch before it."""
    events, folder = Inputs(spark, sf_dir).events, new_folder(spark, "late")
    ago = lambda span: events.agg(F.max("ts")).scalar() - F.expr(f"INTERVAL {span}")
    first, day = F.col("ts") >= ago("12 HOURS"), F.col("ts") >= ago("1 DAY")
    for some in (first, day & ~first, ~day):
        events.filter(some).coalesce(1).write.mode("append").parquet(folder)
    stream = spark.readStream.schema(live.EVENTS).option("maxFilesPerTrigger", 1).parquet(folder).withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "2 hours")
    accepted, late = live.late_rows(stream, ["event_id"])
    return spark.createDataFrame([(accepted, late)], "accepted long, late long")
