"""Queries of the methods: acquisition, decoding, the funnel, identifier quality, alias resolution and its variants."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from devicelens.functions import codec
from devicelens.operators import alias, compare, distrib, funnel, ingest, tags
from devicelens.operators.alias import AliasSpec
from devicelens.plans.inputs import Inputs
from devicelens.plans.oracle import CANON, LIB, alias_sets, decoded
from devicelens.plans.registry import query

# --- acquisition, decoding, clocks


@query("responses_view", "SELECT scan, family, addr, addr_key, recv_s, engine_id, boots, engine_time FROM responses")
def responses_view(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).responses


def _decoded(spark: SparkSession, sf_dir: str) -> DataFrame:
    return codec.with_decoded(Inputs(spark, sf_dir).responses)


@query("engine_id_decode", f"SELECT scan, addr, coalesce(substr(engine_id, 1, 1) >= '8', false) AS conforming, coalesce(length(engine_id) // 2, 0)::INTEGER AS n_bytes, {decoded('engine_id')} FROM responses")
def engine_id_decode(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _decoded(spark, sf_dir).select("scan", "addr", "id.conforming", "id.n_bytes", "id.enterprise", "id.format", "id.data")


@query("engine_id_format", f"""SELECT family, format, count(*) AS ids, round(count(*) / sum(count(*)) OVER (PARTITION BY family), 6) AS share
    FROM (SELECT DISTINCT family, engine_id, format FROM (SELECT family, engine_id, {decoded('engine_id')} FROM responses) x) y GROUP BY family, format""")
def engine_id_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    return distrib.format_share(Inputs(spark, sf_dir).responses, codec.decode(F.col("engine_id"))["format"])


@query("mac_format_render", f"""SELECT DISTINCT engine_id, CASE WHEN format = 'mac' THEN rtrim(regexp_replace(data, '(..)', '\\1:', 'g'), ':')
    WHEN format = 'ipv4' AND length(data) = 8 THEN concat(('0x' || substr(data, 1, 2))::BIGINT, '.', ('0x' || substr(data, 3, 2))::BIGINT, '.', ('0x' || substr(data, 5, 2))::BIGINT, '.', ('0x' || substr(data, 7, 2))::BIGINT)
    WHEN format = 'ipv6' AND length(data) = 32 THEN rtrim(regexp_replace(data, '(....)', '\\1:', 'g'), ':') WHEN format = 'text' THEN decode(unhex(data)) ELSE data END AS readable
    FROM (SELECT engine_id, {decoded('engine_id')} FROM responses) x WHERE engine_id IS NOT NULL""")
def mac_format_render(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _decoded(spark, sf_dir).filter("engine_id IS NOT NULL").select("engine_id", codec.render(F.col("id")).alias("readable")).distinct()


@query("last_reboot", "SELECT scan, addr, recv_s - engine_time AS last_reboot_s FROM responses")
def last_reboot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ingest.with_last_reboot(Inputs(spark, sf_dir).responses).select("scan", "addr", "last_reboot_s")


@query("uptime_now", "SELECT scan, addr, engine_time // 86400 AS days, (engine_time % 86400) // 3600 AS hours, engine_time / 86400::DOUBLE AS uptime_days FROM responses WHERE engine_time > 0")
def uptime_now(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ingest.uptime(Inputs(spark, sf_dir).responses.filter("engine_time > 0")).select("scan", "addr", "days", "hours", "uptime_days")


@query("multi_response", "SELECT req, count(*) AS packets, count(*) - 1 AS extra, sum(bytes)::BIGINT AS bytes, max(recv_s) - min(recv_s) AS duration_s FROM packets GROUP BY req HAVING count(*) > 1")
def multi_response(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ingest.multi_response(Inputs(spark, sf_dir).packets)


@query("multi_response_histogram", "SELECT floor(log10(n))::BIGINT AS power, count(*) AS requests FROM (SELECT count(*) AS n FROM packets GROUP BY req) x GROUP BY 1")
def multi_response_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).packets.groupBy("req").agg(F.count("*").alias("n")).groupBy(F.floor(F.log10("n")).alias("power")).agg(F.count("*").alias("requests"))


@query("dedup_response", """SELECT day, addr, engine_id, boots, engine_time, recv_s, packets, conflict FROM (SELECT recv_s // 86400 AS day, addr, engine_id, boots, engine_time, recv_s, count(*) OVER w AS packets,
    min(engine_id) OVER w <> max(engine_id) OVER w AS conflict, row_number() OVER (PARTITION BY recv_s // 86400, addr ORDER BY recv_s, engine_id, engine_time) AS k
    FROM event_replies WINDOW w AS (PARTITION BY recv_s // 86400, addr)) x WHERE k = 1""")
def dedup_response(spark: SparkSession, sf_dir: str) -> DataFrame:
    return funnel.dedup(Inputs(spark, sf_dir).event_replies.withColumn("day", F.expr("recv_s div 86400")), ("day", "addr"))


@query("amplification", "SELECT req, count(*) AS packets, sum(bytes)::BIGINT AS bytes, round(sum(bytes) / 88.0, 6)::DOUBLE AS factor FROM packets GROUP BY req ORDER BY bytes DESC, req LIMIT 20")
def amplification(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ingest.amplification(Inputs(spark, sf_dir).packets, 88, 20)


@query("amplification_total", "SELECT count(DISTINCT req) AS requests, count(*) AS packets, sum(bytes)::BIGINT AS bytes, round(sum(bytes) / (88.0 * count(DISTINCT req)), 6)::DOUBLE AS factor FROM packets")
def amplification_total(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ingest.amplification_total(Inputs(spark, sf_dir).packets, 88)


@query("id_per_scan_summary", "SELECT scan, family, count(DISTINCT addr) AS addresses, count(DISTINCT engine_id) AS ids FROM responses GROUP BY scan, family")
def id_per_scan_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).responses.groupBy("scan", "family").agg(F.countDistinct("addr").alias("addresses"), F.countDistinct("engine_id").alias("ids"))


MERGED = ["family", "addr", "addr_key", "id1", "id2", "boots1", "boots2", "r1", "r2"]
_MERGED_SQL = """SELECT coalesce(a.family, b.family, z.family) AS family, coalesce(a.addr, b.addr, z.addr) AS addr, coalesce(a.addr_key, b.addr_key, z.addr_key) AS addr_key, a.engine_id AS id1, b.engine_id AS id2, a.boots AS boots1,
    b.boots AS boots2, a.recv_s - a.engine_time AS r1, b.recv_s - b.engine_time AS r2 FROM (SELECT DISTINCT family, addr, addr_key FROM responses) z
    LEFT JOIN (SELECT * FROM responses WHERE scan = 1 AND engine_id <> '') a ON a.addr = z.addr LEFT JOIN (SELECT * FROM responses WHERE scan = 2 AND engine_id <> '') b ON b.addr = z.addr"""


@query("scan_merge", _MERGED_SQL)
def scan_merge(spark: SparkSession, sf_dir: str) -> DataFrame:
    return funnel.two_scans(Inputs(spark, sf_dir).reply_packets, every_target=True).select(*MERGED)


@query("scan_merge_join", _MERGED_SQL)
def scan_merge_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return funnel.two_scans_join(Inputs(spark, sf_dir).reply_packets).select(*MERGED)


@query("reply_collapse", """SELECT r.scan, r.addr, r.engine_id, r.boots, r.engine_time, r.recv_s, p.packets, p.conflict FROM responses r
    JOIN (SELECT scan, addr, count(*) AS packets, coalesce(min(engine_id) <> max(engine_id), false) AS conflict FROM reply_packets GROUP BY scan, addr) p ON p.scan = r.scan AND p.addr = r.addr""")
def reply_collapse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Repeated replies of one scan collapse to the first, which is the reply that the other relations hold."""
    return funnel.dedup(Inputs(spark, sf_dir).reply_packets)


@query("scan_populations", "SELECT family, CASE WHEN in1 AND in2 THEN 'both' WHEN in1 THEN 'only 1' ELSE 'only 2' END AS seen, count(*) AS addresses FROM paired GROUP BY 1, 2")
def scan_populations(spark: SparkSession, sf_dir: str) -> DataFrame:
    seen = Inputs(spark, sf_dir).responses.groupBy("family", "addr").agg(F.bool_or(F.col("scan") == 1).alias("in1"), F.bool_or(F.col("scan") == 2).alias("in2"))
    return seen.groupBy("family", F.when(F.col("in1") & F.col("in2"), "both").when(F.col("in1"), "only 1").otherwise("only 2").alias("seen")).agg(F.count("*").alias("addresses"))


@query("dual_stack_hint", f"""SELECT h.addr, h.addr_key, h.v4, h.v4 IN (SELECT addr FROM responses WHERE family = 4) AS answered FROM (SELECT addr, addr_key,
    concat(('0x' || substr(data, 1, 2))::BIGINT, '.', ('0x' || substr(data, 3, 2))::BIGINT, '.', ('0x' || substr(data, 5, 2))::BIGINT, '.', ('0x' || substr(data, 7, 2))::BIGINT) AS v4
    FROM (SELECT addr, addr_key, {decoded('engine_id')} FROM responses WHERE family = 6 AND scan = 1) x WHERE format = 'ipv4' AND length(data) = 8) h""")
def dual_stack_hint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return alias.dual_stack_hints(Inputs(spark, sf_dir).responses)


@query("target_filter", """SELECT family, addr FROM address a WHERE CASE WHEN family = 4 THEN NOT EXISTS (SELECT 1 FROM special_v4 s WHERE a.v4 BETWEEN s.lo AND s.hi)
    ELSE substr(addr, 1, 14) NOT IN (SELECT DISTINCT concat('2001:0db8:', printf('%04x', s_suppkey)) FROM supplier WHERE s_suppkey % 10 = 3) END""")
def target_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    aliased = x.supplier.filter("s_suppkey % 10 = 3").select(F.format_string("2001:0db8:%04x", "s_suppkey").alias("prefix"))
    return ingest.targets(x.address, aliased).select("family", "addr")


# --- the funnel


def _step_filter(key: str, step: int, extra: str = "") -> None:
    @query(key, f"SELECT family, addr FROM stepped WHERE step = {step}")
    def one(spark: SparkSession, sf_dir: str) -> DataFrame:
        return Inputs(spark, sf_dir).flags.filter(F.col("step") == step).select("family", "addr")


for _k, _key in enumerate(("f_missing_id", "f_not_in_both", "f_inconsistent_id", "f_short_id", "f_promiscuous_id", "f_unroutable_v4", "f_unregistered_mac", "f_zero_time_boots", "f_future_time", "f_inconsistent_boots", "f_inconsistent_reboot"), 1):
    _step_filter(_key, _k)


@query("funnel_counts", f"""SELECT f.family, s.step, s.name, count(*) FILTER (coalesce(x.step, 99) >= s.step) AS entering, count(*) FILTER (x.step = s.step) AS removed, count(*) FILTER (coalesce(x.step, 99) > s.step) AS remaining
    FROM stepped x JOIN (SELECT DISTINCT family FROM responses) f ON f.family = x.family CROSS JOIN (VALUES {', '.join(f"({k}, '{n}')" for k, n in enumerate(funnel.STEPS, 1))}) s(step, name) GROUP BY ALL""")
def funnel_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return funnel.report(Inputs(spark, sf_dir).flags)


_F = {5: "promiscuous_id", 6: "unroutable_v4", 7: "unregistered_mac", 8: "zero_clock", 9: "future_time", 10: "inconsistent_boots", 11: "inconsistent_reboot"}
_OTHERS = " + ".join(f"f{k}::INT" for k in _F)


@query("funnel_standalone", " UNION ALL ".join(f"SELECT family, '{n}' AS name, count(*) FILTER (f{k}) AS dropped_alone, count(*) FILTER (f{k} AND ({_OTHERS}) = 1) AS kept_without FROM stepped WHERE early IS NULL GROUP BY family" for k, n in _F.items()))
def funnel_standalone(spark: SparkSession, sf_dir: str) -> DataFrame:
    return funnel.ablate(Inputs(spark, sf_dir).flags)


@query("funnel_valid", "SELECT family, addr, addr_key, id1 AS engine_id, boots1 AS boots, r1, r2 FROM valid")
def funnel_valid(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).valid.select("family", "addr", "addr_key", F.col("id1").alias("engine_id"), F.col("boots1").alias("boots"), "r1", "r2")


@query("promiscuous_vendor", """SELECT data FROM (SELECT d.data, e.vendor FROM dec d JOIN enterprise_registry e USING (enterprise) WHERE d.early IS NULL AND d.data <> '') x GROUP BY data HAVING count(DISTINCT vendor) > 1""")
def promiscuous_vendor(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    rows = x.merged.withColumn("id", codec.decode(F.col("id1"))).filter(funnel.early_step().isNull())
    return funnel.promiscuous_data(rows, "vendor", x.mac_registry, x.enterprise_registry)


@query("funnel_threshold_sweep", "SELECT 'max_s' AS parameter, t::INTEGER AS threshold, count(*) AS survivors FROM stepped CROSS JOIN (VALUES (1), (2), (5), (10), (20), (60)) v(t) WHERE (step IS NULL OR step = 11) AND abs(r1 - r2) <= t GROUP BY t"
       " UNION ALL SELECT 'min_bytes', t, count(*) FROM early CROSS JOIN (VALUES (3), (4), (5), (8)) v(t) WHERE (early IS NULL OR early = 4) AND length(id1) >= 2 * t GROUP BY t")
def funnel_threshold_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    each = lambda ts: F.explode(F.array(*map(F.lit, ts))).alias("threshold")
    clocks = x.flags.filter("step IS NULL OR step = 11").select(F.abs(F.col("r1") - F.col("r2")).alias("gap"), each((1, 2, 5, 10, 20, 60))).filter("gap <= threshold")
    lengths = x.merged.withColumn("early", funnel.early_step()).filter("early IS NULL OR early = 4").select(F.length("id1").alias("digits"), each((3, 4, 5, 8))).filter("digits >= 2 * threshold")
    count = lambda df, name: df.groupBy("threshold").agg(F.count("*").alias("survivors")).select(F.lit(name).alias("parameter"), "threshold", "survivors")
    return count(clocks, "max_s").union(count(lengths, "min_bytes"))


# --- identifier quality


def _ecdf(rows: str, value: str, by: str = "") -> str:
    """Oracle text of a cumulative distribution."""
    comma = f"{by}, " if by else ""
    part = f"PARTITION BY {by}" if by else ""
    return f"SELECT {comma}value, n, sum(n) OVER ({part} ORDER BY value)::BIGINT AS cum_n, round(sum(n) OVER ({part} ORDER BY value) / sum(n) OVER ({part}), 6) AS frac FROM (SELECT {comma}{value} AS value, count(*) AS n FROM {rows} GROUP BY ALL) h"


@query("addrs_per_engine_id", _ecdf("(SELECT family, engine_id, count(*) AS c FROM responses WHERE scan = 1 AND engine_id IS NOT NULL GROUP BY ALL) x", "c", "family"))
def addrs_per_engine_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return distrib.occurrences(Inputs(spark, sf_dir).responses.filter("scan = 1"), "engine_id", ("family",))


@query("occ_orders_per_customer", _ecdf("(SELECT o_custkey, count(*) AS c FROM orders GROUP BY ALL) x", "c"))
def occ_orders_per_customer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return distrib.occurrences(Inputs(spark, sf_dir).orders, "o_custkey")


@query("occ_events_per_user", _ecdf("(SELECT user_id, count(*) AS c FROM events GROUP BY ALL) x", "c"))
def occ_events_per_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    return distrib.occurrences(Inputs(spark, sf_dir).events, "user_id")


@query("heavy_engine_ids", "SELECT engine_id, count(*) AS n FROM responses WHERE engine_id IS NOT NULL AND scan = 1 GROUP BY engine_id HAVING count(*) > 10 ORDER BY n DESC, engine_id LIMIT 10")
def heavy_engine_ids(spark: SparkSession, sf_dir: str) -> DataFrame:
    return distrib.heavy_hitters(Inputs(spark, sf_dir).responses.filter("scan = 1"), "engine_id", 10, 10)


_ONES = "list_sum(list_transform(range(length(data)), lambda i: bit_count(('0x' || substr(data, (i + 1)::INT, 1))::INT)))"
_WEIGHTS = f"(SELECT engine_id, format, data, {_ONES}::BIGINT AS ones FROM (SELECT engine_id, {decoded('engine_id')} FROM (SELECT DISTINCT engine_id FROM responses) a) b WHERE format IN ('octets', 'nonconforming') AND data <> '')"


def _weights(spark: SparkSession, sf_dir: str) -> DataFrame:
    ids = Inputs(spark, sf_dir).responses.select("engine_id").distinct().withColumn("id", codec.decode(F.col("engine_id")))
    return ids.filter("id.format IN ('octets', 'nonconforming') AND id.data <> ''").select("engine_id", "id.format", "id.data", codec.ones(F.col("id.data")).alias("ones"), codec.rel_hamming(F.col("id.data")).alias("weight"))


@query("hamming_weight", f"SELECT engine_id, format, ones, round(ones / (4.0 * length(data)), 6)::DOUBLE AS weight FROM {_WEIGHTS} w")
def hamming_weight(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _weights(spark, sf_dir).select("engine_id", "format", "ones", F.round("weight", 6).alias("weight"))


@query("hamming_distribution", f"""SELECT format, count(*) AS ids, round(avg(w), 6) AS mean, round(stddev_pop(w), 6) AS sd, round((avg(w * w * w) - 3 * avg(w) * avg(w * w) + 2 * avg(w) ** 3) / stddev_pop(w) ** 3, 5) AS skew
    FROM (SELECT format, (ones / (4.0 * length(data)))::DOUBLE AS w FROM {_WEIGHTS} x) y GROUP BY format""")
def hamming_distribution(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _weights(spark, sf_dir).groupBy("format").agg(F.count("*").alias("ids"), F.round(F.avg("weight"), 6).alias("mean"), F.round(F.stddev_pop("weight"), 6).alias("sd"), F.round(F.skewness("weight"), 5).alias("skew"))


@query("hamming_histogram", f"SELECT format, (ones * 16 // (4 * length(data)))::BIGINT AS bin, count(*) AS ids FROM {_WEIGHTS} x GROUP BY ALL")
def hamming_histogram(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _weights(spark, sf_dir).groupBy("format", F.expr("ones * 16 div (4 * length(data))").alias("bin")).agg(F.count("*").alias("ids"))


@query("hamming_normality", f"""SELECT format, round((avg(w) - 0.5) * sqrt(count(*)) / avg(s), 5) AS z_of_mean, round(avg((abs(w - 0.5) <= s)::INT), 6) AS within_1, round(avg((abs(w - 0.5) <= 2 * s)::INT), 6) AS within_2, round(avg((abs(w - 0.5) <= 3 * s)::INT), 6) AS within_3
    FROM (SELECT format, (ones / (4.0 * length(data)))::DOUBLE AS w, 1 / (2 * sqrt(4.0 * length(data))) AS s FROM {_WEIGHTS} x) y GROUP BY format""")
def hamming_normality(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = _weights(spark, sf_dir).withColumn("s", 1 / (2 * F.sqrt(F.length("data") * F.lit(4.0))))
    inside = lambda k: F.round(F.avg((F.abs(F.col("weight") - 0.5) <= k * F.col("s")).cast("int")), 6).alias(f"within_{k}")
    return rows.groupBy("format").agg(F.round((F.avg("weight") - 0.5) * F.sqrt(F.count("*")) / F.avg("s"), 5).alias("z_of_mean"), inside(1), inside(2), inside(3))


@query("hamming_embeddings", """SELECT label, count(*) AS vectors, round(avg(w), 6) AS mean, round(stddev_pop(w), 6) AS sd FROM (SELECT label, list_sum(list_transform(embedding, lambda x: (x > 0)::INT)) / len(embedding) AS w FROM embeddings) e GROUP BY label""")
def hamming_embeddings(spark: SparkSession, sf_dir: str) -> DataFrame:
    weight = F.size(F.filter("embedding", lambda x: x > 0)) / F.size("embedding")
    return Inputs(spark, sf_dir).embeddings.select("label", weight.alias("w")).groupBy("label").agg(F.count("*").alias("vectors"), F.round(F.avg("w"), 6).alias("mean"), F.round(F.stddev_pop("w"), 6).alias("sd"))


@query("top_id_reboot_spread", """SELECT family, engine_id, count(*) AS addresses, min(r) AS first_s, max(r) AS last_s, max(r) - min(r) AS span_s, quantile_cont(r, 0.5)::DOUBLE AS median_s FROM
    (SELECT family, engine_id, recv_s - engine_time AS r FROM responses WHERE scan = 1) x WHERE (family, engine_id) IN (SELECT (family, engine_id) FROM (SELECT family, engine_id,
    row_number() OVER (PARTITION BY family ORDER BY count(*) DESC, engine_id) AS k FROM responses WHERE scan = 1 AND engine_id IS NOT NULL GROUP BY family, engine_id) y WHERE k <= 3) GROUP BY family, engine_id""")
def top_id_reboot_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ingest.top_id_spread(Inputs(spark, sf_dir).responses.filter("scan = 1"), 3)


@query("top_customer_order_spread", """SELECT o_custkey, count(*) AS orders, datediff('day', min(o_orderdate), max(o_orderdate))::BIGINT AS span_days FROM orders WHERE o_custkey IN (SELECT o_custkey FROM orders GROUP BY 1 ORDER BY count(*) DESC, o_custkey LIMIT 3) GROUP BY 1""")
def top_customer_order_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).orders.groupBy("o_custkey").agg(F.count("*").alias("orders"), F.datediff(F.max("o_orderdate"), F.min("o_orderdate")).cast("long").alias("span_days")).orderBy(F.desc("orders"), "o_custkey").limit(3)


_DELTA = "(SELECT family, addr IN (SELECT addr FROM router_tags) AS is_router, abs(r1 - r2) AS delta FROM stepped WHERE step IS NULL OR step = 11)"


def _delta(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    marked = x.router_tags.select("addr").distinct().withColumn("tag", F.lit(True))
    return x.flags.filter("step IS NULL OR step = 11").join(marked, "addr", "left").select("family", F.coalesce("tag", F.lit(False)).alias("is_router"), F.abs(F.col("r1") - F.col("r2")).alias("delta"))


@query("reboot_delta_ecdf", _ecdf(f"{_DELTA} x", "delta", "family, is_router"))
def reboot_delta_ecdf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return distrib.ecdf(_delta(spark, sf_dir), "delta", ("family", "is_router"))


@query("knee_threshold", f"""SELECT value, frac, score FROM (SELECT value, frac, round(frac - value / greatest(max(value) OVER (), 1), 6) AS score FROM ({_ecdf(f"{_DELTA} x WHERE family = 4 AND is_router AND delta <= 240", "delta")}) c) s ORDER BY score DESC, value LIMIT 1""")
def knee_threshold(spark: SparkSession, sf_dir: str) -> DataFrame:
    return distrib.knee(distrib.ecdf(_delta(spark, sf_dir).filter("family = 4 AND is_router AND delta <= 240"), "delta"))


# --- alias resolution

SETS = ["set_id", "engine_id", "n", "n4", "n6", "boots", "reboot_min", "reboot_max", "class"]


@query("alias_v4", alias_sets("x", CANON, "(SELECT * FROM valid WHERE family = 4) v"))
def alias_v4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return alias.resolve(Inputs(spark, sf_dir).valid, family=4).select(*SETS)


@query("alias_v6", alias_sets("x", CANON, "(SELECT * FROM valid WHERE family = 6) v"))
def alias_v6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return alias.resolve(Inputs(spark, sf_dir).valid, family=6).select(*SETS)


@query("alias_dual", "SELECT * FROM sets")
def alias_dual(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).sets.select(*SETS)


@query("alias_membership", "SELECT set_id, family, addr, addr_key FROM members")
def alias_membership(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).members


@query("alias_class", "SELECT class, n = 1 AS singleton, count(*) AS sets FROM sets GROUP BY ALL")
def alias_class(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).sets.groupBy("class", "singleton").agg(F.count("*").alias("sets"))


def _stats_sql(source: str, by: str = "") -> str:
    comma, group = (f"{by}, ", f"GROUP BY {by}") if by else ("", "")
    return f"""SELECT {comma}count(*) AS sets, count(*) FILTER (n > 1) AS nonsingletons, coalesce(sum(n) FILTER (n > 1), 0)::BIGINT AS addresses_in_them, round(avg(n) FILTER (n > 1), 6) AS mean_size,
        round(coalesce(sum(n) FILTER (n > 1), 0) / sum(n), 6) AS share_covered FROM {source} {group}"""


@query("alias_stats", _stats_sql("sets", "class"))
def alias_stats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return alias.stats(Inputs(spark, sf_dir).sets)


@query("alias_size_ecdf", _ecdf("sets", "n", "class"))
def alias_size_ecdf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return distrib.ecdf(Inputs(spark, sf_dir).sets, "n", ("class",))


@query("router_set_size_ecdf", _ecdf("sets WHERE set_id IN (SELECT set_id FROM router_any)", "n"))
def router_set_size_ecdf(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    return distrib.ecdf(x.sets.join(tags.router_sets(x.members, x.router_tags), "set_id", "left_semi"), "n")


@query("router_sets", "SELECT set_id FROM router_any")
def router_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    return tags.router_sets(x.members, x.router_tags)


@query("router_mode_all", "SELECT set_id FROM members m GROUP BY set_id HAVING bool_and(addr IN (SELECT addr FROM router_tags WHERE source <> 'hoplist'))")
def router_mode_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    return tags.router_sets(x.members, x.router_tags, "all", ("topology", "traceroute"))


@query("router_tag_overview", """SELECT family, source, count(DISTINCT addr) AS addresses, count(DISTINCT addr) FILTER (addr IN (SELECT addr FROM responses)) AS responding
    FROM (SELECT * FROM router_tags UNION ALL SELECT 'union', family, addr FROM router_tags) t GROUP BY ALL""")
def router_tag_overview(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    return tags.overview(x.router_tags, x.responses)


@query("tuple_uniqueness", """SELECT count(*) AS addresses, count(*) FILTER (k = 1) AS unique_addresses, round(count(*) FILTER (k = 1) / count(*), 6) AS share
    FROM valid JOIN (SELECT boots1 AS b, r1 // 20 AS q, count(DISTINCT id1) AS k FROM valid GROUP BY ALL) g ON b = boots1 AND q = r1 // 20""")
def tuple_uniqueness(spark: SparkSession, sf_dir: str) -> DataFrame:
    return alias.tuple_uniqueness(Inputs(spark, sf_dir).valid)


@query("id_reuse_split", "SELECT engine_id, count(*) AS sets, sum(n)::BIGINT AS addresses, max(reboot_max) - min(reboot_min) AS span_s FROM sets GROUP BY engine_id HAVING count(*) > 1")
def id_reuse_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    return alias.reused_ids(Inputs(spark, sf_dir).sets)


def _cells(p: str, q: str) -> str:
    return f"""(SELECT *, (SELECT count(*) FROM {p} z WHERE z.set_id = a) AS n_a, (SELECT count(*) FROM {q} z WHERE z.set_id = b) AS n_b
        FROM (SELECT x.set_id AS a, y.set_id AS b, count(*) AS n_shared FROM {p} x JOIN {q} y USING (addr) GROUP BY ALL) c)"""


_REF = "(SELECT ref_set_id AS set_id, addr FROM counter_sets_v4)"
_REF6 = "(SELECT ref_set_id AS set_id, addr FROM fragid_sets_v6)"
_EXACT = "SELECT count(*) AS exact, count(*) FILTER (n_a = 1) AS exact_singletons, count(*) FILTER (n_a > 1) AS exact_others FROM {} t WHERE n_shared = n_a AND n_a = n_b"
_PARTIAL = "SELECT count(DISTINCT a) AS ours_touched, count(DISTINCT b) AS reference_touched, sum(n_shared)::BIGINT AS shared_addresses FROM {} t"


def _family_members(x: Inputs, family: int | None) -> DataFrame:
    return alias.members(x.valid if family is None else x.valid.filter(F.col("family") == family))


def _table(x: Inputs, kind: str) -> DataFrame:
    reference = {"v4": x.counter_sets_v4.select(F.col("ref_set_id").alias("set_id"), "addr"), "v6": x.fragid_sets_v6.select(F.col("ref_set_id").alias("set_id"), "addr")}
    from devicelens.operators import baselines

    if kind == "names":
        return compare.contingency(x.members, baselines.names(x.ptr, x.name_rules))
    return compare.contingency(_family_members(x, int(kind[1])), reference[kind])


_MEM = {k: f"(SELECT min(addr_key) OVER (PARTITION BY {CANON}) AS set_id, addr FROM valid WHERE family = {k[1]})" for k in ("v4", "v6")}
for _kind, _suffix, _cell in (("v4", "", _cells(_MEM["v4"], _REF)), ("v6", "_v6", _cells(_MEM["v6"], _REF6)), ("names", "_names", _cells("members", "names"))):

    def _pair(kind: str = _kind, suffix: str = _suffix, cell: str = _cell) -> None:
        @query(f"compare_exact{suffix}", _EXACT.format(cell))
        def one(spark: SparkSession, sf_dir: str) -> DataFrame:
            return compare.exact(_table(Inputs(spark, sf_dir), kind))

        @query(f"compare_partial{suffix}", _PARTIAL.format(cell))
        def two(spark: SparkSession, sf_dir: str) -> DataFrame:
            return compare.partial(_table(Inputs(spark, sf_dir), kind))

    _pair()


def _summary_sql(name: str, source: str) -> str:
    return f"SELECT '{name}' AS partition, count(*) AS sets, count(*) FILTER (n > 1) AS nonsingletons, coalesce(sum(n) FILTER (n > 1), 0)::BIGINT AS addresses_in_them, round(avg(n) FILTER (n > 1), 6) AS mean_size FROM (SELECT set_id, count(*) AS n FROM {source} s GROUP BY 1) z"


@query("compare_summary", " UNION ALL ".join(_summary_sql(n, s) for n, s in (("ours", "members"), ("names", "names"), ("counter", _REF), ("fragment", _REF6))))
def compare_summary(spark: SparkSession, sf_dir: str) -> DataFrame:
    from devicelens.operators import baselines

    x = Inputs(spark, sf_dir)
    ref = lambda df: df.select(F.col("ref_set_id").alias("set_id"), "addr")
    return compare.summary({"ours": x.members, "names": baselines.names(x.ptr, x.name_rules), "counter": ref(x.counter_sets_v4), "fragment": ref(x.fragid_sets_v6)})


def _pairwise_sql(key: str, source: str = "valid", where: str = "true") -> str:
    """Oracle text of pair accuracy: sums over groups, for a key of the variant."""
    c2 = "coalesce(sum(n * (n - 1) // 2), 0)::BIGINT"
    base = f"(SELECT v.*, t.device, t.asn FROM {source} v JOIN truth t USING (addr_key) WHERE {where})"
    s = lambda by: f"(SELECT {c2} FROM (SELECT count(*) AS n FROM {base} b GROUP BY {by}) g)"
    return f"""SELECT tp, predicted, actual, round(tp / nullif(predicted, 0), 6) AS precision, round(tp / nullif(actual, 0), 6) AS recall, round(2 * tp / nullif(predicted + actual, 0), 6) AS f1,
        round((every - predicted - actual + 2 * tp) / nullif(every, 0), 6) AS rand_index FROM (SELECT {s(f'device, {key}')} AS tp, {s(key)} AS predicted, {s('device')} AS actual, (SELECT count(*) * (count(*) - 1) / 2 FROM {base} b) AS every) z"""


def _pairwise(x: Inputs, spec: AliasSpec, valid: DataFrame | None = None, where: str = "true") -> DataFrame:
    rows = (x.valid if valid is None else valid).join(x.truth.filter(where).select("addr_key", "device"), "addr_key")
    return compare.pairs_measured(alias.keyed(rows, spec).select(F.col("key").alias("a"), F.col("device").alias("b")))


@query("pairwise_accuracy", _pairwise_sql(CANON))
def pairwise_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _pairwise(Inputs(spark, sf_dir), AliasSpec())


@query("operator_survey", _pairwise_sql(CANON, where="t.asn IN (0, 1, 4, 9, 16, 25)"))
def operator_survey(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _pairwise(Inputs(spark, sf_dir), AliasSpec(), where="asn IN (0, 1, 4, 9, 16, 25)")


@query("completeness_by_device", """SELECT device, sum(n)::BIGINT AS addresses, count(*) AS sets, round(max(n) / sum(n), 6) AS completeness, max((k > 1)::INT) AS merged
    FROM (SELECT m.set_id, t.device, count(*) AS n FROM members m JOIN truth t USING (addr_key) GROUP BY ALL) c JOIN (SELECT m.set_id, count(DISTINCT t.device) AS k FROM members m JOIN truth t USING (addr_key) GROUP BY 1) d USING (set_id) GROUP BY device""")
def completeness_by_device(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    truth = x.members.select("addr", "addr_key").join(x.truth.select("addr_key", F.col("device").alias("set_id")), "addr_key")
    return compare.split_merge(x.members, truth)


# --- variants of the key

VARIANTS = {
    "alias_id_only": (AliasSpec(use_boots=False, reboot="none"), "id1"),
    "alias_tuple_only": (AliasSpec(use_id=False), "boots1, boots2, r1 // 20, r2 // 20"),
    "alias_exact_reboot": (AliasSpec(reboot="exact"), "id1, boots1, boots2, r1, r2"),
    "alias_round": (AliasSpec(reboot="round"), "id1, boots1, boots2, (r1 + 10) // 20, (r2 + 10) // 20"),
    "alias_scan1": (AliasSpec(scans=(1,)), "id1, boots1, r1 // 20"),
    "alias_scan2": (AliasSpec(scans=(2,)), "id1, boots2, r2 // 20"),
    "alias_gap_sessions": (AliasSpec(reboot="gap"), "id1, boots1, boots2, session"),
}
_GAP = "(SELECT *, sum(new) OVER (PARTITION BY id1, boots1, boots2 ORDER BY r1, addr_key) AS session FROM (SELECT *, coalesce(r1 - lag(r1) OVER (PARTITION BY id1, boots1, boots2 ORDER BY r1, addr_key) > 10, false)::INT AS new FROM valid) g0)"
for _name, (_spec, _key) in VARIANTS.items():

    def _variant(name: str = _name, spec: AliasSpec = _spec, key: str = _key) -> None:
        source = f"{_GAP} g" if spec.reboot == "gap" else "valid"

        @query(name, alias_sets("x", key, source))
        def sets(spark: SparkSession, sf_dir: str) -> DataFrame:
            return alias.resolve(Inputs(spark, sf_dir).valid, spec).select(*SETS)

        @query(f"{name}_accuracy", _pairwise_sql(key, _GAP if spec.reboot == "gap" else "valid"))
        def accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
            return _pairwise(Inputs(spark, sf_dir), spec)

    _variant()


WIDTHS = (1, 5, 10, 20, 40, 60)


def _bin_sweep_sql(w: int) -> str:
    key = f"id1, boots1, boots2, r1 // {w}, r2 // {w}"
    return f"""SELECT s.width, s.sets, s.nonsingletons, p.precision, p.recall FROM (SELECT {w}::INTEGER AS width, count(*) AS sets, count(*) FILTER (n > 1) AS nonsingletons FROM (SELECT count(*) AS n FROM valid GROUP BY {key}) x) s
        CROSS JOIN ({_pairwise_sql(key)}) p"""


@query("alias_bin_sweep", " UNION ALL ".join(map(_bin_sweep_sql, WIDTHS)))
def alias_bin_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    return _bin_sweep(x.valid, x.truth)


def _bin_sweep(valid: DataFrame, truth: DataFrame) -> DataFrame:
    """Sets, non-singletons and pair accuracy by width of the bins; a width without rows has no sets."""
    every = F.explode(F.array(*map(F.lit, WIDTHS))).alias("width")
    keyed = lambda rows: alias.keyed(rows.select("*", every), AliasSpec(width_s=F.col("width")))
    sets = keyed(valid).groupBy("width", "key").agg(F.count("*").alias("n")).groupBy("width").agg(F.count("*").alias("sets"), F.count(F.when(F.col("n") > 1, 1)).alias("nonsingletons"))
    pairs = compare.pairs_measured(keyed(valid.join(truth.select("addr_key", "device"), "addr_key")).select("width", F.col("key").alias("a"), F.col("device").alias("b")), "width")
    of = lambda c: F.coalesce(c, F.lit(0).cast("bigint")).alias(c)
    return valid.sparkSession.range(1).select(every).join(sets, "width", "left").join(pairs, "width", "left").select("width", of("sets"), of("nonsingletons"), "precision", "recall")


_PAIRED = "(SELECT * FROM paired WHERE in1 AND in2 AND id1 IS NOT NULL AND id2 IS NOT NULL)"


def _unfiltered(x: Inputs) -> DataFrame:
    return x.merged.filter("id1 IS NOT NULL AND id2 IS NOT NULL")


_UNF = "id1, id2, boots1, boots2, r1, r2"


@query("alias_unfiltered", f"SELECT count(*) AS sets, count(*) FILTER (n > 1) AS nonsingletons, sum(n)::BIGINT AS addresses FROM (SELECT count(*) AS n FROM {_PAIRED} p GROUP BY id1, boots1, boots2, floor(r1 / 20), floor(r2 / 20)) x")
def alias_unfiltered(spark: SparkSession, sf_dir: str) -> DataFrame:
    sets = alias.resolve(_unfiltered(Inputs(spark, sf_dir)))
    return sets.agg(F.count("*").alias("sets"), F.count(F.when(F.col("n") > 1, 1)).alias("nonsingletons"), F.sum("n").alias("addresses"))


@query("alias_unfiltered_accuracy", _pairwise_sql("id1, boots1, boots2, floor(r1 / 20), floor(r2 / 20)", _PAIRED))
def alias_unfiltered_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    return _pairwise(x, AliasSpec(), _unfiltered(x))
