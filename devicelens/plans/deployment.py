"""Queries of coverage, vendors, networks and regions, of the baselines, and of the cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from devicelens.operators import alias, baselines, distrib, fingerprint, netstats
from devicelens.plans.inputs import Inputs
from devicelens.plans.methods import _ecdf, _stats_sql
from devicelens.plans.registry import query

AT = 1705622400  # the end of the second scan


@query("ip_to_as", "SELECT addr, family, addr_key, asn FROM addr_as")
def ip_to_as(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).addr_as


@query("set_asn", "SELECT set_id, asn FROM set_as")
def set_asn(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).set_as


@query("coverage_per_as", "SELECT asn, routers, responding, round(responding / routers, 6) AS coverage FROM coverage")
def coverage_per_as(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).coverage


def _by_threshold(source: str, value: str, size: str, thresholds: tuple[int, ...]) -> str:
    marks = ", ".join(f"({t})" for t in thresholds)
    return _ecdf(f"(SELECT v.t::INTEGER AS threshold, {value} AS val FROM {source} x JOIN (VALUES {marks}) v(t) ON x.{size} >= v.t) y", "val", "threshold")


@query("coverage_ecdf", _by_threshold("(SELECT *, round(responding / routers, 6) AS coverage FROM coverage)", "coverage", "routers", (2, 5, 10, 50, 100)))
def coverage_ecdf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return netstats.by_threshold(Inputs(spark, sf_dir).coverage, "coverage", "routers", (2, 5, 10, 50, 100))


@query("coverage_as_counts", "SELECT t::INTEGER AS threshold, count(*) FILTER (routers >= t) AS networks FROM coverage CROSS JOIN (VALUES (2), (5), (10), (50), (100)) v(t) GROUP BY t")
def coverage_as_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    counts = Inputs(spark, sf_dir).coverage.agg(*(F.count(F.when(F.col("routers") >= t, 1)).alias(f"t{t}") for t in (2, 5, 10, 50, 100)))
    return counts.select(F.explode(F.array(*(F.struct(F.lit(t).alias("threshold"), F.col(f"t{t}").alias("networks")) for t in (2, 5, 10, 50, 100)))).alias("x")).select("x.*")


@query("coverage_combined", """SELECT count(*) AS addresses, count(*) FILTER (o) AS ours, count(*) FILTER (r) AS reference, count(*) FILTER (o AND r) AS both, count(*) FILTER (o OR r) AS either, round(count(*) FILTER (o) / count(*), 6) AS ours_share,
    round(count(*) FILTER (r) / count(*), 6) AS reference_share, round(count(*) FILTER (o OR r) / count(*), 6) AS combined_share, round(count(*) FILTER (o AND r) / nullif(count(*) FILTER (r), 0), 6) AS of_reference,
    round(count(*) FILTER (o AND r) / nullif(count(*) FILTER (o), 0), 6) AS of_ours FROM (SELECT addr, addr IN (SELECT addr FROM responses) AS o,
    addr IN (SELECT addr FROM counter_sets_v4 WHERE ref_set_id IN (SELECT ref_set_id FROM counter_sets_v4 GROUP BY 1 HAVING count(*) > 1)) AS r FROM (SELECT DISTINCT addr FROM router_tags WHERE family = 4) z) q""")
def coverage_combined(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    return netstats.combined_coverage(x.router_tags, x.responses, x.counter_sets_v4)


# --- vendors


@query("vendor_infer", "SELECT set_id, format, vendor, confidence FROM vendors")
def vendor_infer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return Inputs(spark, sf_dir).vendors.select("set_id", "format", "vendor", "confidence")


@query("vendor_agreement", """SELECT CASE WHEN mac_vendor IS NULL AND enterprise_vendor IS NULL THEN 'neither' WHEN mac_vendor IS NULL THEN 'enterprise only' WHEN enterprise_vendor IS NULL THEN 'mac only'
    WHEN mac_vendor = enterprise_vendor THEN 'agree' ELSE 'disagree' END AS verdict, count(*) AS sets FROM vendors GROUP BY 1""")
def vendor_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.agreement(Inputs(spark, sf_dir).vendors)


@query("vendor_per_set", "SELECT set_id, vendor, n, 1 AS ids FROM vendors")
def vendor_per_set(spark: SparkSession, sf_dir: str) -> DataFrame:
    ids = F.when(F.col("engine_id") == F.col("other_id"), 1).otherwise(2)
    return Inputs(spark, sf_dir).vendors.select("set_id", "vendor", "n", ids.alias("ids"))


_POP = "SELECT vendor, count(*) FILTER (class = 'v4') AS v4, count(*) FILTER (class = 'v6') AS v6, count(*) FILTER (class = 'dual') AS dual, count(*) AS devices FROM {} GROUP BY vendor"


@query("vendor_popularity", _POP.format("vendors"))
def vendor_popularity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.popularity(Inputs(spark, sf_dir).vendors)


@query("router_vendor_popularity", _POP.format("routers"))
def router_vendor_popularity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.popularity(Inputs(spark, sf_dir).routers)


def _top(source: str, k: int) -> str:
    return f"""SELECT vendor, devices, place::INTEGER AS place, round(devices / total, 6) AS share, round(running / total, 6) AS running_share FROM (SELECT vendor, devices, row_number() OVER w AS place, sum(devices) OVER () AS total,
        sum(devices) OVER (ORDER BY devices DESC, vendor ROWS UNBOUNDED PRECEDING) AS running FROM (SELECT vendor, count(*) AS devices FROM {source} GROUP BY vendor) p WINDOW w AS (ORDER BY devices DESC, vendor)) z WHERE place <= {k}"""


@query("vendor_topk_share", _top("vendors", 10))
def vendor_topk_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.topk_share(fingerprint.popularity(Inputs(spark, sf_dir).vendors), 10)


@query("router_vendor_topk_share", _top("routers", 4))
def router_vendor_topk_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.topk_share(fingerprint.popularity(Inputs(spark, sf_dir).routers), 4)


@query("mac_position_check", """SELECT d.device, l.interfaces, d.mac = l.least AS is_least FROM (SELECT device, substr(engine_id, 11, 12) AS mac FROM device WHERE length(engine_id) = 22 AND substr(engine_id, 9, 2) = '03') d
    JOIN (SELECT device, min(mac) AS least, count(*) AS interfaces FROM interfaces GROUP BY device) l USING (device)""")
def mac_position_check(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    ids = x.device.filter("length(engine_id) = 22 AND substr(engine_id, 9, 2) = '03'").select("device", F.substring("engine_id", 11, 12).alias("mac"))
    return fingerprint.mac_is_min(ids, x.interfaces)


@query("nat_candidates", "SELECT addr, recv_s // 86400 AS day, count(DISTINCT engine_id) AS ids, count(*) AS packets FROM event_replies GROUP BY 1, 2 HAVING count(DISTINCT engine_id) > 1")
def nat_candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.nat_candidates(Inputs(spark, sf_dir).event_replies)


@query("ephemeral_addresses", """SELECT family, count(*) AS addresses, count(*) FILTER (NOT (in1 AND in2)) AS one_scan_only, count(*) FILTER (in1 AND in2 AND id1 <> id2) AS changed_id,
    round((count(*) FILTER (NOT (in1 AND in2)) + count(*) FILTER (in1 AND in2 AND id1 <> id2)) / count(*), 6) AS ephemeral_share FROM paired GROUP BY family""")
def ephemeral_addresses(spark: SparkSession, sf_dir: str) -> DataFrame:
    seen = Inputs(spark, sf_dir).responses.groupBy("family", "addr").agg(F.count("*").alias("scans"), (F.min("engine_id") != F.max("engine_id")).alias("changed"))
    once, changed = F.count(F.when(F.col("scans") == 1, 1)), F.count(F.when((F.col("scans") > 1) & F.col("changed"), 1))
    return seen.groupBy("family").agg(F.count("*").alias("addresses"), once.alias("one_scan_only"), changed.alias("changed_id"), F.round((once + changed) / F.count("*"), 6).alias("ephemeral_share"))


# --- networks and regions


@query("time_since_reboot", _ecdf(f"(SELECT ({AT} - reboot_max) // 86400 AS days FROM routers) x", "days"))
def time_since_reboot(spark: SparkSession, sf_dir: str) -> DataFrame:
    return netstats.reboot_age(Inputs(spark, sf_dir).routers, AT)


@query("time_since_reboot_shares", f"""SELECT count(*) AS routers, round(avg(({AT} - reboot_max > 365 * 86400)::INT), 6) AS over_a_year, round(avg((reboot_max >= 1704067200)::INT), 6) AS since_new_year,
    round(avg(({AT} - reboot_max <= 30 * 86400)::INT), 6) AS last_30_days FROM routers""")
def time_since_reboot_shares(spark: SparkSession, sf_dir: str) -> DataFrame:
    share = lambda test: F.round(F.avg(test.cast("int")), 6)
    age = AT - F.col("reboot_max")
    new_year = F.unix_seconds(F.date_trunc("year", F.timestamp_seconds(F.lit(AT))))
    return Inputs(spark, sf_dir).routers.agg(F.count("*").alias("routers"), share(age > 365 * 86400).alias("over_a_year"), share(F.col("reboot_max") >= new_year).alias("since_new_year"), share(age <= 30 * 86400).alias("last_30_days"))


@query("routers_per_as", "SELECT asn, region, sum(n)::BIGINT AS routers FROM as_vendor GROUP BY ALL")
def routers_per_as(spark: SparkSession, sf_dir: str) -> DataFrame:
    return netstats.per_as(Inputs(spark, sf_dir).as_vendor).select("asn", "region", "routers")


@query("routers_per_as_counts", "SELECT count(*) AS networks, count(*) FILTER (routers >= 5) AS from_5, count(*) FILTER (routers > 20) AS over_20, count(*) FILTER (routers > 100) AS over_100, count(*) FILTER (routers > 1000) AS over_1000 FROM as_total")
def routers_per_as_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    over = lambda test, name: F.count(F.when(test, 1)).alias(name)
    r = F.col("routers")
    return netstats.per_as(Inputs(spark, sf_dir).as_vendor).agg(F.count("*").alias("networks"), over(r >= 5, "from_5"), over(r > 20, "over_20"), over(r > 100, "over_100"), over(r > 1000, "over_1000"))


@query("routers_per_as_region", _ecdf("as_total", "routers", "region"))
def routers_per_as_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    return distrib.ecdf(netstats.per_as(Inputs(spark, sf_dir).as_vendor), "routers", ("region",))


@query("vendors_per_as", _by_threshold("as_total", "vendors", "routers", (5, 10, 50)))
def vendors_per_as(spark: SparkSession, sf_dir: str) -> DataFrame:
    return netstats.by_threshold(netstats.per_as(Inputs(spark, sf_dir).as_vendor), "vendors", "routers", (5, 10, 50))


@query("vendors_per_as_shares", "SELECT count(*) AS networks, round(avg((vendors = 1)::INT), 6) AS single_vendor, round(avg((vendors > 5)::INT), 6) AS over_five FROM as_total WHERE routers >= 5")
def vendors_per_as_shares(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = netstats.per_as(Inputs(spark, sf_dir).as_vendor).filter("routers >= 5")
    return rows.agg(F.count("*").alias("networks"), F.round(F.avg((F.col("vendors") == 1).cast("int")), 6).alias("single_vendor"), F.round(F.avg((F.col("vendors") > 5).cast("int")), 6).alias("over_five"))


@query("vendor_share_region", """SELECT region, vendor, n, round(100 * n / sum(n) OVER (PARTITION BY region), 4) AS percent FROM (SELECT region, vendor, sum(n)::BIGINT AS n FROM as_vendor GROUP BY ALL
    UNION ALL SELECT 'all', vendor, sum(n)::BIGINT FROM as_vendor GROUP BY ALL) x""")
def vendor_share_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql.window import Window as W

    base = Inputs(spark, sf_dir).as_vendor
    counts = base.withColumn("region", F.explode(F.array("region", F.lit("all")))).groupBy("region", "vendor").agg(F.sum("n").alias("n"))
    return counts.withColumn("percent", F.round(100 * F.col("n") / F.sum("n").over(W.partitionBy("region")), 4))


@query("top_as_vendor_mix", """SELECT asn, routers, vendor, n, place::INTEGER AS place, round(n / routers, 6) AS share FROM (SELECT v.asn, t.routers, v.vendor, v.n, row_number() OVER (PARTITION BY v.asn ORDER BY v.n DESC, v.vendor) AS place
    FROM as_vendor v JOIN (SELECT asn, routers FROM as_total ORDER BY routers DESC, asn LIMIT 10) t USING (asn)) x""")
def top_as_vendor_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from pyspark.sql.window import Window as W

    base = Inputs(spark, sf_dir).as_vendor
    top = netstats.per_as(base).select("asn", "routers").orderBy(F.desc("routers"), "asn").limit(10)
    place = F.row_number().over(W.partitionBy("asn").orderBy(F.desc("n"), "vendor"))
    return base.join(F.broadcast(top), "asn").select("asn", "routers", "vendor", "n", place.alias("place"), F.round(F.col("n") / F.col("routers"), 6).alias("share"))


_DOM = "(SELECT asn, region, routers, (SELECT vendor FROM as_vendor v WHERE v.asn = t.asn ORDER BY n DESC, vendor LIMIT 1) AS top_vendor, round(top / routers, 6) AS dominance FROM as_total t)"


@query("vendor_dominance", f"SELECT * FROM {_DOM} d")
def vendor_dominance(spark: SparkSession, sf_dir: str) -> DataFrame:
    return netstats.dominance(Inputs(spark, sf_dir).as_vendor)


@query("dominance_ecdf", _by_threshold("(SELECT routers, round(top / routers, 6) AS dominance FROM as_total)", "dominance", "routers", (1, 5, 20, 100)))
def dominance_ecdf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return netstats.by_threshold(netstats.dominance(Inputs(spark, sf_dir).as_vendor), "dominance", "routers", (1, 5, 20, 100))


@query("dominance_share", "SELECT count(*) AS networks, round(avg((top / routers >= 0.7)::INT), 6) AS dominated FROM as_total WHERE routers >= 5")
def dominance_share(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = netstats.dominance(Inputs(spark, sf_dir).as_vendor).filter("routers >= 5")
    return rows.agg(F.count("*").alias("networks"), F.round(F.avg((F.col("dominance") >= 0.7).cast("int")), 6).alias("dominated"))


@query("dominance_region", """SELECT region, count(*) AS networks, round(quantile_cont(d, 0.25), 5) AS q1, round(quantile_cont(d, 0.5), 5) AS median, round(quantile_cont(d, 0.75), 5) AS q3, round(avg(d), 5) AS mean
    FROM (SELECT region, (top / routers)::DOUBLE AS d FROM as_total WHERE routers >= 10) x GROUP BY region""")
def dominance_region(spark: SparkSession, sf_dir: str) -> DataFrame:
    at = lambda p: F.round(F.percentile("dominance", F.lit(p)), 5)
    rows = netstats.per_as(Inputs(spark, sf_dir).as_vendor).filter("routers >= 10").withColumn("dominance", F.col("top") / F.col("routers"))
    return rows.groupBy("region").agg(F.count("*").alias("networks"), at(0.25).alias("q1"), at(0.5).alias("median"), at(0.75).alias("q3"), F.round(F.avg("dominance"), 5).alias("mean"))


@query("reboot_timeline", "SELECT strftime(date_trunc('month', make_timestamp(reboot_max * 1000000)), '%Y-%m-%d') AS period, region, count(*) AS reboots FROM routers GROUP BY ALL")
def reboot_timeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    return netstats.reboot_timeline(Inputs(spark, sf_dir).routers, "month", "region")


@query("coincident_reboots", "SELECT asn, reboot_min // 3600 AS bin, count(DISTINCT engine_id) AS devices FROM routers GROUP BY 1, 2 HAVING count(DISTINCT engine_id) >= 2")
def coincident_reboots(spark: SparkSession, sf_dir: str) -> DataFrame:
    return netstats.coincident(Inputs(spark, sf_dir).routers, 3600, 2)


# --- baselines


@query("rdns_names", "SELECT addr, family, set_id FROM names")
def rdns_names(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    return baselines.names(x.ptr, x.name_rules)


@query("rdns_rule_ppv", """SELECT suffix, implied, true_pairs, round(true_pairs / nullif(implied, 0), 6) AS ppv FROM (SELECT suffix, sum(n * (n - 1) // 2)::BIGINT AS implied FROM (SELECT suffix, part, count(*) AS n FROM
    (SELECT r.suffix, regexp_extract(p.name, r.regex, 1) AS part FROM ptr p JOIN name_rules r ON ends_with(p.name, '.' || r.suffix)) a WHERE part <> '' GROUP BY ALL) b GROUP BY suffix) i
    JOIN (SELECT suffix, sum(n * (n - 1) // 2)::BIGINT AS true_pairs FROM (SELECT suffix, part, device, count(*) AS n FROM (SELECT r.suffix, regexp_extract(p.name, r.regex, 1) AS part, t.device FROM ptr p
    JOIN name_rules r ON ends_with(p.name, '.' || r.suffix) JOIN truth t USING (addr_key)) c WHERE part <> '' GROUP BY ALL) d GROUP BY suffix) j USING (suffix)""")
def rdns_rule_ppv(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    return baselines.rule_ppv(x.ptr, x.name_rules, x.truth)


@query("names_pages_hosts", "SELECT stem, count(*) AS pages, count(DISTINCT host) AS hosts FROM (SELECT regexp_extract(url, '^[a-z]+://([^/:]+)', 1) AS host, regexp_extract(url, '^[a-z]+://([a-z]+)', 1) AS stem FROM pages) x WHERE stem <> '' GROUP BY stem")
def names_pages_hosts(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = Inputs(spark, sf_dir).pages.select(F.regexp_extract("url", "^[a-z]+://([^/:]+)", 1).alias("host"), F.regexp_extract("url", "^[a-z]+://([a-z]+)", 1).alias("stem"))
    return rows.filter("stem <> ''").groupBy("stem").agg(F.count("*").alias("pages"), F.countDistinct("host").alias("hosts"))


def _near_counter_sql(samples: str, modulus: int, max_velocity: int, width: int) -> str:
    h = modulus // 2
    step = f"((ipid - lag(ipid) OVER ({{}}) + {modulus}) % {modulus})"
    able = f"""(SELECT asn, addr_key, coalesce(sum(step), 0) AS moved, greatest(max(t) - min(t), 1) AS span FROM (SELECT *, {step.format('PARTITION BY addr_key ORDER BY t, ipid')} AS step FROM {samples}) s
        GROUP BY asn, addr_key HAVING count(*) >= 3 AND coalesce(max(step), 0) < {h})"""
    return f"""SELECT a, b FROM (SELECT a, b, t, {step.format('PARTITION BY a, b ORDER BY t, ipid, addr_key')} AS step FROM (SELECT p.a, p.b, s.addr_key, s.t, s.ipid FROM (SELECT x.addr_key AS a, y.addr_key AS b FROM {able} x
        JOIN {able} y ON x.asn = y.asn AND abs(x.moved * y.span - y.moved * x.span) <= {width} * x.span * y.span AND x.addr_key < y.addr_key) p JOIN {samples} s ON s.addr_key = p.a OR s.addr_key = p.b) u) v
        GROUP BY a, b HAVING coalesce(max(step), 0) < {h} AND coalesce(sum(step), 0) <= (max(t) - min(t) + 1) * {max_velocity}"""


@query("ipid_monotonic_v4", _near_counter_sql("(SELECT * FROM ipid_samples WHERE addr_key IN (SELECT a FROM address WHERE family = 4))", 65536, 60, 1))
def ipid_monotonic_v4(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The shared-counter test of IPv4 addresses, velocities at most 1 a unit of time apart."""
    x = Inputs(spark, sf_dir)
    four = x.address.filter("family = 4").select(F.col("a").alias("addr_key"))
    return baselines.counter_pairs(x.ipid_samples.join(four, "addr_key", "left_semi"), width=1)


@query("fragid_monotonic_v6", _near_counter_sql("fragid_samples", 1 << 32, 1_000_000, 1_000))
def fragid_monotonic_v6(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The shared-counter test of IPv6 addresses over 32-bit fragment identifiers, velocities at most 1,000 a unit of time apart."""
    return baselines.counter_pairs(Inputs(spark, sf_dir).fragid_samples, 1 << 32, 1_000_000, width=1_000)


@query("reference_sets", "SELECT 'v4' AS kind, ref_set_id, count(*) AS n FROM counter_sets_v4 GROUP BY ALL UNION ALL SELECT 'v6', ref_set_id, count(*) FROM fragid_sets_v6 GROUP BY ALL")
def reference_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    both = x.counter_sets_v4.withColumn("kind", F.lit("v4")).union(x.fragid_sets_v6.withColumn("kind", F.lit("v6")))
    return both.groupBy("kind", "ref_set_id").agg(F.count("*").alias("n"))


@query("active_probe_compare", """SELECT result, count(*) AS routers, round(count(*) / sum(count(*)) OVER (), 6) AS share FROM (SELECT CASE WHEN o.outcome = 'none' THEN 'none' WHEN o.vendor = v.vendor THEN 'match' ELSE 'mismatch' END AS result
    FROM (SELECT set_id, addr_key, row_number() OVER (PARTITION BY set_id ORDER BY ('0x' || substr(md5(concat(addr_key, '|pick')), 1, 8))::BIGINT, addr_key) AS k FROM members WHERE family = 4 AND set_id IN (SELECT set_id FROM router_two)) m
    JOIN truth t USING (addr_key) JOIN active_outcome o USING (device) JOIN vendors v USING (set_id) WHERE k = 1) x GROUP BY result""")
def active_probe_compare(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    return baselines.active_compare(x.members.join(x.router_two, "set_id", "left_semi"), x.truth, x.vendors, x.active_outcome)


@query("legacy_scan_compare", "SELECT service, count(*) AS addresses, count(*) FILTER (addr IN (SELECT addr FROM responses)) AS also_ours, (SELECT count(DISTINCT addr) FROM responses) AS ours FROM legacy_responders GROUP BY service")
def legacy_scan_compare(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    return baselines.legacy_summary(x.legacy_responders, x.responses)


@query("low_entropy_id", """SELECT addresses, distinct_16bit, round(65536 * (1 - pow(1 - 1 / 65536, addresses)), 3) AS expected_16bit, (SELECT count(DISTINCT engine_id) FROM responses) AS distinct_ids
    FROM (SELECT count(*) AS addresses, count(DISTINCT ('0x' || substr(md5(concat(addr_key, '|id16')), 1, 8))::BIGINT % 65536) AS distinct_16bit FROM truth) x""")
def low_entropy_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    return baselines.low_entropy(x.truth, x.responses)


# --- cost and accuracy measures


@query("probe_cost", """SELECT p.family, p.targets, p.targets * CASE WHEN p.family = 4 THEN 88 ELSE 108 END AS bytes_out, r.replies, r.replies * CASE WHEN p.family = 4 THEN 130 ELSE 150 END AS bytes_in,
    round(p.targets / CASE WHEN p.family = 4 THEN 5000.0 ELSE 20000.0 END, 6)::DOUBLE AS seconds, 1 AS packets_per_target, 16 AS active_tool_packets FROM (SELECT family, count(*) AS targets FROM address GROUP BY 1) p JOIN (SELECT family, count(*) AS replies FROM responses WHERE scan = 1 GROUP BY 1) r USING (family)""")
def probe_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    targets = x.address.groupBy("family").agg(F.count("*").alias("targets"))
    replies = x.responses.filter("scan = 1").groupBy("family").agg(F.count("*").alias("replies"))
    by = lambda four, six: F.when(F.col("family") == 4, four).otherwise(six)
    return targets.join(replies, "family").select(
        "family", "targets", (F.col("targets") * by(88, 108)).alias("bytes_out"), "replies", (F.col("replies") * by(130, 150)).alias("bytes_in"), F.round(F.col("targets") / by(5000.0, 20000.0), 6).alias("seconds"),
        F.lit(1).alias("packets_per_target"), F.lit(16).alias("active_tool_packets"),
    )


@query("responsive_ratio", """SELECT family, count(*) AS targets, count(*) FILTER (addr IN (SELECT addr FROM responses WHERE scan = 1)) AS responders, round(count(*) FILTER (addr IN (SELECT addr FROM responses WHERE scan = 1)) / count(*), 6) AS ratio FROM address GROUP BY family""")
def responsive_ratio(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    rows = x.address.join(x.responses.filter("scan = 1").select("addr").distinct().withColumn("r", F.lit(1)), "addr", "left")
    return rows.groupBy("family").agg(F.count("*").alias("targets"), F.count("r").alias("responders"), F.round(F.count("r") / F.count("*"), 6).alias("ratio"))


@query("router_share_of_valid", "SELECT family, count(*) AS valid, count(*) FILTER (addr IN (SELECT addr FROM router_tags)) AS routers, round(count(*) FILTER (addr IN (SELECT addr FROM router_tags)) / count(*), 6) AS share FROM valid GROUP BY family")
def router_share_of_valid(spark: SparkSession, sf_dir: str) -> DataFrame:
    x = Inputs(spark, sf_dir)
    rows = x.valid.join(x.router_tags.select("addr").distinct().withColumn("r", F.lit(1)), "addr", "left")
    return rows.groupBy("family").agg(F.count("*").alias("valid"), F.count("r").alias("routers"), F.round(F.count("r") / F.count("*"), 6).alias("share"))


@query("nonsingleton_cover", "SELECT sets, nonsingletons, addresses_in_them, share_covered FROM (" + _stats_sql("sets") + ") z")
def nonsingleton_cover(spark: SparkSession, sf_dir: str) -> DataFrame:
    return alias.stats(Inputs(spark, sf_dir).sets, None).drop("mean_size")


@query("mean_set_size", "SELECT class, mean_size FROM (" + _stats_sql("sets", "class") + ") z")
def mean_set_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    return alias.stats(Inputs(spark, sf_dir).sets).select("class", "mean_size")
