"""Statistics by network and region: address to network, coverage, vendors, dominance, uptime."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from devicelens.functions.codec import ip4_to_long, prefix_of
from devicelens.operators.distrib import cumulate


def lpm(addrs: DataFrame, prefixes: DataFrame, lengths4: tuple[int, ...] | None = None, lengths6: tuple[int, ...] = (48,)) -> DataFrame:
    """Longest-prefix match as one equi join a prefix length instead of a range join; the longest that matches wins. Lengths of IPv4 prefixes are the
    table's own if not said (33 at most, asked of the table); IPv6 prefixes are written out up to their length, and others than ``lengths6`` raise."""
    found = prefixes.select("family", "length").distinct().collect()  # no more rows than there are prefix lengths
    if odd := {r.length for r in found if r.family == 6} - set(lengths6):
        raise ValueError(f"IPv6 prefixes of lengths {sorted(odd)} are in the table, but {lengths6} are matched")
    lengths4 = lengths4 or tuple(sorted(r.length for r in found if r.family == 4))
    rows = addrs.withColumn("_ip", F.when(F.col("family") == 4, ip4_to_long(F.col("addr"))))
    found = []
    for length in lengths4:
        some = prefixes.filter((F.col("family") == 4) & (F.col("length") == length)).groupBy(F.col("base").cast("bigint").alias(f"_b{length}")).agg(F.min("asn").alias(f"_a{length}"))
        rows = rows.join(some, prefix_of(F.col("_ip"), length) == F.col(f"_b{length}"), "left")
        found.append(f"_a{length}")
    for length in lengths6:
        some = prefixes.filter((F.col("family") == 6) & (F.col("length") == length)).groupBy(F.col("base6").alias(f"_c{length}")).agg(F.min("asn").alias(f"_d{length}"))
        rows = rows.join(some, F.when(F.col("family") == 6, F.concat(F.substring_index("addr", "::", 1), F.lit("::"))) == F.col(f"_c{length}"), "left")
        found.append(f"_d{length}")
    return rows.select(*addrs.columns, F.coalesce(*(F.col(c) for c in reversed(found))).alias("asn")).filter("asn IS NOT NULL")


def set_asn(members: DataFrame, addr_as: DataFrame) -> DataFrame:
    """The network of most members, the lowest on ties."""
    votes = members.select("set_id", "addr").join(addr_as.select("addr", "asn"), "addr").groupBy("set_id", "asn").agg(F.count("*").alias("n"))
    return votes.groupBy("set_id").agg(F.max_by("asn", F.struct("n", (-F.col("asn")).alias("low"))).alias("asn"))


def as_vendor(routers: DataFrame) -> DataFrame:
    """Routers by (asn, region, vendor): the base of every network measure."""
    return routers.groupBy("asn", "region", "vendor").agg(F.count("*").alias("n"))


def per_as(base: DataFrame) -> DataFrame:
    return base.groupBy("asn", "region").agg(F.sum("n").alias("routers"), F.count("*").alias("vendors"), F.max("n").alias("top"))


def dominance(base: DataFrame) -> DataFrame:
    """asn, region, routers, top_vendor (lowest name on ties), dominance."""
    rank = F.row_number().over(W.partitionBy("asn").orderBy(F.desc("n"), "vendor"))
    total = F.sum("n").over(W.partitionBy("asn"))
    return base.withColumn("k", rank).withColumn("routers", total).filter("k = 1").select("asn", "region", "routers", F.col("vendor").alias("top_vendor"), F.round(F.col("n") / F.col("routers"), 6).alias("dominance"))


def by_threshold(df: DataFrame, value: str, size: str, thresholds: tuple[int, ...]) -> DataFrame:
    """Cumulative distribution of a value over networks with at least t rows, for every t; each row counts for the thresholds it meets."""
    marks = F.filter(F.array(*(F.lit(t) for t in thresholds)), lambda t: F.col(size) >= t)
    counts = df.select(F.explode(marks).alias("threshold"), F.col(value).alias("value")).groupBy("threshold", "value").agg(F.count("*").alias("n"))
    return cumulate(counts, ("threshold",))


def coverage(tags: DataFrame, responders: DataFrame, addr_as: DataFrame) -> DataFrame:
    """Router IPv4 addresses and how many respond, per network."""
    routers = tags.filter("family = 4").select("addr").distinct()
    there = responders.select("addr").distinct().withColumn("r", F.lit(1))
    rows = routers.join(addr_as.select("addr", "asn"), "addr").join(there, "addr", "left")
    return rows.groupBy("asn").agg(F.count("*").alias("routers"), F.count("r").alias("responding")).withColumn("coverage", F.round(F.col("responding") / F.col("routers"), 6))


def combined_coverage(tags: DataFrame, responders: DataFrame, reference: DataFrame) -> DataFrame:
    """Of all router IPv4 addresses: covered by responses, by non-singleton reference sets, by both, by either."""
    big = reference.groupBy("ref_set_id").agg(F.count("*").alias("n")).filter("n > 1").select("ref_set_id")
    ref = reference.join(big, "ref_set_id", "left_semi").select("addr").distinct().withColumn("ref", F.lit(1))
    ours = responders.select("addr").distinct().withColumn("ours", F.lit(1))
    rows = tags.filter("family = 4").select("addr").distinct().join(ours, "addr", "left").join(ref, "addr", "left")
    both, either = F.count(F.when(F.col("ours").isNotNull() & F.col("ref").isNotNull(), 1)), F.count(F.coalesce("ours", "ref"))
    share = lambda x, y: F.round(F.try_divide(x, y), 6)
    return rows.agg(
        F.count("*").alias("addresses"), F.count("ours").alias("ours"), F.count("ref").alias("reference"), both.alias("both"), either.alias("either"), share(F.count("ours"), F.count("*")).alias("ours_share"),
        share(F.count("ref"), F.count("*")).alias("reference_share"), share(either, F.count("*")).alias("combined_share"), share(both, F.count("ref")).alias("of_reference"), share(both, F.count("ours")).alias("of_ours"),
    )


def reboot_age(sets: DataFrame, at: int) -> DataFrame:
    """Days since the last reboot, as a cumulative distribution."""
    return cumulate(sets.groupBy(F.expr(f"({at} - reboot_max) div 86400").alias("value")).agg(F.count("*").alias("n")))


def coincident(sets: DataFrame, bin_s: int, k: int) -> DataFrame:
    """Groups of at least k devices of one network whose last reboot falls in one bin."""
    return sets.groupBy("asn", F.floor(F.col("reboot_min") / bin_s).alias("bin")).agg(F.countDistinct("engine_id").alias("devices")).filter(F.col("devices") >= k)


def reboot_timeline(sets: DataFrame, unit: str, by: str) -> DataFrame:
    day = F.date_trunc(unit, F.timestamp_seconds("reboot_max"))
    return sets.groupBy(F.date_format(day, "yyyy-MM-dd").alias("period"), by).agg(F.count("*").alias("reboots"))
