"""Reference partitions and baselines the methods are compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W


def names(ptr: DataFrame, rules: DataFrame, min_ppv: float = 0.8) -> DataFrame:
    """Sets by router name: the rule of a name's suffix extracts its router part; equal parts are one router. (addr, family, set_id)"""
    labels = F.split("name", "[.]")  # a name meets the rules by each of its own suffixes, so an equi join does
    ends = F.transform(F.sequence(F.lit(2), F.size(labels)), lambda k: F.array_join(F.slice(labels, k, F.size(labels)), "."))
    rows = ptr.filter(F.size(labels) > 1).withColumn("suffix", F.explode(ends))
    matched = rows.join(rules.filter(F.col("ppv") >= min_ppv), "suffix").withColumn("part", F.expr("regexp_extract(name, regex, 1)"))
    return matched.filter("part <> ''").select("addr", "family", F.concat_ws("/", "suffix", "part").alias("set_id"))


def rule_ppv(ptr: DataFrame, rules: DataFrame, truth: DataFrame) -> DataFrame:
    """Per rule: pairs it implies, those that are true, and their ratio."""
    sets = names(ptr, rules, 0.0).withColumn("suffix", F.substring_index("set_id", "/", 1)).join(ptr.select("addr", "addr_key"), "addr").join(truth.select("addr_key", "device"), "addr_key")
    pairs = lambda: F.sum((F.col("n") * (F.col("n") - 1) / 2).cast("bigint"))
    implied = sets.groupBy("suffix", "set_id").agg(F.count("*").alias("n")).groupBy("suffix").agg(pairs().alias("implied"))
    true = sets.groupBy("suffix", "set_id", "device").agg(F.count("*").alias("n")).groupBy("suffix").agg(pairs().alias("true_pairs"))
    return implied.join(true, "suffix").select("suffix", "implied", "true_pairs", F.round(F.try_divide("true_pairs", "implied"), 6).alias("ppv"))


def velocities(samples: DataFrame, modulus: int, min_samples: int) -> DataFrame:
    """Per address: samples, first and last, forward movement, and whether its own samples are one rising counter."""
    order = W.partitionBy("addr_key").orderBy("t", "ipid")
    step = F.pmod(F.col("ipid") - F.lag("ipid").over(order), F.lit(modulus))
    moved = samples.withColumn("step", step).groupBy("asn", "addr_key").agg(
        F.count("*").alias("samples"), F.min("t").alias("t0"), F.max("t").alias("t1"), F.coalesce(F.sum("step"), F.lit(0)).alias("moved"), F.coalesce(F.max("step"), F.lit(0)).alias("largest")
    )
    moved = moved.filter(F.col("samples") >= min_samples)
    return moved.withColumn("rising", F.col("largest") < modulus // 2).withColumn("velocity", F.expr("moved div greatest(t1 - t0, 1)"))


def similar_velocity(able: DataFrame, width: int) -> DataFrame:
    """a < b of one network whose velocities differ by at most ``width``: each address meets its own and the neighbouring buckets of that width."""
    side = lambda key: able.select("asn", F.col("addr_key").alias(key), F.expr(f"velocity div {width}").alias("bucket"), F.col("moved").alias(f"{key}_moved"), F.greatest(F.expr("t1 - t0"), F.lit(1)).alias(f"{key}_span"))
    around = side("b").withColumn("bucket", F.explode(F.sequence(F.col("bucket") - 1, F.col("bucket") + 1)))
    apart = F.abs(F.col("a_moved") * F.col("b_span") - F.col("b_moved") * F.col("a_span"))
    return side("a").join(around, ["asn", "bucket"]).filter("a < b").filter(apart <= F.lit(width) * F.col("a_span") * F.col("b_span")).select("a", "b")


def counter_pairs(samples: DataFrame, modulus: int = 65536, max_velocity: int = 60, min_samples: int = 3, width: int | None = None) -> DataFrame:
    """Pairs of addresses of one network whose merged samples form one counter: in order of time every step goes forward by less than half
    the modulus, and the whole movement fits the elapsed time. Candidates share network and similar velocity, at most ``width`` apart;
    without a width the whole part of their velocities is equal. All pairs are made, so a network of one velocity costs their square."""
    able = velocities(samples, modulus, min_samples).filter("rising")
    if width:
        pairs = similar_velocity(able, width)
    else:
        a, b = able.select("asn", "velocity", F.col("addr_key").alias("a")), able.select("asn", "velocity", F.col("addr_key").alias("b"))
        pairs = a.join(b, ["asn", "velocity"]).filter("a < b").select("a", "b")
    long = pairs.withColumn("addr_key", F.explode(F.array("a", "b"))).join(samples.select("addr_key", "t", "ipid"), "addr_key")
    order = W.partitionBy("a", "b").orderBy("t", "ipid", "addr_key")
    step = F.pmod(F.col("ipid") - F.lag("ipid").over(order), F.lit(modulus))
    merged = long.withColumn("step", step).groupBy("a", "b").agg(F.coalesce(F.max("step"), F.lit(0)).alias("largest"), F.coalesce(F.sum("step"), F.lit(0)).alias("moved"), (F.max("t") - F.min("t")).alias("elapsed"))
    return merged.filter((F.col("largest") < modulus // 2) & (F.col("moved") <= (F.col("elapsed") + 1) * max_velocity)).select("a", "b")


def active_compare(router_members: DataFrame, truth: DataFrame, vendors: DataFrame, outcomes: DataFrame) -> DataFrame:
    """One IPv4 member a router set, the first by a salted hash, tried by an active tool: none, mismatch or match with our vendor."""
    draw = F.conv(F.substring(F.md5(F.concat(F.col("addr_key").cast("string"), F.lit("|pick"))), 1, 8), 16, 10).cast("bigint")
    pick = router_members.filter("family = 4").groupBy("set_id").agg(F.min_by("addr_key", F.struct(draw.alias("d"), "addr_key")).alias("addr_key"))
    rows = pick.join(truth.select("addr_key", "device"), "addr_key").join(outcomes.select("device", "outcome", F.col("vendor").alias("tool_vendor")), "device").join(vendors.select("set_id", "vendor"), "set_id")
    kind = F.when(F.col("outcome") == "none", "none").when(F.col("tool_vendor") == F.col("vendor"), "match").otherwise("mismatch")
    return rows.groupBy(kind.alias("result")).agg(F.count("*").alias("routers")).withColumn("share", F.round(F.col("routers") / F.sum("routers").over(W.partitionBy()), 6))


def legacy_summary(legacy: DataFrame, responders: DataFrame) -> DataFrame:
    """Addresses of each legacy service, of ours, and in common."""
    ours = responders.select("addr").distinct()
    rows = legacy.join(ours.withColumn("r", F.lit(1)), "addr", "left")
    return rows.groupBy("service").agg(F.count("*").alias("addresses"), F.count("r").alias("also_ours")).withColumn("ours", ours.agg(F.count("*")).scalar())


def low_entropy(addresses: DataFrame, ids: DataFrame) -> DataFrame:
    """Distinct values of a 16-bit identifier among the addresses, what chance predicts, and distinct engine ids beside it."""
    draw = F.conv(F.substring(F.md5(F.concat(F.col("addr_key").cast("string"), F.lit("|id16"))), 1, 8), 16, 10).cast("bigint") % 65536
    seen = addresses.select("addr_key", draw.alias("x")).agg(F.count("*").alias("addresses"), F.countDistinct("x").alias("distinct_16bit"))
    expected = F.round(65536 * (1 - F.pow(F.lit(1 - 1 / 65536), F.col("addresses"))), 3)
    return seen.withColumn("expected_16bit", expected).withColumn("distinct_ids", ids.agg(F.countDistinct("engine_id")).scalar())
