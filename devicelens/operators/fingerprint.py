"""Vendors of devices from what their identifiers say."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from devicelens.functions.codec import decode


def vendor(df: DataFrame, oui: DataFrame, enterprise: DataFrame, column: str = "engine_id") -> DataFrame:
    """Adds vendor, confidence, mac_vendor, enterprise_vendor and format. Registries are small dimensions, joined by broadcast."""
    rows = df.withColumn("_id", decode(F.col(column)))
    macs = F.broadcast(oui.select(F.col("prefix").alias("_prefix"), F.col("vendor").alias("mac_vendor")))
    numbers = F.broadcast(enterprise.select(F.col("enterprise").alias("_number"), F.col("vendor").alias("enterprise_vendor")))
    rows = rows.join(macs, (F.col("_id.format") == "mac") & (F.substring("_id.data", 1, 6) == F.col("_prefix")), "left").join(numbers, F.col("_id.enterprise") == F.col("_number"), "left")
    level = F.when(F.col("mac_vendor").isNotNull(), "high").when(F.col("enterprise_vendor").isNotNull(), "medium").otherwise("none")
    rows = rows.withColumn("vendor", F.coalesce("mac_vendor", "enterprise_vendor", F.lit("unknown"))).withColumn("confidence", level)
    return rows.withColumn("format", F.col("_id.format")).drop("_id", "_prefix", "_number")


def set_vendor(sets: DataFrame, oui: DataFrame, enterprise: DataFrame) -> DataFrame:
    """On sets, not addresses: the members of a set share the identifier."""
    return vendor(sets, oui, enterprise)


def agreement(df: DataFrame) -> DataFrame:
    verdict = (
        F.when(F.col("mac_vendor").isNull() & F.col("enterprise_vendor").isNull(), "neither").when(F.col("mac_vendor").isNull(), "enterprise only").when(F.col("enterprise_vendor").isNull(), "mac only")
        .when(F.col("mac_vendor") == F.col("enterprise_vendor"), "agree").otherwise("disagree")
    )
    return df.groupBy(verdict.alias("verdict")).agg(F.count("*").alias("sets"))


def popularity(sets: DataFrame) -> DataFrame:
    """Devices per vendor by class."""
    of = lambda c: F.count(F.when(F.col("class") == c, 1)).alias(c)
    return sets.groupBy("vendor").agg(of("v4"), of("v6"), of("dual"), F.count("*").alias("devices"))


def topk_share(pop: DataFrame, k: int) -> DataFrame:
    """The k largest vendors with their share and the running share; a table of as many rows as there are vendors."""
    order = W.orderBy(F.desc("devices"), "vendor")
    total = F.sum("devices").over(W.partitionBy())
    running = F.sum("devices").over(order.rowsBetween(W.unboundedPreceding, 0))
    return pop.select("vendor", "devices", F.row_number().over(order).alias("place"), F.round(F.col("devices") / total, 6).alias("share"), F.round(running / total, 6).alias("running_share")).filter(F.col("place") <= k)


def mac_is_min(ids: DataFrame, interfaces: DataFrame) -> DataFrame:
    """Per device with a MAC in its id: whether that is the smallest of its interfaces' MACs."""
    least = interfaces.groupBy("device").agg(F.min("mac").alias("least"), F.count("*").alias("interfaces"))
    return ids.join(least, "device").select("device", "interfaces", (F.col("mac") == F.col("least")).alias("is_least"))


def nat_candidates(packets: DataFrame) -> DataFrame:
    """Addresses whose packets carry more than one id within a day."""
    days = packets.groupBy("addr", F.expr("recv_s div 86400").alias("day")).agg(F.countDistinct("engine_id").alias("ids"), F.count("*").alias("packets"))
    return days.filter("ids > 1")
