"""Replies as they come: clocks, repeated replies, amplification, target lists."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from devicelens.functions.codec import in_ranges
from devicelens.sources.fixture import special_ranges


def with_last_reboot(df: DataFrame) -> DataFrame:
    return df.withColumn("last_reboot_s", F.col("recv_s") - F.col("engine_time"))


def uptime(df: DataFrame) -> DataFrame:
    """Uptime at receipt as an interval, as days and hours, and as fractional days."""
    df = df.withColumn("uptime", F.make_dt_interval(secs=F.col("engine_time").cast("decimal(18,6)")))
    return df.withColumn("days", F.expr("engine_time div 86400")).withColumn("hours", F.expr("(engine_time % 86400) div 3600")).withColumn("uptime_days", F.col("engine_time") / 86400)


def multi_response(packets: DataFrame) -> DataFrame:
    """Requests that drew more than one packet."""
    per = packets.groupBy("req").agg(F.count("*").alias("packets"), F.sum("bytes").alias("bytes"), (F.max("recv_s") - F.min("recv_s")).alias("duration_s"))
    return per.filter("packets > 1").select("req", "packets", (F.col("packets") - 1).alias("extra"), "bytes", "duration_s")


def amplification(packets: DataFrame, request_bytes: int, k: int) -> DataFrame:
    """The k requests with most bytes back, and bytes back over bytes sent."""
    per = packets.groupBy("req").agg(F.count("*").alias("packets"), F.sum("bytes").alias("bytes"))
    return per.withColumn("factor", F.round(F.col("bytes") / float(request_bytes), 6)).orderBy(F.desc("bytes"), "req").limit(k)


def amplification_total(packets: DataFrame, request_bytes: int) -> DataFrame:
    per = packets.groupBy("req").agg(F.count("*").alias("packets"), F.sum("bytes").alias("bytes"))
    return per.agg(F.count("*").alias("requests"), F.sum("packets").alias("packets"), F.sum("bytes").alias("bytes"), F.round(F.sum("bytes") / (F.count("*") * float(request_bytes)), 6).alias("factor"))


def targets(addresses: DataFrame, aliased: DataFrame) -> DataFrame:
    """Routable IPv4 addresses, and IPv6 addresses outside aliased prefixes (column prefix, written out): one anti join a length of prefix."""
    left = addresses.filter((F.col("family") == 6) | ~in_ranges(F.col("v4"), special_ranges()))
    lengths = [r.n for r in aliased.select(F.length("prefix").alias("n")).distinct().collect()]  # no more than an address has characters
    for n in sorted(lengths):
        some = aliased.filter(F.length("prefix") == n).select("prefix").distinct()
        left = left.join(some, F.when(F.col("family") == 6, F.substring("addr", 1, n)) == F.col("prefix"), "left_anti")
    return left


def top_id_spread(replies: DataFrame, k: int) -> DataFrame:
    """Spread of the last reboot of the k most frequent ids of each family."""
    counts = replies.filter("engine_id IS NOT NULL").groupBy("family", "engine_id").agg(F.count("*").alias("n"))
    top = counts.withColumn("k", F.row_number().over(W.partitionBy("family").orderBy(F.desc("n"), "engine_id"))).filter(F.col("k") <= k)
    rows = with_last_reboot(replies).join(F.broadcast(top.select("family", "engine_id")), ["family", "engine_id"])  # at most k rows a family
    r = F.col("last_reboot_s")
    return rows.groupBy("family", "engine_id").agg(F.count("*").alias("addresses"), F.min(r).alias("first_s"), F.max(r).alias("last_s"), (F.max(r) - F.min(r)).alias("span_s"), F.percentile(r, F.lit(0.5)).alias("median_s"))
