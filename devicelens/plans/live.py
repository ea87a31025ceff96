"""Queries over streams; the oracle sees the final state. Also variants that fold or compare more scans."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from devicelens.operators import alias
from devicelens.plans.inputs import Inputs
from devicelens.plans.methods import SETS
from devicelens.plans.registry import query
from devicelens.streaming import live


@query("st_watermark_tumbling", "SELECT (epoch_us(ts) // 3600000000) * 3600 AS start_s, count(*) AS replies FROM events GROUP BY 1")
def st_watermark_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return live.final_state(live.tumbling(live.events(spark, sf_dir)), "complete")


@query("st_sliding", "SELECT (epoch_us(ts) // 3600000000 - k) * 3600 AS start_s, count(*) AS replies FROM events CROSS JOIN range(6) r(k) GROUP BY 1")
def st_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return live.final_state(live.tumbling(live.events(spark, sf_dir), "6 hours", "1 hour"), "complete")


@query("st_session", """SELECT user_id, min(t) AS start_us, count(*) AS replies FROM (SELECT user_id, t, sum(new) OVER (PARTITION BY user_id ORDER BY t) AS s FROM (SELECT user_id, epoch_us(ts) AS t,
    coalesce(epoch_us(ts) - lag(epoch_us(ts)) OVER (PARTITION BY user_id ORDER BY ts) > 1800000000, false)::INT AS new FROM events) a) b GROUP BY user_id, s""")
def st_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    return live.final_state(live.sessions(live.events(spark, sf_dir)), "complete")


@query("st_dedup", "SELECT DISTINCT user_id, strftime(ts, '%Y-%m-%d') AS day FROM events")
def st_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return live.final_state(live.first_of_day(live.events(spark, sf_dir)), "append")


@query("st_alias_counts", "SELECT user_id, count(*) AS replies FROM events GROUP BY user_id")
def st_alias_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return live.final_state(live.counts(live.events(spark, sf_dir)), "complete")


@query("st_stream_static_vendor", "SELECT c_mktsegment, count(*) AS replies FROM events JOIN customer ON c_custkey = user_id GROUP BY 1")
def st_stream_static_vendor(spark: SparkSession, sf_dir: str) -> DataFrame:
    return live.final_state(live.by_segment(live.events(spark, sf_dir), Inputs(spark, sf_dir).customer), "complete")


@query("st_foreach_batch_upsert", "SELECT user_id, count(*) AS replies FROM events GROUP BY user_id")
def st_foreach_batch_upsert(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = live.shared_folder(spark, "upsert")
    live.upsert_counts(live.events(spark, sf_dir), folder)
    return spark.read.parquet(folder).groupBy("user_id").agg(F.sum("replies").alias("replies"))


@query("incremental_alias", "SELECT * FROM sets")
def incremental_alias(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sets of half the addresses, then the other half folded in: keys are functions of rows, so partial sets merge by key."""
    rows = alias.keyed(Inputs(spark, sf_dir).valid)
    n4, n6 = F.count(F.when(F.col("family") == 4, 1)), F.count(F.when(F.col("family") == 6, 1))

    def part(half: int) -> DataFrame:
        some = rows.filter(F.pmod("addr_key", F.lit(2)) == half).groupBy("key")
        return some.agg(F.min("addr_key").alias("set_id"), F.min("id1").alias("engine_id"), F.count("*").alias("n"), n4.alias("n4"), n6.alias("n6"), F.min("boots1").alias("boots"), F.min("r1").alias("reboot_min"), F.max("r1").alias("reboot_max"))

    both = part(0).union(part(1)).groupBy("key").agg(
        F.min("set_id").alias("set_id"), F.min("engine_id").alias("engine_id"), *(F.sum(c).alias(c) for c in ("n", "n4", "n6")), F.min("boots").alias("boots"), F.min("reboot_min").alias("reboot_min"), F.max("reboot_max").alias("reboot_max")
    )
    return alias.classify(both).select(*SETS)


@query("n_scan_consistency", """SELECT family, addr FROM responses WHERE engine_id <> '' AND boots > 0 AND engine_time > 0 GROUP BY family, addr
    HAVING count(DISTINCT scan) = 2 AND count(DISTINCT engine_id) = 1 AND count(DISTINCT boots) = 1 AND max(recv_s - engine_time) - min(recv_s - engine_time) <= 10""")
def n_scan_consistency(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Any number of scans: the same id and boots in all of them, last reboots within 10 s."""
    return consistent(Inputs(spark, sf_dir).responses)


def consistent(responses: DataFrame) -> DataFrame:
    """family and addr of those that gave valid replies in every scan of the table, all alike; replies of one scan may repeat."""
    rows = responses.filter("engine_id <> '' AND boots > 0 AND engine_time > 0").withColumn("r", F.col("recv_s") - F.col("engine_time"))
    per = rows.groupBy("family", "addr").agg(F.countDistinct("scan").alias("scans"), F.min("engine_id").alias("a"), F.max("engine_id").alias("b"), F.min("boots").alias("c"), F.max("boots").alias("d"), (F.max("r") - F.min("r")).alias("gap"))
    every = responses.agg(F.countDistinct("scan")).scalar()
    return per.filter((F.col("scans") == every) & F.expr("a = b AND c = d AND gap <= 10")).select("family", "addr")
