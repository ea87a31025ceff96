"""Router address datasets and the sets they mark."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def router_sets(members: DataFrame, tags: DataFrame, mode: str = "any", sources: tuple[str, ...] | None = None) -> DataFrame:
    """set_id of the sets of which any (or all) members are in a chosen dataset; tags are collapsed to addresses before the join."""
    chosen = tags.filter(F.col("source").isin(*sources)) if sources else tags
    marked = members.select("set_id", "addr").join(chosen.select("addr").distinct().withColumn("tagged", F.lit(True)), "addr", "left")
    test = F.bool_or if mode == "any" else F.bool_and
    return marked.groupBy("set_id").agg(test(F.coalesce("tagged", F.lit(False))).alias("router")).filter("router").select("set_id")


def overview(tags: DataFrame, responders: DataFrame) -> DataFrame:
    """family, source (or union), addresses and how many respond."""
    by_addr = tags.join(responders.select("addr").distinct().withColumn("r", F.lit(1)), "addr", "left")
    per = by_addr.groupBy("family", "source").agg(F.count("*").alias("addresses"), F.count("r").alias("responding"))
    union = by_addr.groupBy("family", "addr").agg(F.max("r").alias("r")).groupBy("family").agg(F.count("*").alias("addresses"), F.count("r").alias("responding"))
    return per.union(union.select("family", F.lit("union").alias("source"), "addresses", "responding"))
