"""Distributions: histograms, cumulative shares, heavy hitters, knees."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W


def ecdf(df: DataFrame, value: str, by: tuple[str, ...] = ()) -> DataFrame:
    """(by.., value, n, cum_n, frac): counted to a histogram first, so the ordered window sees distinct values only."""
    counts = df.filter(F.col(value).isNotNull()).groupBy(*by, F.col(value).alias("value")).agg(F.count("*").alias("n"))
    return cumulate(counts, by)


def cumulate(counts: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    order = W.partitionBy(*by).orderBy("value")
    cum = F.sum("n").over(order.rowsBetween(W.unboundedPreceding, 0))
    return counts.withColumn("cum_n", cum).withColumn("frac", F.round(F.col("cum_n") / F.sum("n").over(W.partitionBy(*by)), 6))


def occurrences(df: DataFrame, key: str, by: tuple[str, ...] = ()) -> DataFrame:
    """Cumulative distribution of how many rows each key has."""
    return ecdf(df.filter(F.col(key).isNotNull()).groupBy(*by, key).agg(F.count("*").alias("rows")), "rows", by)


def heavy_hitters(df: DataFrame, key: str, k: int, threshold: int = 0) -> DataFrame:
    return df.filter(F.col(key).isNotNull()).groupBy(key).agg(F.count("*").alias("n")).filter(F.col("n") > threshold).orderBy(F.desc("n"), key).limit(k)


def knee(curve: DataFrame) -> DataFrame:
    """The point of a cumulative curve farthest above its chord: largest frac - value / max, smallest value on ties."""
    top = F.max("value").over(W.partitionBy())
    scored = curve.withColumn("score", F.round(F.col("frac") - F.col("value") / F.greatest(top, F.lit(1)), 6))
    return scored.agg(F.max_by(F.struct("value", "frac", "score"), F.struct("score", (-F.col("value")).alias("v"))).alias("x")).select("x.*")


def format_share(df: DataFrame, column: Column, by: str = "family") -> DataFrame:
    """Share of each category among distinct ids."""
    counts = df.select(by, "engine_id", column.alias("format")).distinct().groupBy(by, "format").agg(F.count("*").alias("ids"))
    return counts.withColumn("share", F.round(F.col("ids") / F.sum("ids").over(W.partitionBy(by)), 6))
