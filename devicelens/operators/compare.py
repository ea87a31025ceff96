"""Comparing partitions of addresses by their contingency; pairs are counted, never made."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W


def contingency(p: DataFrame, q: DataFrame) -> DataFrame:
    """(a, b, n_shared, n_a, n_b) of two partitions given as (set_id, addr). One pass over the addresses of both: those are co-grouped by a
    full join, and the sizes of sets are windows over the counted cells, which a set's cells share a task in."""
    left, right = p.select(F.col("set_id").alias("a"), "addr"), q.select(F.col("set_id").alias("b"), "addr")
    cells = left.join(right, "addr", "full").groupBy("a", "b").agg(F.count("*").alias("n_shared"))
    sized = cells.withColumn("n_a", F.sum("n_shared").over(W.partitionBy("a"))).withColumn("n_b", F.sum("n_shared").over(W.partitionBy("b")))
    return sized.filter("a IS NOT NULL AND b IS NOT NULL")


def exact(table: DataFrame) -> DataFrame:
    """Sets with the same members in both, by singletons and others."""
    same = table.filter("n_shared = n_a AND n_a = n_b")
    return same.agg(F.count("*").alias("exact"), F.count(F.when(F.col("n_a") == 1, 1)).alias("exact_singletons"), F.count(F.when(F.col("n_a") > 1, 1)).alias("exact_others"))


def partial(table: DataFrame) -> DataFrame:
    """Sets of each partition that share an address with the other."""
    return table.agg(F.countDistinct("a").alias("ours_touched"), F.countDistinct("b").alias("reference_touched"), F.sum("n_shared").alias("shared_addresses"))


def summary(partitions: dict[str, DataFrame]) -> DataFrame:
    """Sets, non-singletons, addresses and mean size of several partitions."""
    found = None
    for name, p in partitions.items():
        sizes = p.groupBy("set_id").agg(F.count("*").alias("n"))
        more = F.col("n") > 1
        row = sizes.agg(F.count("*").alias("sets"), F.count(F.when(more, 1)).alias("nonsingletons"), F.coalesce(F.sum(F.when(more, F.col("n"))), F.lit(0)).alias("addresses_in_them"), F.round(F.avg(F.when(more, F.col("n"))), 6).alias("mean_size"))
        row = row.select(F.lit(name).alias("partition"), "*")
        found = row if found is None else found.union(row)
    return found


def pairwise(p: DataFrame, truth: DataFrame) -> DataFrame:
    """Pair precision, recall, F1 and Rand index over the addresses both have."""
    return pairs_measured(p.select("addr", F.col("set_id").alias("a")).join(truth.select("addr", F.col("set_id").alias("b")), "addr"))


def pairs_measured(both: DataFrame, *by: str) -> DataFrame:
    """The same over rows that hold the set (a) and the true one (b) of an address already; apart for each value of the columns ``by``."""
    # cells, sets and devices in one pass: counts of cells are summed by either side
    cells = both.groupBy(*by, "a", "b").agg(F.count("*").alias("n"))
    sums = cells.groupingSets([(*by, "a", "b"), (*by, "a"), (*by, "b")], *by, "a", "b").agg(F.sum("n").alias("n"), F.grouping_id().alias("g"))
    of = lambda g: F.coalesce(F.sum(F.when(F.col("g") == g, (F.col("n") * (F.col("n") - 1) / 2).cast("bigint"))), F.lit(0).cast("bigint"))
    one = sums.groupBy(*by).agg(of(0).alias("tp"), F.sum(F.when(F.col("g") == 0, F.col("n"))).alias("total"), of(1).alias("predicted"), of(2).alias("actual"))
    every = F.col("total") * (F.col("total") - 1) / 2
    precision, recall = F.try_divide("tp", "predicted"), F.try_divide("tp", "actual")
    return one.select(
        *by, "tp", "predicted", "actual", F.round(precision, 6).alias("precision"), F.round(recall, 6).alias("recall"),
        F.round(F.try_divide(2 * F.col("tp"), F.col("predicted") + F.col("actual")), 6).alias("f1"), F.round(F.try_divide(every - F.col("predicted") - F.col("actual") + 2 * F.col("tp"), every), 6).alias("rand_index"),
    )


def split_merge(p: DataFrame, truth: DataFrame) -> DataFrame:
    """Per true device: its addresses, in how many sets they stand, and the largest of those."""
    both = p.select("addr", F.col("set_id").alias("a")).join(truth.select("addr", F.col("set_id").alias("b")), "addr")
    cells = both.groupBy("a", "b").agg(F.count("*").alias("n"))
    crowd = cells.groupBy("a").agg(F.count("*").alias("devices"))
    rows = cells.join(crowd, "a").groupBy("b").agg(F.sum("n").alias("addresses"), F.count("*").alias("sets"), F.max("n").alias("largest"), F.max((F.col("devices") > 1).cast("int")).alias("merged"))
    return rows.select(F.col("b").alias("device"), "addresses", "sets", F.round(F.col("largest") / F.col("addresses"), 6).alias("completeness"), "merged")
