"""Sets from pairs: connected components, for the methods whose result is a relation between addresses rather than a key."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from devicelens.operators.alias import AliasSpec, keyed
from devicelens.sources.stored import new_folder


def _kept(df: DataFrame) -> DataFrame:
    """The rows, written to the shared folder: a round's lineage ends there."""
    path = new_folder(df.sparkSession, "linking")
    df.write.parquet(path)
    return df.sparkSession.read.parquet(path)


def connected(pairs: DataFrame) -> DataFrame:
    """node and root (the smallest node reachable) of the nodes of pairs (a, b).

    Each round every node takes the first of its closed neighbourhood and the graph is contracted to those: the smallest in the first
    round, the first by a new hash in the others, so that chains halve whatever their order.
    """
    left = _kept(pairs.select("a", "b").filter("a <> b").distinct())
    roots, number = None, 0
    while not left.isEmpty():
        order = lambda c: F.struct(F.xxhash64(F.lit(number), F.col(c)).alias("h") if number else F.lit(0).alias("h"), F.col(c).alias("n"))  # noqa: B023, E731
        both = left.union(left.select(F.col("b").alias("a"), F.col("a").alias("b")))
        first = _kept(both.groupBy("a").agg(F.min(order("b")).alias("f")).select(F.col("a").alias("node"), F.least("f", order("a"))["n"].alias("root")))
        step = first.select(F.col("node").alias("root"), F.col("root").alias("next"))
        roots = first if roots is None else _kept(roots.join(step, "root", "left").select("node", F.coalesce("next", "root").alias("root")))
        ends = {k: first.select(F.col("node").alias(k), F.col("root").alias(f"r{k}")) for k in "ab"}
        left = _kept(left.join(ends["a"], "a").join(ends["b"], "b").filter("ra <> rb").select(F.col("ra").alias("a"), F.col("rb").alias("b")).distinct())
        number += 1
    if roots is None:
        return left.select(F.col("a").alias("node"), F.col("b").alias("root"))
    return roots.join(roots.groupBy("root").agg(F.min("node").alias("least")), "root").select("node", F.col("least").alias("root"))


def two_grids(valid: DataFrame, width_s: int = 20) -> DataFrame:
    """family, addr, addr_key and set_id: addresses that share a bin of either of two grids, shifted by half a bin, stand in one set, and so
    does what hangs together over them. Only sets of the two grids that differ become edges."""
    rows = keyed(valid, AliasSpec(width_s=width_s)).withColumnRenamed("key", "k0")
    rows = keyed(rows, AliasSpec(reboot="round", width_s=width_s)).withColumnRenamed("key", "k1").select("family", "addr", "addr_key", "k0", "k1")
    least = lambda k: rows.groupBy(k).agg(F.min("addr_key").alias(f"s_{k}"))
    placed = rows.join(least("k0"), "k0").join(least("k1"), "k1")
    roots = connected(placed.select(F.col("s_k0").alias("a"), F.col("s_k1").alias("b")))
    return placed.join(roots, placed.s_k0 == roots.node, "left").select("family", "addr", "addr_key", F.coalesce("root", "s_k0").alias("set_id"))


def capped_pairs(members: DataFrame, cap: int) -> DataFrame:
    """set_id, a, b: pairs (a < b) of the first ``cap`` members of every set, for samples to validate; a set gives no more than cap^2 / 2 rows."""
    from pyspark.sql.window import Window as W

    first = members.withColumn("k", F.row_number().over(W.partitionBy("set_id").orderBy("addr_key"))).filter(F.col("k") <= cap)
    side = lambda name: first.select("set_id", F.col("addr_key").alias(name))
    return side("a").join(side("b"), "set_id").filter("a < b")


def tests_per_target(targets: DataFrame, tried: DataFrame, ours: int, tool: int) -> DataFrame:
    """method, targets, tests a target, tests in all: one probe for every target, against an active tool's tests for those it tried."""
    of = lambda name, df, n: df.agg(F.count("*").alias("targets")).select(F.lit(name).alias("method"), "targets", F.lit(n).alias("tests_per_target"), (F.col("targets") * n).alias("tests"))
    return of("one probe", targets, ours).union(of("active tool", tried, tool))




def exploded(pairs: DataFrame, samples: DataFrame) -> DataFrame:
    """a, b, addr_key, t and ipid: the samples of both addresses of every pair."""
    return pairs.withColumn("addr_key", F.explode(F.array("a", "b"))).join(samples.select("addr_key", "t", "ipid"), "addr_key")
