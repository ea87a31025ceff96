"""Alias resolution: addresses whose identifiers and clocks agree are one device."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W


@dataclass(frozen=True)
class AliasSpec:
    """Which fields make the key. ``reboot``: floor, round, exact, gap or none; ``width_s`` may be a column where rows are keyed by several widths (floor)."""

    use_id: bool = True
    use_boots: bool = True
    scans: tuple[int, ...] = (1, 2)
    reboot: str = "floor"
    width_s: int | Column = 20
    gap_s: int = 10


def bins(reboot: Column, spec: AliasSpec) -> Column:
    if spec.reboot == "exact":
        return reboot
    shift = spec.width_s // 2 if spec.reboot == "round" else 0
    return F.floor((reboot + shift) / spec.width_s)


def key_columns(spec: AliasSpec) -> list[Column]:
    parts = [F.col("id1").alias("k_id")] if spec.use_id else []
    for k in spec.scans:
        parts += [F.col(f"boots{k}").alias(f"k_boots{k}")] if spec.use_boots else []
        parts += [bins(F.col(f"r{k}"), spec).alias(f"k_reboot{k}")] if spec.reboot in ("floor", "round", "exact") else []
    return parts


def keyed(valid: DataFrame, spec: AliasSpec = AliasSpec()) -> DataFrame:
    """The rows with ``key``, a digest of the chosen fields: a function of the row alone, without a shuffle, but for gap sessions."""
    parts = key_columns(spec)
    if spec.reboot == "gap":
        base = W.partitionBy("id1", "boots1", "boots2").orderBy("r1", "addr_key")
        new = (F.col("r1") - F.lag("r1").over(base) > spec.gap_s).cast("int")
        valid = valid.withColumn("_new", F.coalesce(new, F.lit(0))).withColumn("_session", F.sum("_new").over(base.rowsBetween(W.unboundedPreceding, 0)))
        parts = [F.col("id1"), F.col("boots1"), F.col("boots2"), F.col("_session")]
    return valid.withColumn("key", F.md5(F.concat_ws("|", *(F.coalesce(p.cast("string"), F.lit("-")) for p in parts)))).drop("_new", "_session")


def resolve(valid: DataFrame, spec: AliasSpec = AliasSpec(), family: int | None = None) -> DataFrame:
    """set_id (smallest address key), engine_id, n, n4, n6, class and clock of every alias set: one shuffle on the key."""
    rows = keyed(valid if family is None else valid.filter(F.col("family") == family), spec)
    n4, n6 = F.count(F.when(F.col("family") == 4, 1)), F.count(F.when(F.col("family") == 6, 1))
    sets = rows.groupBy("key").agg(
        F.min("addr_key").alias("set_id"), F.min("id1").alias("engine_id"), F.max("id1").alias("other_id"), F.count("*").alias("n"), n4.alias("n4"), n6.alias("n6"),
        F.min("boots1").alias("boots"), F.min("r1").alias("reboot_min"), F.max("r1").alias("reboot_max"),
    )
    return classify(sets.drop("key"))


def classify(sets: DataFrame) -> DataFrame:
    return sets.withColumn("class", F.when(F.col("n6") == 0, "v4").when(F.col("n4") == 0, "v6").otherwise("dual")).withColumn("singleton", F.col("n") == 1)


def members(valid: DataFrame, spec: AliasSpec = AliasSpec()) -> DataFrame:
    """family, addr, addr_key, set_id: the long form."""
    rows = keyed(valid, spec)
    return rows.withColumn("set_id", F.min("addr_key").over(W.partitionBy("key"))).select("set_id", "family", "addr", "addr_key")


def stats(sets: DataFrame, by: str | None = "class") -> DataFrame:
    """Sets, non-singletons, addresses in those, their mean size, and the share of all addresses they cover."""
    more = F.col("n") > 1
    grouped = sets.groupBy(by) if by else sets.groupBy()
    covered = F.sum(F.when(more, F.col("n")).otherwise(0))
    return grouped.agg(
        F.count("*").alias("sets"), F.count(F.when(more, 1)).alias("nonsingletons"), covered.alias("addresses_in_them"),
        F.round(F.avg(F.when(more, F.col("n"))), 6).alias("mean_size"), F.round(covered / F.sum("n"), 6).alias("share_covered"),
    )


def tuple_uniqueness(df: DataFrame, bin_s: int = 20) -> DataFrame:
    """Addresses whose (boots, last-reboot bin) belongs to one id only."""
    groups = df.groupBy("boots1", F.floor(F.col("r1") / bin_s).alias("bin")).agg(F.count("*").alias("n"), (F.min("id1") == F.max("id1")).alias("one"))
    unique = F.sum(F.when(F.col("one"), F.col("n")).otherwise(0))
    return groups.agg(F.sum("n").alias("addresses"), unique.alias("unique_addresses"), F.round(unique / F.sum("n"), 6).alias("share"))


def reused_ids(sets: DataFrame) -> DataFrame:
    """Identifiers that the clock splits into several sets."""
    return sets.groupBy("engine_id").agg(F.count("*").alias("sets"), F.sum("n").alias("addresses"), (F.max("reboot_max") - F.min("reboot_min")).alias("span_s")).filter("sets > 1")


def dual_stack_hints(replies: DataFrame) -> DataFrame:
    """IPv6 replies whose id holds an IPv4 address, and whether that address answered too."""
    from devicelens.functions.codec import decode, render

    hints = replies.filter("family = 6 AND scan = 1").withColumn("id", decode(F.col("engine_id"))).filter("id.format = 'ipv4' AND length(id.data) = 8").select("addr", "addr_key", render(F.col("id")).alias("v4"))
    there = replies.filter("family = 4").select(F.col("addr").alias("v4")).distinct().withColumn("answered", F.lit(True))
    return hints.join(there, "v4", "left").select("addr", "addr_key", "v4", F.coalesce("answered", F.lit(False)).alias("answered"))
