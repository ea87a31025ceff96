"""Mixing sources to target weights by subset sums over document lengths.

Of every source the mix wants a number of words, the target. Whole repeats of a source go first; for what then remains of its
target, documents are counted by exact length and a like share of every length is taken. What a length's share lacks to a whole
document is carried to the next greater length, so neighbouring lengths share their documents out between them, and in the end less
than one document of the greatest length is left to fill. A bounded-knapsack dynamic program fills that with documents still at hand; where no
choice of them fits exactly, some of the shares are taken back, more and more of them, and the program chooses among those documents as
well. It ends with an exact fit, or with the best of all choices where the whole source fits its ``PROGRAM_WORDS``; in greater
sources a gap could only stay if not even that many words of free choice fit. How many documents of a
length go is thus decided on counts alone, whatever the seed; which of them, by a seeded order.

Rows: a null text has size 0 and is never taken; a null source is a source of its own, the last; rows that are repeated count
each; equal rows are equal to the order too, so reruns agree. An empty table gives no rows. Other columns are kept, but those named size,
source_size, target or taken, which the result's own replace.
"""

from __future__ import annotations

import math
from collections.abc import Iterable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from .common import WORD, text_or_empty

WEIGHTS, SHARE, MAX_REPEATS, SEED = (5, 2, 1), 1.0, 3, "mix-1"
DEALT = 256  # parts by the seeded order within one source and length, so that no single task ranks them all
PROGRAM_WORDS = 1 << 21  # words the dynamic program runs over at most, but for a single longer document: 4 bytes each


def sized(docs: DataFrame) -> DataFrame:
    return docs.withColumn("size", F.regexp_count(text_or_empty(), F.lit(WORD)).cast("long"))


def targets(totals: DataFrame, weights: Iterable[int] = WEIGHTS, share: float = SHARE, most: float = MAX_REPEATS) -> DataFrame:
    """source, source_size and target of every source, from one row (source, source_size) each.

    Sources in excess of ``most`` times their size are held there, and what they leave is shared among the others by weight, until
    none is above. The sources to hold are those with the smallest size for their weight, so a single ordered pass finds them.
    """
    cycle = F.array(*(F.lit(float(w)) for w in weights))
    by_name = W.orderBy(F.col("source").isNull(), F.encode("source", "utf-8"))
    tight = W.orderBy(F.col("limit") / F.col("weight"), F.col("place"))
    rest = tight.rowsBetween(0, W.unboundedFollowing)
    before = tight.rowsBetween(W.unboundedPreceding, -1)
    whole = W.partitionBy()
    return (
        totals.withColumn("place", F.row_number().over(by_name) - 1)
        .withColumn("weight", F.element_at(cycle, (F.col("place") % F.size(cycle) + 1).cast("int")))
        .withColumn("limit", F.col("source_size") * F.lit(float(most)))
        .withColumn("budget", F.sum("source_size").over(whole) * F.lit(float(share)))
        .withColumn("rate", (F.col("budget") - F.coalesce(F.sum("limit").over(before), F.lit(0.0))) / F.sum("weight").over(rest))
        .withColumn("held", F.col("rate") * F.col("weight") > F.col("limit"))
        .withColumn("free_rate", F.min(F.when(~F.col("held"), F.struct(F.row_number().over(tight).alias("n"), F.col("rate")))).over(whole)["rate"])
        .select("source", "source_size", F.when(F.col("free_rate").isNull() | (F.col("free_rate") * F.col("weight") > F.col("limit")), F.col("limit")).otherwise(F.col("free_rate") * F.col("weight")).alias("target"))
    )


def knapsack(budget: int, at_hand: dict[int, int]) -> dict[int, int]:
    """How many documents of each length, of those at hand, come nearest to the budget from below.

    One bit a sum says what can be reached, and one number a sum by which lot it was reached first: lots of 1, 2, 4 ... documents of a
    length stand for every number of them. Lengths come in the order given, and a sum prefers those that came first.
    """
    mask, reach, lots = (1 << (budget + 1)) - 1, 1, []
    first = np.full(budget + 1, -1, np.int32)
    for n, count in at_hand.items():
        rest, lot = min(count, budget // n), 1
        while rest > 0 and not reach >> budget & 1:
            lot = min(lot, rest)
            new = (reach << n * lot) & mask & ~reach
            if new:
                bits = np.unpackbits(np.frombuffer(new.to_bytes(-(-(budget + 1) // 8), "little"), np.uint8), bitorder="little")
                first[np.flatnonzero(bits)] = len(lots)
                lots.append((n, lot))
                reach |= new
            rest, lot = rest - lot, lot * 2
    at, taken = reach.bit_length() - 1, {}
    while at:  # a sum's first lot came after those of the sum without it
        n, lot = lots[first[at]]
        taken[n] = taken.get(n, 0) + lot
        at -= n * lot
    return taken


def fill(budget: int, lengths: dict[int, int], program_words: int = PROGRAM_WORDS) -> dict[int, int]:
    """How many documents of each length go: a like share of every length, then what fills the budget best from below."""
    if budget <= 0 or not lengths:
        return {}
    total = sum(n * c for n, c in lengths.items())
    if total <= budget:
        return dict(lengths)
    budget -= budget % math.gcd(*lengths)  # nothing lies between
    taken, owed = {}, 0  # owed: words times total, always less than a document of the length at hand
    for n in sorted(lengths):
        taken[n], part = divmod(lengths[n] * budget, total)
        owed += n * part
        if part and owed >= n * total:
            taken[n] += 1
            owed -= n * total
    left = budget - sum(n * c for n, c in taken.items())
    longest_first, back, given, free = sorted(lengths, reverse=True), {}, 0, 0
    while True:
        # documents of shares that were taken back come first, so the shares change no more than they must
        at_hand = {n: c for n, c in back.items() if c}
        more = knapsack(left + given, at_hand | {n: lengths[n] - taken[n] + back.get(n, 0) for n in longest_first if lengths[n] > taken[n] - back.get(n, 0)})
        gap = left + given - sum(n * c for n, c in more.items())
        held = [n for n in sorted(lengths) if taken[n] > back.get(n, 0)]
        free = max(2 * free, 4 * longest_first[0])
        if not gap or not held or left + given >= max(program_words, 2 * longest_first[0]):
            break
        while held and given < free:  # one more document of each length, the shortest first
            for n in held:
                if given < free:
                    back[n] = back.get(n, 0) + 1
                    given += n
            held = [n for n in held if taken[n] > back.get(n, 0)]
    for n in lengths:
        taken[n] += more.get(n, 0) - back.get(n, 0)
    return {n: c for n, c in taken.items() if c}


def choose_counts(lengths: DataFrame, goals: DataFrame) -> DataFrame:
    """source, size, repeats, extra, source_size and target: all documents of the size go ``repeats`` times, ``extra`` of them once more.

    A task holds the counts by length of one source: as many rows as it has lengths, however many documents.
    """

    def chosen(rows: pd.DataFrame) -> pd.DataFrame:
        target, total = float(rows.target.iloc[0]), int(rows.source_size.iloc[0])
        counts = dict(zip(rows["size"].tolist(), rows.documents.tolist()))
        counts.pop(0, None)
        repeats = min(MAX_REPEATS, int(target // total)) if total else 0
        extra = fill(round(target - repeats * total), counts) if repeats < MAX_REPEATS else {}
        return pd.DataFrame({"source": rows.source, "size": rows["size"], "repeats": [repeats if n else 0 for n in rows["size"]], "extra": [extra.get(n, 0) for n in rows["size"].tolist()], "source_size": total, "target": target})

    with_goal = lengths.join(goals, lengths.source.eqNullSafe(goals.source)).drop(goals.source)
    return with_goal.groupBy("source").applyInPandas(chosen, "source string, size long, repeats long, extra long, source_size long, target double")


def mix(docs: DataFrame, weights: Iterable[int] = WEIGHTS, share: float = SHARE, seed: str = SEED) -> DataFrame:
    """The rows of docs with size, source_size, target and taken (words that go, repeats counted)."""
    kept = [c for c in docs.columns if c not in ("size", "source_size", "target", "taken")]
    if "text" not in kept:  # sizes are known already
        rows = docs.select(*kept, "size")
    else:
        rows = sized(docs.select(*kept))
    lengths = rows.groupBy("source", "size").agg(F.count("*").alias("documents"))
    goals = targets(lengths.groupBy("source").agg(F.sum(F.col("size") * F.col("documents")).alias("source_size")), weights, share)
    counts = choose_counts(lengths, goals)
    order = F.xxhash64(F.lit(seed), F.col("doc_id"))
    mine = lambda name: F.col(f"mix.{name}")  # noqa: E731  the operator's own columns are fields of one, so that none can clash
    rows = rows.select(F.struct(*kept, "size").alias("row"), F.struct(F.col("source").alias("source"), F.col("size").alias("size"), order.alias("order"), F.pmod(F.shiftright(order, 20), F.lit(DEALT)).cast("int").alias("part"), F.col("doc_id").alias("doc_id")).alias("mix"))
    # a part's documents come after those of the parts before it
    parts = rows.groupBy(mine("source").alias("source"), mine("size").alias("size"), mine("part").alias("part")).agg(F.count("*").alias("n"))
    ahead = W.partitionBy("source", "size").orderBy("part").rowsBetween(W.unboundedPreceding, -1)
    parts = parts.withColumn("ahead", F.coalesce(F.sum("n").over(ahead), F.lit(0)))
    plan = parts.join(counts, parts.source.eqNullSafe(counts.source) & (parts["size"] == counts["size"])).select(
        F.struct(parts.source.alias("source"), parts["size"].alias("size"), F.col("part"), "repeats", (F.col("extra") - F.col("ahead")).alias("extra"), "source_size", "target").alias("plan")
    )
    joined = rows.join(plan, mine("source").eqNullSafe(F.col("plan.source")) & (mine("size") == F.col("plan.size")) & (mine("part") == F.col("plan.part")))
    ranked = W.partitionBy(mine("source"), mine("size"), mine("part")).orderBy(mine("order"), mine("doc_id"))
    once_more = (F.row_number().over(ranked) <= F.col("plan.extra")).cast("long")
    taken = mine("size") * (F.col("plan.repeats") + once_more)
    return joined.select("row", "plan", taken.alias("taken")).select(*(F.col(f"row.`{c}`").alias(c) for c in (*kept, "size")), F.col("plan.source_size").alias("source_size"), F.col("plan.target").alias("target"), "taken")
