"""The methods as functions for SQL and Python callers: Arrow and pandas UDFs, table functions, SQL functions, and views.

The queries use the native expressions of ``codec``; what is here is for callers who need a function, and is tested to equal those.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window as W

from devicelens.functions.codec import AGENT_ENTERPRISE, FORMATS


@F.arrow_udf(returnType=T.StringType())
def engine_id_format(engine_id: pa.Array) -> pa.Array:
    """The format of identifiers in hex, as ``codec.decode`` gives it, by Arrow's own kernels."""
    text = pc.fill_null(engine_id, "")
    code, head = pc.utf8_slice_codeunits(text, 8, 10), pc.utf8_slice_codeunits(text, 0, 8)
    length = pc.utf8_length(text)
    cases = [
        (pc.equal(length, 0), "missing"),
        (pc.less(pc.utf8_slice_codeunits(text, 0, 1), "8"), "nonconforming"),
        (pc.less(length, 10), "truncated"),
        *((pc.equal(code, value), name) for value, name in FORMATS.items()),
        (pc.less(code, "80"), "reserved"),
        (pc.equal(head, f"{(1 << 31) + AGENT_ENTERPRISE:08x}"), "agent"),
    ]
    found = pa.array(["vendor"] * len(text), pa.string())
    for condition, name in reversed(cases):
        found = pc.if_else(condition, name, found)
    return found


@F.pandas_udf(returnType=T.DoubleType())
def knee_of(value: pd.Series, frac: pd.Series) -> float:
    """The value of a curve's point farthest above its chord; of equally far ones the smallest."""
    score = np.round(frac - value / max(value.max(), 1), 6)
    return float(value[score == score.max()].min())


@F.udtf(returnType=T.StructType([T.StructField("field", T.StringType()), T.StructField("value", T.StringType())]))
class DecodeEngineId:
    """One identifier as rows of field and value."""

    def eval(self, engine_id: str) -> Iterator[tuple[str, str]]:
        if not engine_id:
            return
        conforming = engine_id[0] >= "8"
        yield "conforming", str(conforming).lower()
        if conforming and len(engine_id) >= 10:
            yield "enterprise", str(int(engine_id[:8], 16) - (1 << 31))
            yield "data", engine_id[10:]
        else:
            yield "data", engine_id[8:] if conforming else engine_id


@F.udtf(returnType=T.StructType([T.StructField("addr", T.StringType())]))
class ExpandPrefix:
    """The first addresses of an IPv4 prefix, as targets."""

    def eval(self, base: int, length: int, n: int) -> Iterator[tuple[str]]:
        for x in range(base, base + min(n, 1 << (32 - length))):
            yield (".".join(str(x >> s & 255) for s in (24, 16, 8, 0)),)


def counter_test(able: DataFrame, samples: DataFrame, modulus: int, max_velocity: int, width: int, whole: int = 2000, part: int = 1000) -> DataFrame:
    """a < b of one network that have velocities at most ``width`` apart and whose samples (addr_key, t, ipid) rise as one counter; ``able`` as
    ``baselines.velocities`` gives it. Pairs are made within a group, never as rows of samples: a network of at most ``whole`` addresses is a group;
    a larger one has a group a bucket of velocity, to which those of the bucket below come as guests; and where more than ``part`` stand in such a
    bucket it is dealt into parts, a group for every two of them."""

    def merged(t, ipid, start, size, i, j):
        """Whether the samples of pairs, in order of time, are one counter."""
        ids, number = np.concatenate([i, j]), np.concatenate([np.arange(len(i))] * 2)
        n = size[ids]
        at = np.repeat(start[ids] - (np.cumsum(n) - n), n) + np.arange(n.sum())
        number = np.repeat(number, n)
        order = np.lexsort((ipid[at], t[at], number))
        at, number = at[order], number[order]
        step = np.diff(ipid[at], prepend=0) % modulus
        begin = np.flatnonzero(np.append(True, number[1:] != number[:-1]))
        step[begin] = 0
        span = t[at[np.append(begin[1:], len(at)) - 1]] - t[at[begin]]
        return (np.maximum.reduceat(step, begin) < modulus // 2) & (np.add.reduceat(step, begin) <= (span + 1) * max_velocity)

    def of_group(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("addr_key")
        key, moved, t0, t1 = (rows[c].to_numpy() for c in ("addr_key", "moved", "t0", "t1"))
        guest, own = rows.guest.to_numpy(), rows.own.to_numpy()
        crossing = bool(rows.lo.iloc[0] != rows.hi.iloc[0])
        t, ipid = (np.concatenate(rows[c].to_numpy()) for c in ("t", "ipid"))
        size = rows.t.map(len).to_numpy()
        start = np.cumsum(size) - size
        first, last, span = ipid[start], ipid[start + size - 1], np.maximum(t1 - t0, 1)
        found, rows_at_once = [], max(1, (1 << 20) // len(key))
        for low in range(0, len(key), rows_at_once):
            i = np.arange(low, min(low + rows_at_once, len(key)))[:, None]
            near = np.abs(moved[i] * span - moved * span[i]) <= width * span[i] * span
            near &= (i < np.arange(len(key))) & ~(guest[i] & guest)
            if crossing:
                near &= own[i] != own
            i, j = np.nonzero(near)
            i += low
            # of two addresses of which one was seen before the other only the step between them is new
            before, after = t1[i] < t0[j], t1[j] < t0[i]
            apart = before | after
            f, s = np.where(before, i, j), np.where(before, j, i)
            step = (first[s] - last[f]) % modulus
            same = apart & (step < modulus // 2) & (moved[f] + moved[s] + step <= (t1[s] - t0[f] + 1) * max_velocity)
            rest = np.flatnonzero(~apart)
            if len(rest):
                same[rest] = merged(t, ipid, start, size, i[rest], j[rest])
            found.append(np.stack([key[i[same]], key[j[same]]]))
        a, b = np.concatenate(found, axis=1)
        return pd.DataFrame({"a": a, "b": b})

    per = samples.groupBy("addr_key").agg(F.array_sort(F.collect_list(F.struct("t", "ipid"))).alias("x")).select("addr_key", F.col("x.t").alias("t"), F.col("x.ipid").alias("ipid"))
    many = F.count("*").over(W.partitionBy("asn")) > whole
    home = F.when(many, F.expr(f"velocity div {width}")).otherwise(F.lit(0))
    rows = able.filter("rising").select("asn", "addr_key", "moved", "t0", "t1", many.alias("many"), home.alias("home"), F.when(many, F.array(F.lit(0), F.lit(1))).otherwise(F.array(F.lit(0))).alias("up"))
    rows = rows.withColumn("up", F.explode("up")).withColumn("bucket", F.col("home") + F.col("up")).withColumn("guest", F.col("up") == 1)
    parts = F.when(F.col("many"), F.ceil(F.col("n") / part)).otherwise(F.lit(1))
    rows = rows.withColumn("n", F.count("*").over(W.partitionBy("asn", "bucket"))).withColumn("parts", parts).withColumn("own", F.pmod(F.xxhash64("addr_key"), F.col("parts")))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("parts") - 1)))
    rows = rows.withColumn("lo", F.least("own", "other")).withColumn("hi", F.greatest("own", "other")).drop("many", "home", "up", "n", "parts", "other")
    return rows.join(per, "addr_key").groupBy("asn", "bucket", "lo", "hi").applyInPandas(of_group, "a long, b long")


#: SQL functions that Catalyst puts in place of their calls.
SQL_FUNCTIONS = {
    "ip4_number": "(addr STRING) RETURNS BIGINT RETURN cast(split_part(addr, '.', 1) AS BIGINT) * 16777216 + cast(split_part(addr, '.', 2) AS BIGINT) * 65536 + cast(split_part(addr, '.', 3) AS BIGINT) * 256 + cast(split_part(addr, '.', 4) AS BIGINT)",
    "rel_hamming": "(data STRING) RETURNS DOUBLE RETURN aggregate(sequence(1, length(data)), 0, (s, k) -> s + bit_count(cast(conv(substring(data, k, 1), 16, 10) AS BIGINT))) / (4.0D * length(data))",
}


def register(spark: SparkSession) -> None:
    """Makes the functions callable from SQL in this session."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")
    spark.udf.register("engine_id_format", engine_id_format)
    spark.udtf.register("decode_engine_id", DecodeEngineId)
    spark.udtf.register("expand_prefix", ExpandPrefix)


def views(spark: SparkSession, relations: dict[str, DataFrame], prefix: str = "dl_") -> None:
    """Temporary views of relations and results of methods, and the functions, so that all can be used from SQL."""
    register(spark)
    for name, df in relations.items():
        df.createOrReplaceTempView(f"{prefix}{name}")
