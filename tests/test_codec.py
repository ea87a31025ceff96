"""Worked values of identifiers."""

from pyspark.sql import functions as F

from devicelens.functions import codec


def rows(spark, values):
    return spark.createDataFrame([(v,) for v in values], "engine_id string")


def test_golden_reply(spark):
    x = rows(spark, ["800007c703748ef831db80"]).select(codec.decode(F.col("engine_id")).alias("id")).select("id.*", codec.render(F.col("id")).alias("readable")).first()
    assert (x.conforming, x.enterprise, x.format, x.data, x.n_bytes, x.readable) == (True, 1991, "mac", "748ef831db80", 11, "74:8e:f8:31:db:80")


def test_golden_bit_weights(spark):
    got = rows(spark, ["0300e0acf1325a88", "3910910680002970", "0f010e3732bed25e00000000"]).select(codec.ones(F.col("engine_id")).alias("n"), codec.rel_hamming(F.col("engine_id")).alias("w")).collect()
    assert [r.n for r in got] == [23, 17, 31]
    assert [round(r.w, 3) for r in got] == [0.359, 0.266, 0.323]


def test_odd_identifiers_never_raise(spark):
    got = rows(spark, [None, "", "80", "80aabb", "0300e0acf1325a88", "8000000106", "80002327" + "80" + "00", "8000000101" + "0a"]).select(codec.decode(F.col("engine_id")).alias("id")).select("id.*", codec.render(F.col("id")).alias("r")).collect()
    assert [r.format for r in got] == ["missing", "missing", "truncated", "truncated", "nonconforming", "reserved", "agent", "ipv4"]


def test_addresses(spark):
    x = spark.range(1).select(codec.ip4_to_long(F.lit("20.0.1.2")).alias("n"), codec.long_to_ip4(F.lit(335544578)).alias("a"), codec.prefix_of(F.lit(335544578), 24).alias("p"), codec.mac_normalise(F.lit("AA-bb:CC.01")).alias("m")).first()
    assert (x.n, x.a, x.p, x.m) == (335544578, "20.0.1.2", 335544576, "aabbcc01")
