"""Counter tests on hand-made samples and against their oracle texts."""

import pytest

from devicelens.operators import baselines
from devicelens.plans import load
from tests.test_entry import SF, duck, plain  # noqa: F401


def counters(spark, rows):
    return spark.createDataFrame([(7, key, t, v) for key, found in rows.items() for t, v in found], "asn long, addr_key long, t long, ipid long")


def pairs(df):
    return {(r.a, r.b) for r in df.collect()}


def against_oracle(spark, duck, key):  # noqa: F811
    queries, texts = load()
    got, want = queries[key](spark, SF).select("a", "b").toPandas(), duck.sql(texts[key]).df()
    assert len(want) and plain(got.astype(object).itertuples(index=False)) == plain(want[["a", "b"]].astype(object).itertuples(index=False))
    return got


def test_counter_of_varying_speed(spark):
    one = lambda t: 39 * t // 10 if t <= 100 else 390 + 41 * (t - 100) // 10  # noqa: E731 - 3.9 a unit of time, then 4.1
    rows = {1: [(t, one(t)) for t in (0, 40, 90)], 2: [(t, one(t)) for t in (110, 150, 210)], 3: [(t, 20 * t) for t in (0, 50, 99)], 4: [(t, (65_000 + one(t)) % 65_536) for t in (20, 130, 205)]}
    samples = counters(spark, rows)
    assert (1, 2) not in pairs(baselines.counter_pairs(samples))
    found = pairs(baselines.counter_pairs(samples, width=1))
    assert (1, 2) in found and not any(3 in p for p in found)


def test_ipid_pairs_equal_oracle(spark, duck):  # noqa: F811
    got = against_oracle(spark, duck, "ipid_monotonic_v4")
    from devicelens.plans.inputs import Inputs

    four = {r.a for r in Inputs(spark, SF).address.filter("family = 4").select("a").collect()}
    assert set(got.a) | set(got.b) <= four


def test_32_bit_counter_wraps(spark):
    one = lambda t: ((1 << 32) - 40_000_000 + 500_000 * t) % (1 << 32)
    rows = {1: [(t, one(t)) for t in (0, 50, 120)], 2: [(t, one(t)) for t in (30, 90, 140)]}
    assert pairs(baselines.counter_pairs(counters(spark, rows), 1 << 32, 1_000_000, width=1_000)) == {(1, 2)}


def test_fragid_pairs_equal_oracle(spark, duck):  # noqa: F811
    from devicelens.plans.inputs import Inputs

    x = Inputs(spark, SF)
    six = {r.a for r in x.address.filter("family = 6").select("a").collect()}
    assert {r.addr_key for r in x.fragid_samples.select("addr_key").distinct().collect()} <= six
    assert x.fragid_samples.agg({"ipid": "max"}).first()[0] > 1 << 31
    got = against_oracle(spark, duck, "fragid_monotonic_v6")
    assert set(got.a) | set(got.b) <= six
    same = {r.addr_key: r.device for r in x.truth.select("addr_key", "device").collect()}
    assert any(same[r.a] == same[r.b] for r in got.itertuples())
