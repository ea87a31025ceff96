"""The shared-counter test by groups equals the plain one, however groups are cut."""

import random

import pytest

from devicelens.functions import udfs
from devicelens.operators import baselines


@pytest.mark.parametrize("whole, part", [(1000, 1000), (5, 1000), (5, 4)])
def test_groups_give_the_pairs_of_the_plain_test(spark, whole, part):
    draw, rows = random.Random(7), []
    for key in range(90):
        begin, speed, offset = draw.randrange(60), draw.choice([1, 2, 3, 9]), draw.choice([0, 0, 40_000, 60_000])
        rows += [(key, key % 3, begin + d, (offset + (begin + d) * speed) % 65536) for d in draw.sample(range(25), draw.randrange(3, 7))]
    samples = spark.createDataFrame(rows, "addr_key long, asn long, t long, ipid long")
    want = sorted(map(tuple, baselines.counter_pairs(samples, width=1).collect()))
    got = udfs.counter_test(baselines.velocities(samples, 65536, 3), samples, 65536, 60, 1, whole=whole, part=part)
    assert want and sorted(map(tuple, got.collect())) == want and "FlatMapGroupsInPandas" in got._jdf.queryExecution().executedPlan().toString()
