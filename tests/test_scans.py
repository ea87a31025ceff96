"""Consistency over any number of scans."""

from devicelens.plans.live import consistent, n_scan_consistency
from devicelens.plans import load
from tests.test_entry import SF, duck, plain  # noqa: F401


def test_every_scan_of_the_table_counts(spark):
    rows = [("all", s) for s in (1, 2, 3)] + [("twice", s) for s in (1, 1, 2, 3)] + [("two", s) for s in (1, 2)] + [("one", s) for s in (1, 1)]
    table = spark.createDataFrame([(s, 4, a, 1_000 * s, "80aa", 3, 500 + 1_000 * (s - 1)) for a, s in rows], "scan int, family int, addr string, recv_s long, engine_id string, boots long, engine_time long")
    assert {r.addr for r in consistent(table).collect()} == {"all", "twice"}


def test_two_scans_equal_oracle(spark, duck):  # noqa: F811
    got, want = n_scan_consistency(spark, SF).toPandas(), duck.sql(load()[1]["n_scan_consistency"]).df()
    assert plain(got.astype(object).itertuples(index=False)) == plain(want.astype(object).itertuples(index=False))
