"""Pair accuracy counts rows, also where an address has several."""

from types import SimpleNamespace

from devicelens.operators.alias import AliasSpec
from devicelens.plans import methods


def test_an_address_with_several_rows_is_not_multiplied(spark):
    valid = spark.createDataFrame([("a", 1, "x"), ("a", 2, "y"), ("b", 3, "x")], "addr string, addr_key long, id1 string")
    truth = spark.createDataFrame([(1, 7), (2, 8), (3, 7)], "addr_key long, device long")
    got = methods._pairwise(SimpleNamespace(valid=valid, truth=truth), AliasSpec(use_boots=False, reboot="none")).first()
    assert (got.tp, got.predicted, got.actual, got.rand_index) == (1, 1, 1, 1.0)
