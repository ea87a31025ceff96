"""The sweep over widths of bins: sets, non-singletons and pair accuracy of each."""

from devicelens.operators import compare
from devicelens.plans import load, methods
from tests.test_entry import SF, duck, plain  # noqa: F401
from tests.test_methods import valid


def sweep(spark, rows, truth):
    found = methods._bin_sweep(valid(spark, rows), spark.createDataFrame(truth, "addr_key long, device long"))
    return {r.width: tuple(r)[1:] for r in found.collect()}


def test_every_width_has_its_precision_and_recall(spark):
    rows = [("a", 4, "x", 120), ("b", 4, "x", 123), ("c", 4, "x", 138), ("d", 4, "x", 150), ("e", 4, "y", 120)]
    got = sweep(spark, rows, [(1, 7), (2, 7), (3, 7), (4, 8), (5, 9)])  # d is another device of the same id
    assert got == {1: (5, 0, None, 0.0), 5: (4, 1, 1.0, 0.333333), 10: (4, 1, 1.0, 0.333333), 20: (3, 1, 1.0, 1.0), 40: (2, 1, 0.5, 1.0), 60: (2, 1, 0.5, 1.0)}


def test_rows_without_a_true_device_count_as_sets_only(spark):
    got = sweep(spark, [("a", 4, "x", 100), ("b", 4, "x", 100), ("c", 4, "z", 100)], [(1, 7), (2, 7)])
    assert set(got.values()) == {(2, 1, 1.0, 1.0)}


def test_no_rows_give_every_width(spark):
    assert sweep(spark, [], []) == {w: (0, 0, None, None) for w in (1, 5, 10, 20, 40, 60)}


def test_pairs_measured_apart_equal_those_of_each_part(spark):
    rows = [(w, i // (2 * w), i // 3) for w in (1, 2, 5) for i in range(30)]
    both = spark.createDataFrame(rows, "w int, a long, b long")
    got = {r.w: tuple(r)[1:] for r in compare.pairs_measured(both, "w").collect()}
    assert got == {w: tuple(compare.pairs_measured(both.filter(f"w = {w}").drop("w")).first()) for w in (1, 2, 5)}


def test_sweep_equals_oracle(spark, duck):  # noqa: F811
    queries, texts = load()
    got, want = queries["alias_bin_sweep"](spark, SF).toPandas(), duck.sql(texts["alias_bin_sweep"]).df()
    assert list(got.columns) == list(want.columns) == ["width", "sets", "nonsingletons", "precision", "recall"]
    assert plain(got.astype(object).itertuples(index=False)) == plain(want.astype(object).itertuples(index=False))
