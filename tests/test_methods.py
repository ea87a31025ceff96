"""The funnel and alias resolution on hand-made rows."""

from pyspark.sql import functions as F

from devicelens.operators import alias, compare, distrib, funnel
from devicelens.operators.alias import AliasSpec

SCHEMA = "scan int, family int, addr string, addr_key long, recv_s long, engine_id string, boots long, engine_time long"
MAC = "800023290311223344556{}"


def replies(spark, rows):
    """(addr, family, [(id, boots, reboot) of scan 1 and of scan 2, or None])"""
    found = []
    for key, (addr, family, scans) in enumerate(rows, 1):
        for k, one in enumerate(scans, 1):
            if one:
                found.append((k, family, addr, key, 10_000_000 * k, one[0], one[1], 10_000_000 * k - one[2]))
    return spark.createDataFrame(found, SCHEMA)


def registry(spark):
    return spark.createDataFrame([("112233", "Brand#1")], "prefix string, vendor string")


def test_each_row_lands_on_its_own_step(spark):
    good = (MAC.format("6"), 3, 5_000)
    rows = [
        ("ok", 4, [good, good]), ("missing", 4, [(None, 3, 5_000), (None, 3, 5_000)]), ("once", 4, [good, None]), ("differs", 4, [good, (MAC.format("7"), 3, 5_000)]), ("short", 4, [("80aabb", 3, 5_000)] * 2),
        ("private", 4, [("80002329010a000001", 3, 5_000)] * 2), ("mac", 4, [("8000232903ffffff445566", 3, 5_000)] * 2), ("zero", 4, [(MAC.format("8"), 0, 5_000)] * 2),
        ("future", 4, [(MAC.format("8"), 3, -9)] * 2), ("boots", 4, [(MAC.format("8"), 3, 5_000), (MAC.format("8"), 4, 5_000)]), ("jump", 4, [(MAC.format("8"), 3, 5_000), (MAC.format("8"), 3, 5_011)]),
        ("prom1", 4, [("8000232905aaaaaaaa", 3, 5_000)] * 2), ("prom2", 4, [("8000232a05aaaaaaaa", 3, 5_000)] * 2),
    ]
    flags = funnel.flagged(funnel.two_scans(replies(spark, rows)), registry(spark))
    got = {r.addr: r.step for r in flags.select("addr", "step").collect()}
    assert got == {"ok": None, "missing": 1, "once": 2, "differs": 3, "short": 4, "prom1": 5, "prom2": 5, "private": 6, "mac": 7, "zero": 8, "future": 9, "boots": 10, "jump": 11}
    report = {r.step: (r.entering, r.removed, r.remaining) for r in funnel.report(flags).collect()}
    assert report[1] == (13, 1, 12) and report[11][2] == 1


def test_promiscuous_sees_only_survivors(spark):
    rows = [("a", 4, [("8000232905aaaaaaaa", 3, 5_000)] * 2), ("b", 4, [("8000232a05aaaaaaaa", 3, 5_000), None])]
    got = {r.addr: r.step for r in funnel.flagged(funnel.two_scans(replies(spark, rows)), registry(spark)).collect()}
    assert got == {"a": None, "b": 2}


def test_pivot_merge_equals_join_merge(spark):
    good = (MAC.format("6"), 3, 5_000)
    df = replies(spark, [("a", 4, [good, good]), ("b", 6, [good, None]), ("c", 4, [None, good]), ("d", 4, [(None, 1, 2), None])])
    a, b = funnel.two_scans(df), funnel.two_scans_join(df)
    assert sorted(map(str, a.collect())) == sorted(map(str, b.select(*a.columns).collect()))


def valid(spark, rows):
    return spark.createDataFrame([(f, a, k, i, 3, 3, r, r) for k, (a, f, i, r) in enumerate(rows, 1)], "family int, addr string, addr_key long, id1 string, boots1 long, boots2 long, r1 long, r2 long")


def test_dual_stack_concept(spark):
    sets = alias.resolve(valid(spark, [("A", 4, "x", 100), ("B", 4, "x", 101), ("C6", 6, "x", 102), ("D", 4, "y", 100)])).orderBy("set_id").collect()
    assert [(s["n"], s["class"]) for s in sets] == [(3, "dual"), (1, "v4")]


def test_bin_edges_and_gaps(spark):
    rows = valid(spark, [("a", 4, "x", 19), ("b", 4, "x", 20), ("c", 4, "y", 0), ("d", 4, "y", 19)])
    sizes = lambda spec: sorted(r["n"] for r in alias.resolve(rows, spec).collect())
    assert sizes(AliasSpec()) == [1, 1, 2]
    assert sizes(AliasSpec(reboot="gap")) == [1, 1, 2]
    assert sizes(AliasSpec(use_boots=False, reboot="none")) == [2, 2]
    assert {(r.addr, r.set_id) for r in alias.members(rows, AliasSpec(reboot="gap")).collect()} == {("a", 1), ("b", 1), ("c", 3), ("d", 4)}


def test_cloned_id_is_split(spark):
    rows = valid(spark, [("a", 4, "x", 100), ("b", 4, "x", 90_000_000)])
    assert alias.resolve(rows).count() == 2
    assert alias.resolve(rows, AliasSpec(use_boots=False, reboot="none")).count() == 1


def test_partition_measures(spark):
    p = spark.createDataFrame([(1, "a"), (1, "b"), (2, "c"), (3, "d")], "set_id long, addr string")
    q = spark.createDataFrame([("x", "a"), ("x", "b"), ("y", "c"), ("y", "d")], "set_id string, addr string")
    assert compare.exact(compare.contingency(p, q)).first().exact == 1
    assert compare.exact(compare.contingency(p, p)).first().exact == 3
    x = compare.pairwise(p, q).first()
    assert (x.tp, x.predicted, x.actual, x.precision, x.recall, x.rand_index) == (1, 1, 2, 1.0, 0.5, round(5 / 6, 6))


def test_ecdf_and_knee(spark):
    df = spark.createDataFrame([(0,)] * 6 + [(1,)] * 3 + [(10,)], "v long")
    curve = distrib.ecdf(df, "v").orderBy("value").collect()
    assert [(r.value, r.cum_n, r.frac) for r in curve] == [(0, 6, 0.6), (1, 9, 0.9), (10, 10, 1.0)]
    assert distrib.knee(distrib.ecdf(df, "v")).first().value == 1


def test_merge_plan_has_one_shuffle(spark):
    plan = funnel.two_scans(replies(spark, [("a", 4, [("x", 1, 1), ("x", 1, 1)])]))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1 and "Python" not in plan
