"""Sketches within their error bounds, repeated replies, captures with bad lines, sets from pairs, plans."""

import pytest

from devicelens.operators import funnel, linking, netstats
from devicelens.plans import load
from devicelens.plans.inputs import Inputs
from devicelens.plans.surface import partitioned
from devicelens.sources import capture

SF = "/root/testdata/sf0.01"
REPLIES = "scan int, family int, addr string, addr_key long, recv_s long, engine_id string, boots long, engine_time long"


def run(spark, key):
    return load()[0][key](spark, SF).collect()


def test_sketches_within_their_bounds(spark):
    ids = {k: {r.engine_id for r in Inputs(spark, SF).responses.filter(f"scan = {k} AND engine_id IS NOT NULL").select("engine_id").distinct().collect()} for k in (1, 2)}
    got, = run(spark, "approx_id_counts")
    for estimate, true in ((got.scan_1, len(ids[1])), (got.scan_2, len(ids[2])), (got.both, len(ids[1] & ids[2]))):
        assert abs(estimate - true) <= 0.05 * true + 1
    exact = {r.engine_id: r["count"] for r in Inputs(spark, SF).responses.filter("scan = 1 AND engine_id IS NOT NULL").groupBy("engine_id").count().collect()}
    top = sorted(exact.values(), reverse=True)[:10]
    found = run(spark, "approx_heavy_ids")
    assert sorted((r.n for r in found), reverse=True) == pytest.approx(top, rel=0.05) and all(abs(r.n - exact[r.engine_id]) <= 0.05 * r.n + 1 for r in found)
    gaps = sorted(abs(r.r1 - r.r2) for r in Inputs(spark, SF).merged.select("r1", "r2").collect() if r.r1 is not None and r.r2 is not None)
    for r, share in zip(run(spark, "approx_ecdf"), (0.25, 0.5, 0.75, 0.9)):
        low, high = (gaps[min(len(gaps) - 1, max(0, int((share + d) * len(gaps))))] for d in (-0.001, 0.001))
        assert low <= r.gap_s <= high


def test_a_merged_row_has_one_packets_fields(spark):
    rows = [(1, 4, "a", 1, 100, "80aa", 3, 50), (1, 4, "a", 1, 105, "80zz", 9, 99), (1, 4, "b", 2, 90, None, 0, 0), (1, 4, "b", 2, 95, "80bb", 1, 5), (2, 4, "a", 1, 900, "80aa", 3, 850), (2, 4, "c", 3, 7, "", None, None)]
    df = spark.createDataFrame(rows, REPLIES)
    want = {("a", "80aa", 3, 50, "80aa", 850), ("b", "80bb", 1, 90, None, None), ("c", None, None, None, None, None)}
    for merged in (funnel.two_scans(df), funnel.two_scans_join(df)):
        assert {(r.addr, r.id1, r.boots1, r.r1, r.id2, r.engine_time2) for r in merged.collect()} == want


def test_merge_of_scans_shuffles_once(spark):
    plan = funnel.two_scans(spark.createDataFrame([], REPLIES))._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") == 1


def test_captures_keep_lines_that_do_not_parse(spark, tmp_path):
    (tmp_path / "a.txt").write_text("1\t4\t1.2.3.4\t7\t100\t80aa\t3\t50\n1\t4\t\t\t\t\t\t\nbroken\n1\tx\t1.2.3.4\t7\t100\t80aa\t3\t50")
    capture.register(spark)
    rows = spark.read.format("capture_lines").load(str(tmp_path)).collect()
    assert sorted(r.malformed or "" for r in rows) == ["", "", "1\tx\t1.2.3.4\t7\t100\t80aa\t3\t50", "broken"]
    assert (1, 4, "1.2.3.4", 7, 100, "80aa", 3, 50, None) in {tuple(r) for r in rows} and (1, 4, *[None] * 7) in {tuple(r) for r in rows}


def test_connected_names_components_by_their_smallest_node(spark):
    pairs = [(i, i + 1) for i in range(9)] + [(20, 25), (25, 22), (40, 41)]
    assert {(r.node, r.root) for r in linking.connected(spark.createDataFrame(pairs, "a long, b long")).collect()} == {(i, 0) for i in range(10)} | {(20, 20), (25, 20), (22, 20), (40, 40), (41, 40)}
    assert linking.connected(spark.createDataFrame([], "a long, b long")).count() == 0


def test_stored_replies_are_pruned_and_bucketed(spark):
    table = partitioned(Inputs(spark, SF).responses)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    plan = spark.sparkContext._jvm.PythonSQLUtils.explainString(table.filter("family = 6 AND scan = 1")._jdf.queryExecution(), "formatted")
    assert "PartitionFilters: [isnotnull(family" in plan
    joined = table.alias("a").join(table.alias("b").hint("merge"), "addr")._jdf.queryExecution().executedPlan().toString()
    spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    assert "Exchange" not in joined


def test_prefixes_of_other_lengths(spark):
    addrs = spark.createDataFrame([("10.1.2.3", 4), ("10.9.9.9", 4), ("11.0.0.1", 4)], "addr string, family int")
    prefixes = [(4, 10 << 24, None, 8, 1), (4, (10 << 24) + (1 << 16), None, 16, 2), (4, (10 << 24) + (1 << 16) + 512, None, 23, 3)]
    schema = "family int, base long, base6 string, length int, asn long"
    assert {(r.addr, r.asn) for r in netstats.lpm(addrs, spark.createDataFrame(prefixes, schema)).collect()} == {("10.1.2.3", 3), ("10.9.9.9", 1)}
    with pytest.raises(ValueError):
        netstats.lpm(addrs, spark.createDataFrame([(6, None, "2001:0db8::", 32, 1)], schema))


def plan_of(spark, key):
    return load()[0][key](spark, SF)._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize(
    "key, there, absent",
    [
        ("topk_heap", "TakeOrderedAndProject", "Sort ["), ("agg_sort", "SortAggregate", "ObjectHashAggregate"), ("agg_hash", "HashAggregate", "SortAggregate"), ("join_broadcast_hash", "BroadcastHashJoin", "SortMergeJoin"),
        ("join_sort_merge", "SortMergeJoin", "BroadcastHashJoin"), ("join_shuffle_hash", "ShuffledHashJoin", "SortMergeJoin"), ("sort_global", "rangepartitioning", "SinglePartition"), ("scan_parquet_pruned", "PushedFilters: [IsNotNull(o_totalprice)", "Exchange"),
    ],
)
def test_plans_of_operators(spark, key, there, absent):
    plan = spark.sparkContext._jvm.PythonSQLUtils.explainString(load()[0][key](spark, SF)._jdf.queryExecution(), "formatted") if key == "scan_parquet_pruned" else plan_of(spark, key)
    assert there in plan and absent not in plan


def test_pair_accuracy_reads_few_tables(spark):
    plan = plan_of(spark, "pairwise_accuracy")
    assert plan.count("FileScan") <= 8
