"""Registered queries against the oracle on the smallest tables."""

import duckdb
import pytest

import __spark_entry__ as entry
from devicelens.plans import load
from devicelens.sources.fixture import GIVEN

SF = "/root/testdata/sf0.001"
SOME = ["responses_view", "funnel_counts", "alias_dual", "pairwise_accuracy", "vendor_popularity", "compare_exact", "ip_to_as", "reply_collapse", "scan_merge", "scan_merge_join"]
SURFACE = [
    "alias_two_offset_bins", "ipid_sets_v4", "fragid_sets_v6_computed", "grouped_map_pair_test", "tests_per_target", "join_self_pairs", "scan_partitioned", "scan_csv_json_orc_roundtrip", "source_python_capture",
    "source_python_capture_stream", "sink_sets", "sink_stream", "catalog_views", "udf_engine_id_arrow", "udaf_knee", "udtf_decode", "udtf_expand_prefix", "sql_udf_rel_hamming", "fn_map", "fn_ipv4_in_text", "st_scan_join",
    "join_stream_stream", "st_reboot_detector", "st_late_data",
]


@pytest.fixture(scope="module")
def duck():
    c = duckdb.connect()
    for t in GIVEN:
        c.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    return c


def plain(rows):
    def one(v):
        if v is None or str(v) in ("<NA>", "NaT", "nan"):
            return "-"
        return f"{float(v):.9g}" if not isinstance(v, str) and hasattr(v, "__float__") else str(v)

    return sorted(tuple(map(one, r)) for r in rows)


@pytest.mark.parametrize("key", SOME + SURFACE)
def test_query_equals_oracle(spark, duck, key):
    queries, texts = load()
    got, want = queries[key](spark, SF).toPandas(), duck.sql(texts[key]).df()
    names = sorted(got.columns)
    assert names == sorted(want.columns)
    assert plain(got[names].astype(object).itertuples(index=False)) == plain(want[names].astype(object).itertuples(index=False))


def test_entry_has_rows(spark):
    assert entry.entry(spark).count() > 0


def test_every_oracle_text_belongs_to_a_query():
    assert set(entry.oracle_sql()) <= set(entry.queries())
