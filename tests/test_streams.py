"""Results of streams stay with the executors."""

import collections

from devicelens.plans import surface
from devicelens.sources.fixture import stored
from devicelens.streaming import live

SF = "/root/testdata/sf0.001"


def test_appended_rows_are_in_files(spark):
    got = live.final_state(live.events(spark, SF).select("event_id", "user_id"), "append")
    assert got.inputFiles() and got.count() == spark.read.parquet(f"{SF}/events.parquet").count()
    none = live.final_state(live.events(spark, SF).filter("event_id < 0").select("event_id"), "append")
    assert none.columns == ["event_id"] and none.count() == 0


def test_complete_results_are_in_files(spark):
    got = live.final_state(live.counts(live.events(spark, SF)), "complete")
    want = spark.read.parquet(f"{SF}/events.parquet").groupBy("user_id").count()
    assert got.inputFiles() and {tuple(r) for r in got.collect()} == {tuple(r) for r in want.collect()}


def test_scan_join_keeps_its_state_on_disk(spark, monkeypatch, tmp_path):
    monkeypatch.setattr(live, "shared_folder", lambda _, what: str(tmp_path / what))
    settings = [spark.conf.get(k, None) for k in live.STATE_ON_DISK]
    got = surface.st_scan_join(spark, SF).collect()
    assert settings == [spark.conf.get(k, None) for k in live.STATE_ON_DISK]
    kept = [p for p in (tmp_path / "stream-checkpoint/state").rglob("*") if p.is_file()]
    assert "RocksDBStateStoreProvider" in (tmp_path / "stream-checkpoint/offsets/0").read_text() and kept and not any(p.name.endswith(".delta") for p in kept)
    spark.read.parquet(stored(spark, SF, "responses")).createOrReplaceTempView("replies_of_scans")
    want = spark.sql("""SELECT a.addr, a.engine_id, b.engine_id, a.recv_s, b.recv_s FROM replies_of_scans a JOIN replies_of_scans b
        ON a.addr = b.addr AND a.scan = 1 AND b.scan = 2 AND b.recv_s BETWEEN a.recv_s AND a.recv_s + 1209600""").collect()
    assert got and collections.Counter(map(tuple, got)) == collections.Counter(map(tuple, want))
