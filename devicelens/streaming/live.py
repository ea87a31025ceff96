"""The methods over a stream of replies: windows, sessions, duplicates, joins with dimensions, and folding batches into a table."""

from __future__ import annotations

import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from devicelens.sources.stored import new_folder as shared_folder

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"

#: State in RocksDB on the executors' disks, one store a partition, and native memory of an executor bounded.
STATE_ON_DISK = {
    "spark.sql.streaming.stateStore.providerClass": "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider", "spark.sql.streaming.join.stateFormatVersion": "3",
    "spark.sql.streaming.stateStore.rocksdb.changelogCheckpointing.enabled": "true", "spark.sql.streaming.stateStore.rocksdb.trackTotalNumberOfRows": "false",
    "spark.sql.streaming.stateStore.rocksdb.boundedMemoryUsage": "true", "spark.sql.streaming.stateStore.rocksdb.maxMemoryUsageMB": "500",
}


@contextmanager
def state_on_disk(spark: SparkSession) -> Iterator[None]:
    """Streams started in here keep their state on disk; the session's own settings are as before afterwards."""
    before = {k: spark.conf.get(k, None) for k in STATE_ON_DISK}
    try:
        for k, v in STATE_ON_DISK.items():
            spark.conf.set(k, v)
        yield
    finally:
        for k, v in before.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def events(spark: SparkSession, sf_dir: str, late: str = "2 hours") -> DataFrame:
    """The events as a stream with zoned event time and a watermark."""
    stream = spark.readStream.schema(EVENTS).parquet(f"{sf_dir}/events*.parquet")
    return stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def final_state(stream: DataFrame, mode: str) -> DataFrame:
    """Runs the stream over what there is now and gives its result, which the executors write to the shared folder: none of it passes through the
    driver. Appended rows are there exactly once; of complete results each batch's replaces the one before."""
    folder = shared_folder(stream.sparkSession, "stream")
    if mode == "append":
        return to_files(stream, folder)
    writer = stream.writeStream.foreachBatch(lambda batch, _: batch.write.mode("overwrite").parquet(folder)).outputMode(mode)
    writer.trigger(availableNow=True).option("checkpointLocation", f"{folder}-checkpoint").start().awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(folder)


def tumbling(stream: DataFrame, width: str = "1 hour", slide: str | None = None) -> DataFrame:
    window = F.window("ts", width, slide) if slide else F.window("ts", width)
    return stream.groupBy(window.alias("w")).agg(F.count("*").alias("replies")).select(F.unix_seconds("w.start").alias("start_s"), "replies")


def sessions(stream: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """Bursts of one address: replies that follow each other within the gap."""
    return stream.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("replies")).select("user_id", F.unix_micros("w.start").alias("start_us"), "replies")


def first_of_day(stream: DataFrame) -> DataFrame:
    """One reply an address and day."""
    return stream.withColumn("day", F.to_date("ts")).dropDuplicates(["user_id", "day"]).select("user_id", F.date_format("day", "yyyy-MM-dd").alias("day"))


def counts(stream: DataFrame) -> DataFrame:
    return stream.groupBy("user_id").agg(F.count("*").alias("replies"))


def by_segment(stream: DataFrame, customers: DataFrame) -> DataFrame:
    """Live counts by a dimension of the address."""
    return stream.join(customers.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id").groupBy("c_mktsegment").agg(F.count("*").alias("replies"))


def upsert_counts(stream: DataFrame, folder: str) -> None:
    """Folds every micro-batch into counts by address; a batch that is repeated overwrites its own part, so nothing is counted twice."""

    def fold(batch: DataFrame, number: int) -> None:
        batch.groupBy("user_id").agg(F.count("*").alias("replies"), F.max("ts").alias("last")).write.mode("overwrite").parquet(f"{folder}/batch={number}")

    stream.writeStream.foreachBatch(fold).trigger(availableNow=True).option("checkpointLocation", f"{folder}-checkpoint").start().awaitTermination()


def stored_stream(spark: SparkSession, path: str, time: str, late: str, files_at_once: int | None = None) -> DataFrame:
    """A stored relation as a stream, with event time ``ts`` from a column of seconds and a watermark."""
    reader = spark.readStream.schema(spark.read.parquet(path).schema)
    reader = reader.option("maxFilesPerTrigger", files_at_once) if files_at_once else reader
    return reader.parquet(path).withColumn("ts", F.timestamp_seconds(time)).withWatermark("ts", late)


def scan_join(first: DataFrame, second: DataFrame, within: str = "14 days") -> DataFrame:
    """Replies of one scan joined live with those of the next, of the same address and within a time: state older than that goes. What is left holds every reply of both
    scans where those lie within the time of each other, so it belongs on disk (``state_on_disk``)."""
    a = first.select("addr", F.col("ts").alias("ts1"), F.col("engine_id").alias("id1"), F.col("recv_s").alias("recv_s1"))
    b = second.select(F.col("addr").alias("addr2"), F.col("ts").alias("ts2"), F.col("engine_id").alias("id2"), F.col("recv_s").alias("recv_s2"))
    on = (F.col("addr") == F.col("addr2")) & (F.col("ts2") >= F.col("ts1")) & (F.col("ts2") <= F.col("ts1") + F.expr(f"INTERVAL {within}"))
    return a.join(b, on).select("addr", "id1", "id2", "recv_s1", "recv_s2")


def changes(stream: DataFrame, jump_s: int = 10, idle: str = "30 days") -> DataFrame:
    """Per address, what differs from its reply before: an id change, a reboot (more restarts) or a clock jump (a last reboot that moved by more than
    ``jump_s`` with as many restarts). The last reply is the state; that of an address that is silent for so long goes."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    idle_ms = int(pd.Timedelta(idle).total_seconds() * 1000)

    def seen(key, batches, state):
        if state.hasTimedOut:
            state.remove()
            return
        last = tuple(state.get) if state.exists else None
        rows = pd.concat(list(batches)).sort_values(["recv_s", "event_id"])
        found = []
        for r in rows.itertuples(index=False):
            now = (r.engine_id, int(r.boots), int(r.recv_s - r.engine_time))
            if last:
                kind = "id" if now[0] != last[0] else "reboot" if now[1] > last[1] else "clock" if abs(now[2] - last[2]) > jump_s else None
                if kind:
                    found.append((int(key[0]), int(r.event_id), kind))
            last = now
        state.update(last)
        state.setTimeoutTimestamp(max(int(rows.recv_s.max()) * 1000, state.getCurrentWatermarkMs()) + idle_ms)
        yield pd.DataFrame(found, columns=["addr", "event_id", "change"])

    rows = stream.groupBy("addr")
    return rows.applyInPandasWithState(seen, "addr long, event_id long, change string", "engine_id string, boots long, reboot_s long", "append", GroupStateTimeout.EventTimeTimeout)


def late_rows(stream: DataFrame, keys: list[str]) -> tuple[int, int]:
    """Rows that the watermark let in and rows that came too late, of a stream whose rows are distinct by the keys and time."""
    name = f"late_{uuid.uuid4().hex}"
    writer = stream.dropDuplicates([*keys, "ts"]).writeStream.format("memory").queryName(name).outputMode("append").trigger(availableNow=True)
    run = writer.option("checkpointLocation", shared_folder(stream.sparkSession, "late")).start()
    run.awaitTermination()
    dropped = sum(op["numRowsDroppedByWatermark"] for p in run.recentProgress for op in p["stateOperators"])
    return stream.sparkSession.table(name).count(), dropped


def to_files(stream: DataFrame, folder: str) -> DataFrame:
    """Writes a stream to files, each batch exactly once, and gives what is there."""
    run = stream.writeStream.format("parquet").option("path", folder).option("checkpointLocation", f"{folder}-checkpoint").trigger(availableNow=True).start()
    run.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(folder)
