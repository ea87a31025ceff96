"""A data source of captures in lines of text: scan, family, address, key, time of receipt, identifier, restarts, clock; tab-separated, an empty field is
null. It reads folders as a batch, a file a task, and as a stream that takes up files as they appear. Lines that don't parse are kept
with their text in ``malformed``."""

from __future__ import annotations

from collections.abc import Iterator
from urllib.parse import unquote, urlparse

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, DataSourceStreamReader, InputPartition

FIELDS = {"scan": int, "family": int, "addr": str, "addr_key": int, "recv_s": int, "engine_id": str, "boots": int, "engine_time": int}
SCHEMA = "scan int, family int, addr string, addr_key long, recv_s long, engine_id string, boots long, engine_time long, malformed string"


def _store(uri: str):
    """The file system of a path or address, and the path in it."""
    from pyarrow import fs

    parsed = urlparse(uri)
    return (fs.LocalFileSystem(), unquote(parsed.path)) if parsed.scheme in ("", "file") else fs.FileSystem.from_uri(uri)


def files(uri: str) -> list[str]:
    """Data files of a folder, in order of names."""
    from pyarrow import fs

    store, path = _store(uri)
    found = store.get_file_info(fs.FileSelector(path, recursive=True))
    return sorted(f.path for f in found if f.is_file and not f.base_name.startswith(("_", ".")))


def parsed(line: str) -> tuple:
    parts = line.split("\t")
    try:
        if len(parts) != len(FIELDS):
            raise ValueError
        return (*(kind(x) if x else None for x, kind in zip(parts, FIELDS.values())), None)
    except ValueError:
        return (*(None for _ in FIELDS), line)


def _rows(uri: str, path: str) -> Iterator[tuple]:
    store, _ = _store(uri)
    with store.open_input_stream(path) as raw:
        held = b""
        while block := raw.read(1 << 20):
            *lines, held = (held + block).split(b"\n")
            yield from (parsed(x.decode("utf-8", "replace")) for x in lines)
        if held:
            yield parsed(held.decode("utf-8", "replace"))


class CaptureReader(DataSourceReader):
    def __init__(self, uri: str):
        self.uri = uri

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(path) for path in files(self.uri)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        return _rows(self.uri, partition.value) if partition.value else iter(())


class CaptureStreamReader(DataSourceStreamReader):
    """Offsets count the files in order of names; files are only added behind those there are."""

    def __init__(self, uri: str):
        self.uri = uri

    def initialOffset(self) -> dict:
        return {"files": 0}

    def latestOffset(self) -> dict:
        return {"files": len(files(self.uri))}

    def partitions(self, start: dict, end: dict) -> list[InputPartition]:
        return [InputPartition(path) for path in files(self.uri)[start["files"] : end["files"]]]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        return _rows(self.uri, partition.value)

    def commit(self, end: dict) -> None:
        pass


class CaptureSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "capture_lines"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> CaptureReader:
        return CaptureReader(self.options["path"])

    def streamReader(self, schema) -> CaptureStreamReader:
        return CaptureStreamReader(self.options["path"])


def register(spark: SparkSession) -> None:
    spark.dataSource.register(CaptureSource)
