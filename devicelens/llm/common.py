"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

WORD = r"[^\x20\x09-\x0D]+"  # a word: a run of bytes that are no ASCII white space
PORTION_BYTES, PORTION_ROWS = 1 << 20, 2_048


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: the session's spark.checkpoint.dir, or one of our own where that is unset."""
    own = spark.conf.get("spark.checkpoint.dir", None)
    if own:
        return own
    sc = spark.sparkContext
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        if not sc.master.startswith("local"):
            raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="devicelens-checkpoint-"))
    return sc._jsc.sc().getCheckpointDir().get()


def cut(df: DataFrame) -> DataFrame:
    """The same rows with their lineage cut by a reliable checkpoint in the shared folder."""
    shared_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def scratch(spark: SparkSession, what: str) -> str:
    """A new path under the shared folder for tables that an operator writes and reads again."""
    return os.path.join(shared_dir(spark), f"{what}-{uuid.uuid4().hex}")


def dealt(size: int, block_bytes: int, range_bytes: int) -> tuple[int, int]:
    """Blocks of documents, and ranges of keys, for so many bytes of text."""
    return max(1, -(-size // block_bytes)), max(1, -(-size // range_bytes))


def _hashed(k: int) -> int:
    """Spark's hash of an int column."""
    m = 0xFFFFFFFF
    turned = lambda x, r: (x << r | x >> (32 - r)) & m
    h = (turned(42 ^ turned(k * 0xCC9E2D51 & m, 15) * 0x1B873593 & m, 13) * 5 + 0xE6546B64) & m
    h ^= 4
    h = (h ^ h >> 16) * 0x85EBCA6B & m
    h = (h ^ h >> 13) * 0xC2B2AE35 & m
    h ^= h >> 16
    return h - (1 << 32) if h >> 31 else h


def labelled(block: Column, n: int) -> Column:
    """The numbers 0 to n - 1 by labels that a shuffle into n partitions deals out one to each; numbers of very many blocks stay as they are, as
    chance is even then."""
    if n > 2_048:
        return block
    labels: dict[int, int] = {}
    k = 0
    while len(labels) < n:
        labels.setdefault(_hashed(k) % n, k)
        k += 1
    return F.element_at(F.array(*(F.lit(x) for x in dict(sorted(labels.items())).values())), block + 1)


def text_or_empty(column: str = "text") -> Column:
    return F.coalesce(F.col(column), F.lit(""))


def spread(df: DataFrame, per_task: int = 1) -> int:
    """How many partitions a shuffle of this session has by default."""
    return max(1, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions")) * per_task)


def portions(batches: Iterator[pa.RecordBatch], text: int, at_most: int = PORTION_BYTES, rows: int = PORTION_ROWS) -> Iterator[pa.RecordBatch]:
    """All rows, in order, in smaller batches: the texts of column ``text`` have at_most bytes together (a longer one stands alone), so
    what Python makes of a batch doesn't grow with the batch that Spark sends."""
    for batch in batches:
        first, size = 0, 0
        for i, n in enumerate(pc.fill_null(pc.binary_length(batch.column(text)), 0).to_pylist()):
            if i > first and (size + n > at_most or i - first == rows):
                yield batch.slice(first, i - first)
                first, size = i, 0
            size += n
        yield batch.slice(first)


def quiet_tokenizers() -> None:
    """One thread a task: the cores are Spark's to share out."""
    os.environ["TOKENIZERS_PARALLELISM"] = "false"


def remainder(column: str, modulus: int) -> Column:
    """crc32 of an id written as text, modulo."""
    return F.pmod(F.crc32(F.encode(F.col(column).cast("string"), "utf-8")), F.lit(modulus))
