"""Relations kept as Parquet in the folder that driver and executors share, so that queries read them instead of deriving them again."""

from __future__ import annotations

import os
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

_PATHS: dict[tuple[str, str, str], str] = {}
_FOLDERS: dict[str, str] = {}


def shared_root(spark: SparkSession) -> str | None:
    """The session's spark.checkpoint.dir; on one machine a folder of our own where that is unset; on a cluster without it nothing is shared."""
    given = spark.conf.get("spark.checkpoint.dir", None)
    if given or not spark.sparkContext.master.startswith("local"):
        return given
    return _FOLDERS.setdefault(spark.sparkContext.applicationId, tempfile.mkdtemp(prefix="devicelens-shared-"))


def new_folder(spark: SparkSession, what: str) -> str:
    """A new path that driver and executors share."""
    root = shared_root(spark)
    if not root:
        raise ValueError("spark.checkpoint.dir must name a folder that the driver and all executors share")
    return os.path.join(root, f"{what}-{uuid.uuid4().hex}")


def exists(spark: SparkSession, path: str) -> bool:
    path = spark._jvm.org.apache.hadoop.fs.Path(path)
    return path.getFileSystem(spark._jsc.hadoopConfiguration()).exists(path)


def stored_path(spark: SparkSession, sf_dir: str, name: str, derived: Callable[[], DataFrame]) -> str | None:
    """Where the relation of a directory of tables is stored; written when first asked for. None where nothing is shared."""
    if not shared_root(spark):
        return None
    key = (spark.sparkContext.applicationId, sf_dir, name)
    if key not in _PATHS or not exists(spark, f"{_PATHS[key]}/_SUCCESS"):
        _PATHS[key] = new_folder(spark, name)
        derived().write.parquet(_PATHS[key])
    return _PATHS[key]
