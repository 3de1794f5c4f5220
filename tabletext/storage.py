"""Intermediate tables in the folder that driver and executors share.

``spark.checkpoint.dir`` names that folder.  Only where it is unset, as in tests, a folder of the
local machine takes its place.  A written table cuts the lineage: a lost executor costs a re-read,
not a recomputation.  Tables go when ``release`` is told that their readers are done, or with the
application.
"""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own: dict[str, str] = {}
_written: list[str] = []


def shared_folder(spark: SparkSession) -> str:
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if "dir" not in _own:
        _own["dir"] = tempfile.mkdtemp(prefix="tabletext-")
        atexit.register(shutil.rmtree, _own["dir"], True)
    return "file://" + _own["dir"]


def _path(spark: SparkSession, path: str):
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    return at.getFileSystem(spark._jsc.hadoopConfiguration()), at


def folder(spark: SparkSession, name: str) -> str:
    """A new empty folder for intermediate data, which goes as written tables go."""
    path = f"{shared_folder(spark)}/tabletext/{name}-{uuid.uuid4().hex}"
    files, at = _path(spark, path)
    files.mkdirs(at)
    files.deleteOnExit(at)
    _written.append(path)
    return path


def written(df: DataFrame, name: str) -> DataFrame:
    """Write a table and read it again, with the schema known beforehand."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/tabletext/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    files, at = _path(spark, path)
    files.deleteOnExit(at)
    _written.append(path)
    return spark.read.schema(df.schema).parquet(path)


def mark() -> int:
    """How many tables have been written; for ``release``."""
    return len(_written)


def release(spark: SparkSession, since: int = 0) -> None:
    """Deletes the tables written since a mark, when what reads them has been written itself."""
    while len(_written) > since:
        delete(spark, _written.pop())


def delete(spark: SparkSession, path: str) -> None:
    files, at = _path(spark, path)
    files.delete(at, True)


def partitions_for(spark: SparkSession, rows: float, each: int) -> int:
    """Enough partitions that none gets far more than ``each`` rows, and at least the session's number."""
    return int(max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-rows // each), 1))
