"""Tables written once in the folder that all executors share, and removed when the process ends."""

from __future__ import annotations

import atexit
import os
from collections.abc import Callable
from typing import TypeVar
from uuid import uuid4

from pyspark.sql import DataFrame, SparkSession

T = TypeVar("T")
_left: list[tuple[SparkSession, str]] = []
_made: dict[tuple, object] = {}


def new_folder(spark: SparkSession) -> str:
    """A new folder under spark.checkpoint.dir; where that is unset (a local master, as in tests), under the warehouse."""
    base = spark.sparkContext.getCheckpointDir() or spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        base = spark.conf.get("spark.sql.warehouse.dir")
    folder = f"{base.rstrip('/')}/polymetric_{uuid4().hex}"
    _left.append((spark, folder))
    return folder


def delete(spark: SparkSession, path: str) -> None:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)


def size_of(spark: SparkSession, path: str) -> int:
    """Bytes under a path, by the file system's own listing."""
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(p).getLength()


@atexit.register
def _clear() -> None:
    for spark, path in _left:
        try:
            delete(spark, path)
        except Exception:  # noqa: BLE001 - the session may be over; the folder's owner clears it then
            return


def once(spark: SparkSession, key: tuple, make: Callable[[], T]) -> T:
    """What ``make`` gave the first time in this application, such as a saved table or index."""
    name = (spark.sparkContext.applicationId, os.getpid(), *key)
    if name not in _made:
        _made[name] = make()
    return _made[name]  # type: ignore[return-value]


def written(df: DataFrame, path: str) -> DataFrame:
    """The table written, and read by its known schema without a look at the files."""
    df.write.mode("overwrite").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
