"""Tables in the shared folder: how loops cut their lineage so that a lost executor costs a re-read only."""

from __future__ import annotations

import itertools
import os
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession, name: str) -> str:
    """A fresh folder below spark.checkpoint.dir; a temporary one only where that is unset on a local master."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not spark.sparkContext.master.startswith("local"):
            raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
        base = "file://" + os.path.join(tempfile.gettempdir(), f"shoal-shared-{os.getpid()}")
    folder = f"{base.rstrip('/')}/shoal/{name}-{uuid.uuid4().hex[:12]}"
    _MADE.append(folder)
    return folder


#: Folders named by this process, oldest first.
_MADE: list[str] = []


def made() -> int:
    """A mark for `remove_made`."""
    return len(_MADE)


def remove_made(spark: SparkSession, since: int = 0) -> None:
    """Removes all folders named since the mark. Only for runs whose results are written elsewhere or no longer needed."""
    for folder in _MADE[since:]:
        _delete(spark, folder)
    del _MADE[since:]


def _delete(spark: SparkSession, path: str) -> None:
    jvm_path = spark._jvm.org.apache.hadoop.fs.Path(path)
    jvm_path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(jvm_path, True)


class Scratch:
    """Written tables of one run; `drop` removes those no longer needed."""

    def __init__(self, spark: SparkSession, name: str) -> None:
        self.spark, self.base, self.numbers = spark, shared_folder(spark, name), itertools.count(1)  # threads share it

    def write(self, df: DataFrame, rows_per_file: int = 0) -> DataFrame:
        """Writes the rows and returns a DataFrame that reads them. Readers hold up to 4,096 rows of a file at once, so files of
        large rows should have few."""
        path = f"{self.base}/{next(self.numbers)}"
        df.write.option("maxRecordsPerFile", rows_per_file).parquet(path)
        out = self.spark.read.schema(df.schema).parquet(path)
        out._scratch_path = path
        return out

    def drop(self, *tables: DataFrame | None) -> None:
        for t in tables:
            path = getattr(t, "_scratch_path", None)
            if path:
                _delete(self.spark, path)
