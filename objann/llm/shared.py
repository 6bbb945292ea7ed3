"""Helpers that several operators use: the shared folder, written tables, null-safe columns."""

from __future__ import annotations

import atexit
import gc
import shutil
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_own_folder: str | None = None


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir`` of the session, else the folder
    that ``setCheckpointDir`` was given.

    Only where there is neither and the master is local, as in tests, a temporary folder is made and
    set as checkpoint folder; it goes when the process ends.  On any other master this is an error,
    as executors cannot read the driver's folders.
    """
    global _own_folder
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    given = spark.sparkContext._jsc.sc().getCheckpointDir()
    if given.isDefined() and (_own_folder is None or _own_folder not in given.get()):
        return given.get().rstrip("/")
    if _own_folder is None:
        master = spark.sparkContext.master
        if master != "local" and not master.startswith("local["):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        _own_folder = tempfile.mkdtemp(prefix="objann-shared-")
        atexit.register(shutil.rmtree, _own_folder, ignore_errors=True)
        spark.sparkContext.setCheckpointDir(f"{_own_folder}/rdd")
    return f"file://{_own_folder}"


def delete_path(spark: SparkSession, path: str) -> None:
    """Delete a folder of the shared store, whatever file system it is on."""
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


_scopes: list[list["WrittenTable"]] = []


class WrittenTable:
    """A DataFrame cut from its lineage: written as Parquet to the shared folder and read back.

    A table made inside ``scratch()`` goes at its end, unless it is ``lasting``.
    """

    def __init__(self, df: DataFrame, name: str, lasting: bool = False):
        self.spark, self.gone = df.sparkSession, False
        if _scopes and not lasting:
            _scopes[-1].append(self)
        self.path = f"{shared_folder(self.spark)}/objann/{name}-{uuid.uuid4().hex}"
        df.write.option("compression", "zstd").parquet(self.path)
        self.df = self.spark.read.schema(df.schema).parquet(self.path)

    def drop(self) -> None:
        if not self.gone:
            self.gone = True
            delete_path(self.spark, self.path)


@contextmanager
def scratch() -> Iterator[None]:
    """Tables that are written inside are deleted at the end; what a result reads must be ``lasting``."""
    held: list[WrittenTable] = []
    _scopes.append(held)
    try:
        yield
    finally:
        _scopes.remove(held)
        for table in held:
            table.drop()


def written(df: DataFrame, name: str, lasting: bool = False) -> DataFrame:
    """``df`` written to the shared folder and read back; later stages never recompute it."""
    return WrittenTable(df, name, lasting).df


def release_shuffles(spark: SparkSession) -> None:
    """Lets Spark delete the shuffle files of finished jobs now: it does so once the driver has collected their plans."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def text_or_empty(column: str = "text"):
    return F.coalesce(F.col(column).cast("string"), F.lit(""))


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def byte_slices(batch: pa.RecordBatch, column: int, most: int) -> Iterator[pa.RecordBatch]:
    """The batch in slices of whole rows whose text or binary ``column`` holds at most ``most`` bytes, or one row."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    first = 0
    while first < batch.num_rows:
        done = ends[first - 1] if first else 0
        stop = max(first + 1, int(np.searchsorted(ends, done + most, side="right")))
        yield batch.slice(first, stop - first)
        first = stop
