"""Reading and writing tables."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own_folder: str | None = None


def load_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def work_folder(spark: SparkSession) -> str:
    """Where driver and executors both read and write: ``spark.checkpoint.dir``, or a temporary folder where the master is local."""
    global _own_folder
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if _own_folder is None:
        if not spark.sparkContext.master.startswith("local") or spark.sparkContext.master.startswith("local-cluster"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        _own_folder = tempfile.mkdtemp(prefix="objann-work-")
        atexit.register(shutil.rmtree, _own_folder, ignore_errors=True)
    return f"file://{_own_folder}"


def written(df: DataFrame, name: str) -> DataFrame:
    """``df`` written to the work folder and read back: lineage is cut, and a lost executor loses nothing."""
    path = f"{work_folder(df.sparkSession)}/objann-search/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def read_any(spark: SparkSession, path: str, fmt: str, schema: str, **options) -> DataFrame:
    """A JSON, CSV, ORC, text or Parquet source with a declared schema."""
    return spark.read.schema(schema).options(**options).format(fmt).load(path)


def write_report(df: DataFrame, path: str, fmt: str = "csv") -> None:
    writer = df.write.mode("overwrite")
    (writer.option("header", True) if fmt == "csv" else writer).format(fmt).save(path)
