"""Tables in the folder that all executors share."""

from __future__ import annotations

import atexit
import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``; where that is unset and all executors are threads of one machine (tests), one of our own."""
    if not (found := spark.conf.get("spark.checkpoint.dir", None)):
        context = spark.sparkContext
        if not (found := context.getCheckpointDir()):
            if not re.fullmatch(r"local(\[.*\])?", context.master):
                raise RuntimeError(f"set spark.checkpoint.dir to a folder that all executors of {context.master} share")
            context.setCheckpointDir(tempfile.mkdtemp(prefix="keyloom-"))
            found = context.getCheckpointDir()
    return found.rstrip("/")


def _files(spark: SparkSession, path: str):
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


def remove(spark: SparkSession, path: str) -> None:
    files, where = _files(spark, path)
    files.delete(where, True)


def is_folder(spark: SparkSession, path: str) -> bool:
    files, where = _files(spark, path)
    return files.getFileStatus(where).isDirectory()


def is_there(spark: SparkSession, path: str) -> bool:
    files, where = _files(spark, path)
    return files.exists(where)


def folders(spark: SparkSession, path: str) -> list[str]:
    """Names of the folders in a folder; none if that isn't there."""
    files, where = _files(spark, path)
    return [f.getPath().getName() for f in files.listStatus(where) if f.isDirectory()] if files.exists(where) else []


def remove_at_exit(spark: SparkSession, path: str) -> None:
    atexit.register(_at_exit, spark, path)


def written(df: DataFrame, name: str) -> tuple[DataFrame, str]:
    """Writes ``df`` as Parquet into the shared folder and reads it again: lineage ends there and lost executors cost nothing."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/keyloom-{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    remove_at_exit(spark, path)
    return spark.read.schema(df.schema).parquet(path), path


def _at_exit(spark: SparkSession, path: str) -> None:
    try:
        remove(spark, path)
    except Exception:  # noqa: BLE001  the session may be gone by then; the folder is scratch space
        pass
