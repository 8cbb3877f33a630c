"""Cutting the lineage of what an iteration carries on."""

from __future__ import annotations

import tempfile
import uuid

import pyarrow.fs
from pyspark.sql import DataFrame


def shared_folder(spark) -> str:
    """The folder that all executors share: ``spark.checkpoint.dir``. In local mode alone, one is made where that is unset."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if folder is None and not context.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="checkpoints-"))
    return context.getCheckpointDir()


def settle(df: DataFrame) -> DataFrame:
    """A reliable checkpoint: survives lost executors, and later plans start from it."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def written(df: DataFrame) -> DataFrame:
    """As ``settle``, by a compressed table: less disk, and no trace of the old plan's partitioning in later ones, which
    joins of a checkpoint with itself would make longer each time."""
    return placed(df)[0]


def placed(df: DataFrame) -> tuple[DataFrame, str]:
    """As ``written``, with the table's folder, for ``dropped``."""
    path = fresh_folder(df.sparkSession)
    df.write.option("compression", "zstd").parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path), path


def fresh_folder(spark) -> str:
    return f"{shared_folder(spark)}/{uuid.uuid4().hex}"


def opened(folder: str) -> tuple[pyarrow.fs.FileSystem, str]:
    """File system and path of a folder that Python opens without Spark; raises where it cannot."""
    local = folder.startswith("file:") and not folder.startswith("file://")
    return pyarrow.fs.FileSystem.from_uri(f"file://{folder[5:]}" if local else folder)


def plainly_shared(spark) -> bool:
    """Whether Python opens the shared folder without Spark."""
    try:
        files, path = opened(shared_folder(spark))
        return files.get_file_info(path).type == pyarrow.fs.FileType.Directory
    except (OSError, ValueError, NotImplementedError):
        return False


def part_files(folder: str, column: str, value: int) -> list:
    """The open parquet files of one part of a table that is partitioned by ``column``, in order of name."""
    files, path = opened(folder)
    own = files.get_file_info(pyarrow.fs.FileSelector(f"{path}/{column}={value}", allow_not_found=True))
    return [files.open_input_file(x.path) for x in sorted(own, key=lambda x: x.path) if x.path.endswith(".parquet")]


def dropped(spark, *folders: str) -> None:
    """Delete folders within the shared one that nothing reads any more, and let Spark forget the files of old shuffles."""
    if not folders:
        return
    context = spark.sparkContext
    for folder in folders:
        if not folder.startswith(context.getCheckpointDir()):
            raise ValueError(f"{folder} is not in the shared folder")
        path = context._jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(context._jsc.hadoopConfiguration()).delete(path, True)
    swept(spark)


def swept(spark) -> None:
    """Shuffle files are deleted when their plans are: the driver's JVM is asked to collect them."""
    spark.sparkContext._jvm.System.gc()
