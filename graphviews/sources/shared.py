"""Tables in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where it is not set, a temporary folder on a local master and an error on a cluster."""
    where = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if where is None:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="graphviews-"))
        where = spark.sparkContext.getCheckpointDir()
    return where.rstrip("/")


def files(spark: SparkSession, path: str):
    """The file system behind a path, and the path as it knows it."""
    target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), target


def new_path(spark: SparkSession, label: str) -> str:
    """A path that no one uses, removed when the session ends."""
    path = f"{shared_folder(spark)}/{label}-{uuid.uuid4().hex}"
    fs, target = files(spark, path)
    fs.deleteOnExit(target)
    return path


@dataclass
class Run:
    """A stored table: its rows' relation, their number, and its folder."""

    df: DataFrame
    rows: int
    path: str
    marked: int = 0  # rows that met the condition counted besides


def run_of(df: DataFrame, label: str, folder: str | None = None, mark: Column | None = None) -> Run:
    """df written as a table, in the folder if one is given (and left there at the session's end); rows are counted by the write itself."""
    path = f"{folder}/{label}-{uuid.uuid4().hex}" if folder else new_path(df.sparkSession, label)
    counted = Observation()
    marked = F.count_if(mark) if mark is not None else F.count_if(F.lit(False))
    df.observe(counted, F.count(F.lit(1)).alias("n"), marked.alias("marked")).write.parquet(path)
    back = df.sparkSession.read.schema(df.schema).parquet(path)
    if "n" in (got := counted.get):
        return Run(back, got["n"], path, got["marked"])
    # the plan turned out to be empty, and the counts with it
    return Run(back, back.count(), path, back.where(mark).count() if mark is not None else 0)


def stored(df: DataFrame, label: str) -> DataFrame:
    """df written as a table and read back: lineage ends, lost executors cost a reread."""
    return run_of(df, label).df


def removed(spark: SparkSession, path: str) -> None:
    fs, target = files(spark, path)
    fs.delete(target, True)


def dropped(df: DataFrame) -> None:
    """Remove the files behind a stored table that no later plan reads."""
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        removed(df.sparkSession, folder)
