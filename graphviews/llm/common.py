"""Helpers that the operators share: reading tables, shared-folder tables, word rules."""

from __future__ import annotations

import ctypes
import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: The ASCII characters that the word rules split at.
BLANKS = "\x20\x09\x0a\x0b\x0c\x0d"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = "abcdefghijklmnopqrstuvwxyz"

_ALNUM = set(b"0123456789" + UPPER.encode() + LOWER.encode())
#: Byte table of the alphanumeric rule: A-Z lower-cased, every other ASCII byte but 0-9a-z a blank.
ALNUM_TABLE = bytes(
    (c + 32 if 65 <= c <= 90 else c) if c in _ALNUM or c >= 128 else 32 for c in range(256)
)
#: Byte table that only lower-cases A-Z; bytes.split() then splits at exactly BLANKS.
LOWER_TABLE = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))


def alnum_words(text: bytes | None) -> list[bytes]:
    """Runs of ASCII letters and digits and of non-ASCII characters, A-Z lower-cased."""
    return text.translate(ALNUM_TABLE).split() if text else []


def blank_words(text: bytes | None) -> list[bytes]:
    """Runs without ASCII white space, A-Z lower-cased."""
    return text.translate(LOWER_TABLE).split() if text else []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_memory: list = [None, None]


def worker_memory(owner: str, make):
    """What one operator remembers in a worker process from task to task; another owner's request drops it."""
    if _memory[0] != owner:
        _memory[:] = [None, None]
        _memory[:] = [owner, make()]
    return _memory[1]


def returned_memory() -> None:
    """Give freed memory of a worker process back to the system, where its C library can."""
    gc.collect()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def bounded_batches(df: DataFrame, rows: int = 1000, size: int = 64 << 20) -> DataFrame:
    """df, in a session that hands Python at most so many rows or bytes of texts at once (one row at least)."""
    for name, most in (("spark.sql.execution.arrow.maxRecordsPerBatch", rows), ("spark.sql.execution.arrow.maxBytesPerBatch", size)):
        set_ = int(str(df.sparkSession.conf.get(name, str(most + 1))).rstrip("b"))
        if not 0 < set_ <= most:
            df.sparkSession.conf.set(name, most)
    return df


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; where the session names none, a temporary one on a local master and an error on a cluster."""
    where = spark.conf.get("spark.checkpoint.dir", None)
    if where is None:
        context = spark.sparkContext
        where = context.getCheckpointDir()
        if where is None:
            if not context.master.startswith("local"):
                raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
            context.setCheckpointDir(tempfile.mkdtemp(prefix="graphviews-"))
            where = context.getCheckpointDir()
    return where.rstrip("/")


def scratch_path(spark: SparkSession, label: str) -> str:
    """A new path in the shared folder, removed when the session ends."""
    path = f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}"
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(target)
    return path


def stored(df: DataFrame, label: str) -> DataFrame:
    """Write df as a table in the shared folder and read it back: lineage ends there, any executor can reread it."""
    spark = df.sparkSession
    path = scratch_path(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def drop_stored(df: DataFrame) -> None:
    """Remove the files of a stored() table that no later plan reads."""
    spark = df.sparkSession
    jvm = spark.sparkContext._jvm
    conf = spark.sparkContext._jsc.hadoopConfiguration()
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        target = jvm.org.apache.hadoop.fs.Path(folder)
        target.getFileSystem(conf).delete(target, True)


def held_out(doc_id: str, modulus: int, remainder: int):
    """Column: crc32 of the decimal id, modulo, equals the remainder; null ids hash as the empty text."""
    crc = F.crc32(F.coalesce(F.col(doc_id).cast("string"), F.lit("")).cast("binary"))
    return crc % modulus == remainder


def shielded(df: DataFrame, added: list[str]) -> tuple[DataFrame, dict[str, str]]:
    """df with columns renamed that an operator would add itself, and how to name them back."""
    back = {f"{c}__input": c for c in df.columns if c in added}
    return df.withColumnsRenamed({v: k for k, v in back.items()}), back
