"""Helpers that the training-data operators share."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

# Workers share an executor's memory with the JVM: blocks over 1 MB go back to the system as soon as they are freed (-3 and -1 are
# glibc's numbers of the thresholds for mapping and trimming; other C libraries lack the call).
if hasattr(ctypes.CDLL(None), "mallopt"):
    ctypes.CDLL(None).mallopt(-3, 1 << 20)
    ctypes.CDLL(None).mallopt(-1, 1 << 20)
pa.set_memory_pool(pa.system_memory_pool())

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
#: Delimiters become spaces and A-Z lower case; every byte of a non-ASCII character is kept.
WORD_TABLE = bytes(b + 32 if 65 <= b <= 90 else b if b >= 128 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))


def pick(df: DataFrame, *names: str) -> DataFrame:
    """The named columns alone, found by exact name, so that further columns whose names differ only by case (or repeat) do no harm."""
    at = df.columns
    if missing := [n for n in names if n not in at]:
        raise ValueError(f"columns {missing} are missing from {at}")
    numbered = df.toDF(*[f"_{i}" for i in range(len(at))])
    return numbered.select(*[F.col(f"_{at.index(n)}").alias(n) for n in names])


def without(df: DataFrame, *names: str) -> DataFrame:
    """All columns but those of the given names in any case: an operator's own output columns take their place."""
    gone = {n.lower() for n in names}
    at = [i for i, c in enumerate(df.columns) if c.lower() not in gone]
    return df if len(at) == len(df.columns) else df.toDF(*[f"_{i}" for i in range(len(df.columns))]).select(*[F.col(f"_{i}").alias(df.columns[i]) for i in at])


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir; a temporary one only where that is unset, as in tests."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        found = tempfile.mkdtemp(prefix="rambler-")
        spark.sparkContext.setCheckpointDir(found)
    return found


def written(df: DataFrame) -> DataFrame:
    """`df` stored as Parquet in the shared folder and read again: its lineage ends there, and what reads it twice computes it once.

    The folder is scratch space; its owner clears it (a lost executor never takes these files along)."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


@contextmanager
def small_batches(spark: SparkSession, rows: int = 1024):
    """Within it, executed plans hand at most `rows` rows at a time to Python, which bounds what a batch of long texts takes. The session's setting comes back."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, str(min(rows, int(before)) if int(before) > 0 else rows))
    try:
        yield
    finally:
        spark.conf.set(name, before)


def byte_texts(column: pa.Array | pa.ChunkedArray) -> list[bytes]:
    """UTF-8 bytes of a string column; null becomes empty."""
    return [b or b"" for b in column.cast(pa.binary()).to_pylist()]


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


_HELD: dict[str, object] = {}


def give_back() -> None:
    """Hands what this process has freed back to the system: workers live on from stage to stage, and their peaks would add up."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def release() -> None:
    """Frees the object that a worker holds for a stage."""
    _HELD.clear()
    give_back()


def per_worker(token: str, build):
    """What `build` makes, once for each token in a worker process. Workers serve many stages: only the latest token's object is kept."""
    if token not in _HELD:
        _HELD.clear()
        give_back()
        _HELD[token] = build()
    return _HELD[token]
