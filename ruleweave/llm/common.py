"""Helpers that the operators of this subpackage share: tables, the shared folder, group counts."""

from __future__ import annotations

import contextlib
import ctypes
import math
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

GROUP_BYTES, MAX_GROUP_BYTES, MIN_ROW_BYTES = 8 << 20, 64 << 20, 512


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """A new folder that driver and executors share: below spark.checkpoint.dir or the context's checkpoint folder. Only a local session that has
    neither (as in tests) gets one below the temp folder."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        root = f"{tempfile.gettempdir()}/checkpoints"
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(root)
    return f"{root.rstrip('/')}/ruleweave-{uuid.uuid4().hex}"


def staged(df: DataFrame, codec: str = "zstd") -> DataFrame:
    """Writes df as Parquet into the shared folder and reads it back: lineage ends here and lost executors lose nothing."""
    path = shared_dir(df.sparkSession)
    df.write.option("compression", codec).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def checkpointed(df: DataFrame) -> DataFrame:
    """checkpoint() in the shared folder; the folder is set here only where the session has none."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


def text_bytes(df: DataFrame, col: str = "text") -> int:
    """Bytes of all texts: one narrow scan, one number to the driver."""
    return df.agg(F.sum(F.octet_length(col))).first()[0] or 0


def small_batches(spark: SparkSession, rows: int = 1000) -> None:
    """Arrow batches of at most `rows` rows in this session (a runtime setting): texts are long, and a worker holds a batch several times over."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(key)) <= rows:
        spark.conf.set(key, str(rows))


def lean(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """A mapInArrow function that hands freed memory back when its task ends: workers outlive tasks, and the next stage needs the room."""

    def go(batches):
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            with contextlib.suppress(OSError, AttributeError):  # where the C library has no such call
                ctypes.CDLL(None).malloc_trim(0)

    return go


def group_count(total_bytes: int) -> int:
    """Number of groups of documents: about 8 MB of text each while the corpus is small, up to 64 MB when it is huge.

    Groups and buckets exchange one row per pair, so groups grow with the square root of the corpus, which keeps a row's payload at some
    hundred bytes up to 8 TB; beyond that the bound on a worker's memory (about 100 bytes a word, so 1 GB) goes first.
    """
    per = min(MAX_GROUP_BYTES, max(GROUP_BYTES, math.isqrt(MIN_ROW_BYTES * max(1, total_bytes))))
    return max(1, math.ceil(total_bytes / per))


def shuffle_width(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))
