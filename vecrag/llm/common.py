"""Shared helpers of the training-data operators."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import re
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that a Python operator holds decoded at once (a longer single text is its own slice).
SLICE_BYTES = 1 << 19
#: Bytes and rows of an Arrow batch.
BATCH_BYTES, BATCH_ROWS = 4 << 20, 2000


#: What a worker keeps from task to task of one operator; the tasks of others clear it, so that it does not lie beside them.
KEPT: dict = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given parquet tables, by a path that only Spark has to understand."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def held_out(doc_id: str = "doc_id") -> Column:
    """Rows that no model may learn from: crc32 of the id's decimal text, modulo 4, is 2."""
    return F.coalesce(F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(4)) == 2, F.lit(False))


def checkpointed(df: DataFrame) -> DataFrame:
    """Cut the lineage through the shared folder the cluster names in spark.checkpoint.dir."""
    _checkpoint_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def _checkpoint_folder(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir. Where that is unset, a single machine gets one of its own; a cluster must name one."""
    sc = spark.sparkContext
    if sc.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        if named is None and not sc.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(named or tempfile.mkdtemp(prefix="ckpt"))
    return sc.getCheckpointDir()


def shared_folder(spark: SparkSession) -> str:
    """A new folder in the shared one, for tables that a job writes and reads again."""
    return f"{_checkpoint_folder(spark)}/{uuid.uuid4().hex}"


def numbered(df: DataFrame) -> tuple[DataFrame, Callable[[DataFrame], DataFrame]]:
    """The table with its columns named c0, c1, .., and what gives them their own names back: no helper column can clash."""
    names = df.columns
    given = df.select(*(F.col(f"`{c.replace('`', '``')}`").alias(f"c{i}") for i, c in enumerate(names)))
    return given, lambda out: out.select(*(F.col(f"c{i}").alias(c) for i, c in enumerate(names)))


def slices(batch: pa.RecordBatch, column: str, most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut a batch so that each piece has about `most` bytes in `column`, whole rows only."""
    if not batch.num_rows:
        return
    sizes = pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False)
    cuts = np.flatnonzero(np.diff(np.cumsum(sizes, dtype=np.int64) // most)) + 1
    edges = [0, *cuts.tolist(), batch.num_rows]
    for a, b in zip(edges, edges[1:], strict=False):
        if b > a:
            yield batch.slice(a, b - a)


def small_batches(spark: SparkSession) -> None:
    """Hold Arrow batches to BATCH_BYTES and BATCH_ROWS from now on: texts are long, and both the JVM and the worker hold a
    whole batch. Settings of the session that are lower stay.
    """
    rows, size = "spark.sql.execution.arrow.maxRecordsPerBatch", "spark.sql.execution.arrow.maxBytesPerBatch"
    if not 0 < int(spark.conf.get(rows)) <= BATCH_ROWS:
        spark.conf.set(rows, BATCH_ROWS)
    number, unit = re.fullmatch(r"(\d+)\s*([a-z]*)", str(spark.conf.get(size)).lower()).groups()
    if int(number) << {"": 0, "b": 0, "k": 10, "kb": 10, "m": 20, "mb": 20, "g": 30, "gb": 30}[unit] > BATCH_BYTES:
        spark.conf.set(size, BATCH_BYTES)


def map_slices(df: DataFrame, column: str, work: Callable[[pa.RecordBatch], pa.RecordBatch], schema: str) -> DataFrame:
    """mapInArrow over bounded slices of each batch."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        clear_kept()
        for batch in batches:
            for piece in slices(batch, column):
                yield work(piece)
        release()

    small_batches(df.sparkSession)
    return df.mapInArrow(run, schema)


def clear_kept() -> None:
    if KEPT:
        KEPT.clear()
        release()


def release() -> None:
    """Give memory that a task has freed back to the system: its worker may wait idle beside other stages."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # not glibc
        ctypes.CDLL(None).malloc_trim(0)


def sampled_ids(df: DataFrame, doc_id: str, share: Column, seed: int) -> Column:
    """True for a share of the ids, fixed by (seed, id) alone: the same rows in every run and layout."""
    return F.pmod(F.xxhash64(F.lit(seed), F.col(doc_id)), F.lit(1 << 30)) < share * F.lit(1 << 30)


def sampled_text(text: Column, key: Column, most: int, windows: int, seed: int) -> Column:
    """A text of up to `most` characters as it is; of a longer one `windows` windows, `most` characters together.

    The text is cut into as many equal stretches, and each gives one window at a place hashed from (seed, key, window).
    """
    width, n = most // windows, F.char_length(text)
    stretch = F.floor(n / windows).cast("int")
    start = lambda k: F.lit(k) * stretch + F.pmod(F.xxhash64(F.lit(seed), key, F.lit(k)), F.greatest(stretch - width, F.lit(0)) + 1).cast("int") + 1
    return F.when(n > most, F.concat_ws("\n", *(F.substr(text, start(k), F.lit(width)) for k in range(windows)))).otherwise(text)
