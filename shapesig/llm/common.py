"""Helpers shared by the operators: checkpoints, table reads, blocks of Arrow rows."""

from __future__ import annotations

import ctypes
import math
import tempfile
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: White space of every word rule here, as a Java and RE2 character class.
SPACE = r"[\x20\x09-\x0D]"
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cut(df: DataFrame) -> DataFrame:
    """Cut the lineage with a checkpoint in the folder the cluster shares.

    The folder is the session's ``spark.checkpoint.dir``; a temporary one is
    used only for a local master (tests), never on a cluster.
    """
    spark = df.sparkSession
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        at = spark.conf.get("spark.checkpoint.dir", None)
        if at is None:
            if not sc.master.startswith("local[") and sc.master != "local":
                raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
            at = tempfile.mkdtemp(prefix="ckpt-")
        sc.setCheckpointDir(at)
    return df.checkpoint()


#: Bytes of an Arrow batch that goes to a Python worker.
BATCH_BYTES = 4 << 20


def in_arrow(df: DataFrame, run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: str | T.StructType) -> DataFrame:
    """``mapInArrow`` in batches of ``BATCH_BYTES``, whatever the rows' size; the session keeps that setting.

    At the end of a task its worker gives freed memory back to the system, for
    workers are kept and stages add up.
    """
    df.sparkSession.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))

    def lean(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        pa.default_memory_pool().release_unused()
        if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
            trim(0)

    return df.mapInArrow(lean, schema)


#: Rows of ids that a broadcast may hold: 8 MB of values.
MOST_IDS = 500_000


def few_ids(ids: DataFrame) -> DataFrame:
    """A settled table of ids, marked for broadcast if it was counted to be small; otherwise the join shuffles both sides."""
    return F.broadcast(ids) if ids.limit(MOST_IDS + 1).count() <= MOST_IDS else ids


def text_bytes(docs: DataFrame, column: str = "text") -> int:
    """UTF-8 bytes of a text column over all rows; used to size blocks, never to skip rows."""
    return int(docs.agg(F.sum(F.octet_length(column)).alias("b")).first()["b"] or 0)


def block_count(total_bytes: int, most: int = 100_000) -> int:
    """Blocks for ``total_bytes`` of text: their size grows with the root of the total, 64 MB at most.

    Blocks times buckets then stays near the total in 64 KB units, so packed
    exchanges neither shatter at 100 TB nor hold more than a block in memory.
    """
    size = min(64 << 20, max(1 << 20, 256 * math.isqrt(max(1, total_bytes))))
    return max(8, min(most, -(-total_bytes // size)))


def rows_of(batch: pa.RecordBatch, column: str, most_bytes: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Slices of a batch with about ``most_bytes`` in ``column`` each, one row at least."""
    sizes = np.diff(offsets_of(batch.column(batch.schema.get_field_index(column))))
    start = 0
    while start < batch.num_rows:
        end = start + max(1, int(np.searchsorted(np.cumsum(sizes[start:]), most_bytes, side="right")))
        yield batch.slice(start, end - start)
        start = end


def offsets_of(strings: pa.Array) -> np.ndarray:
    wide = pa.types.is_large_string(strings.type) or pa.types.is_large_binary(strings.type)
    kind = np.int64 if wide else np.int32
    if len(strings) == 0:
        return np.zeros(1, np.int64)
    return np.frombuffer(strings.buffers()[1], kind, len(strings) + 1, strings.offset * kind().itemsize).astype(np.int64)
