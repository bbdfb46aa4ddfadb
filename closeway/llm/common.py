"""Shared pieces of the corpus operators."""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"


def fold(id_col: str, n: int) -> Column:
    """crc32 of the id as text, modulo n; a null id counts as the empty text."""
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("")).cast("binary")) % n


def text_rows(batches: Iterator[pa.RecordBatch], column: str = "text") -> Iterator[tuple[pa.RecordBatch, list]]:
    """Each Arrow batch with its texts as UTF-8 bytes (None for null), not decoded."""
    for batch in batches:
        if batch.num_rows:
            yield batch, batch.column(batch.schema.get_field_index(column)).cast(pa.binary()).to_pylist()


def only(df: DataFrame, **names: str) -> DataFrame:
    """Only the named columns, under the operator's own names, so that further columns can't clash."""
    return df.select(*[F.col(f"`{have}`").alias(want) for want, have in names.items()])


#: Bytes in an Arrow batch where many stages share the executors.
BATCH_BYTES = 4 << 20


def steady(spark: SparkSession, most: int = BATCH_BYTES) -> None:
    """Bound the session's Arrow batches by bytes: JVM and workers then hold few texts at a time, however long they are.

    The setting may be changed in a running session; a lower one is kept.
    """
    key = "spark.sql.execution.arrow.maxBytesPerBatch"
    size = spark.sparkContext._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(spark.conf.get(key))
    if size <= 0 or size > most:
        spark.conf.set(key, str(most))


def hand_back() -> None:
    """Give a worker's freed memory back to the machine: workers outlive their tasks and the next stage needs room."""
    gc.collect()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library keeps its own pools
        return
