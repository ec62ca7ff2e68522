"""Helpers for operators that run Python over Arrow batches."""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from eventpulse.plans.scratch import ship

#: Characters of text that are worked on at once, whatever the size of the Arrow batches.
SLICE_CHARS = 4_000_000


def map_batches(df: DataFrame, fn: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]], schema: StructType | str) -> DataFrame:
    """``df.mapInArrow`` with this package importable on the workers, which give back their memory after each task."""
    ship(df.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from fn(batches)
        finally:
            release()

    return df.mapInArrow(run, schema)


def release() -> None:
    """Return memory that Arrow and the C library keep for later: idle workers stay beside the JVM for the next stage."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # the GNU library has it
    if trim:
        trim(0)


def slices(batch: pa.RecordBatch, text: str, most: int = SLICE_CHARS) -> Iterator[pa.RecordBatch]:
    """Consecutive parts of a batch, each of about ``most`` bytes of text, of one row at least."""
    col = batch.column(text)
    if col.nbytes <= most or batch.num_rows <= 1:
        yield batch
        return
    start = size = 0
    for i, n in enumerate(x.as_py() or 0 for x in pc.binary_length(col)):
        if size and size + n > most:
            yield batch.slice(start, i - start)
            start, size = i, 0
        size += n
    if start < batch.num_rows:
        yield batch.slice(start)


def text_of(df: DataFrame, *cols: str, text: str = "text") -> DataFrame:
    """The named columns and the text, null texts as empty ones."""
    cols = [F.col(c).cast("long").alias(c) if c == "doc_id" else F.col(c) for c in cols]
    return df.select(*cols, F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"))
