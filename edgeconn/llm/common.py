"""What the operators of this subpackage share."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes of text that a Python worker handles at once.
BLOCK_BYTES = 1 << 20
#: Bytes of an Arrow batch between Spark and a Python worker.
BATCH_BYTES = 4 << 20
_BATCH = "spark.sql.execution.arrow.maxBytesPerBatch"


def small_batches(spark: SparkSession) -> None:
    """Bound Arrow batches by bytes where the session has no stricter bound:
    ten thousand rows, Spark's only bound else, of long texts or large sets are
    too much for the JVM's buffers and the worker's together."""
    held = spark.conf.get(_BATCH, None)
    if held is None or not 0 < _bytes(held) <= BATCH_BYTES:
        spark.conf.set(_BATCH, str(BATCH_BYTES))


def _bytes(size: str) -> int:
    """Bytes of a size as Spark writes it: 1024, 64b, 64k, 4MB, 1g."""
    number = size.strip().lower().removesuffix("b")
    scale = {"k": 10, "m": 20, "g": 30, "t": 40}.get(number[-1:], 0)
    return int(number.rstrip("kmgt")) << scale


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A given table, by a path that Spark's reader opens."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def text_or_empty(col: str | Column) -> Column:
    return F.coalesce(F.col(col) if isinstance(col, str) else col, F.lit(""))


def held_out(doc_id: Column, folds: int) -> Column:
    """True where crc32 of the id's decimal text leaves no remainder."""
    return F.crc32(doc_id.cast("string").cast("binary")) % folds == 0


def schema_of(df: DataFrame) -> str:
    return ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields)


def keep_rows(docs: DataFrame, make, text: str = "text", limit: int = BLOCK_BYTES) -> DataFrame:
    """Rows of ``docs``, all columns, that pass a test of their whole texts.

    ``make()`` runs once per task and gives a function from a list of texts
    (nulls as empty) to a list of booleans. Nothing is shuffled.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        test = make()
        for b in blocks(batches, text, limit):
            yield b.filter(pa.array(test([t or "" for t in b.column(text).to_pylist()]), pa.bool_()))

    return docs.mapInArrow(run, schema_of(docs))


def blocks(batches: Iterator[pa.RecordBatch], text: str = "text", limit: int = BLOCK_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut record batches into slices of about ``limit`` bytes of text each.

    A single text longer than the limit makes a slice of its own; no row is
    split or dropped.
    """
    import numpy as np
    import pyarrow.compute as pc

    for batch in batches:
        n = batch.num_rows
        if not n:
            continue
        sizes = pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        ends = np.cumsum(sizes)
        start = 0
        while start < n:
            base = ends[start - 1] if start else 0
            stop = max(start + 1, int(np.searchsorted(ends, base + limit, "right")))
            yield batch.slice(start, stop - start)
            start = stop
    pa.default_memory_pool().release_unused()  # workers are kept for other stages
