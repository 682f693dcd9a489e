"""Helpers shared by the training-data operators.

Text leaves the JVM in Arrow batches and is handled as bytes: ``bytes.split()``
splits on exactly 09-0D and 20, and ``bytes.lower()`` folds exactly A-Z, which
are the tokenisation and case rules of all operators here.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

#: Rows of one Arrow batch: with 2 MB texts a batch stays within 2 GB of offsets.
BATCH_ROWS = 1000
#: Bytes of text that are worked on together.
BLOCK_BYTES = 24 << 20


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share; one of our own only where none is set and all of Spark runs on this machine."""
    base = spark.conf.get("spark.checkpoint.dir", None) or None
    if base is None:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = tempfile.mkdtemp(prefix="attention-engine-")
        spark.conf.set("spark.checkpoint.dir", base)
    return base.rstrip("/")


def fresh_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def materialise(df: DataFrame, name: str) -> DataFrame:
    """Cut the lineage with a table in the shared folder."""
    path = fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def bound_batches(spark: SparkSession) -> None:
    """Keep Arrow batches of long texts small; a runtime setting of the session."""
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", str(BATCH_ROWS))


def byte_list(column: pa.Array) -> list:
    """The values of a text column as bytes, null as empty."""
    return [b"" if x is None else x for x in column.cast(pa.binary()).to_pylist()]


def blocks(batches: Iterator[pa.RecordBatch], text: str = "text", limit: int = BLOCK_BYTES) -> Iterator[pa.Table]:
    """Arrow batches joined until they hold ``limit`` bytes."""
    held, size = [], 0
    for batch in batches:
        if batch.num_rows == 0:
            continue
        held.append(batch)
        size += batch.nbytes
        if size >= limit:
            yield pa.Table.from_batches(held).combine_chunks()
            held, size = [], 0
    if held:
        yield pa.Table.from_batches(held).combine_chunks()


def one(column: pa.ChunkedArray) -> pa.Array:
    """The single chunk of a combined column."""
    return column.chunk(0) if column.num_chunks == 1 else column.combine_chunks()


def intern(words: list, table: dict) -> np.ndarray:
    """Numbers of the words; ``table`` grows by those it lacks."""
    for w in words:
        if w not in table:
            table[w] = len(table)
    return np.fromiter(map(table.__getitem__, words), np.int64, len(words))


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit mixer over an unsigned array."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x
