"""Shared plumbing of the training-data operators: lineage cuts, global numbering, Arrow mapping."""

from __future__ import annotations

import contextlib
import ctypes
import gc
from collections.abc import Callable, Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import ensure_checkpoint_dir, ship

#: Java pattern of one word as the size and shingle contracts define it (ASCII white space splits).
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def free_name(df: DataFrame, wish: str) -> str:
    """A column name that df does not have, whatever the case of its letters."""
    taken = {c.lower() for c in df.columns}
    while wish.lower() in taken:
        wish += "_"
    return wish


def cut(df: DataFrame) -> DataFrame:
    """Materialise in the shared folder: lost executors can't take it along, and later reads are stable."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def numbered(df: DataFrame, order: list[Column], name: str) -> DataFrame:
    """Dense global 0-based index in the given order, without sending all rows through one task.

    Range partitions are sorted locally; only one count per partition is summed up centrally.
    """
    local = cut(
        df.repartitionByRange(*order)
        .sortWithinPartitions(*order)
        .withColumn("_pid", F.spark_partition_id())
        .withColumn("_lid", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)))
    )
    before = Window.orderBy("_pid").rowsBetween(Window.unboundedPreceding, -1)
    starts = local.groupBy("_pid").agg(F.count(F.lit(1)).alias("_n")).select("_pid", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start"))
    return local.join(F.broadcast(starts), "_pid").withColumn(name, F.col("_start") + F.col("_lid")).drop("_pid", "_lid", "_start")


def slices(batch: pa.RecordBatch, column: str, limit: int) -> Iterator[pa.RecordBatch]:
    """Cut a batch so that no piece holds much more than limit bytes in one text column (a row is never split)."""
    sizes = pc.binary_length(batch.column(column)).to_pylist()
    first = total = 0
    for i, n in enumerate(sizes):
        total += n or 0
        if total >= limit:
            yield batch.slice(first, i + 1 - first)
            first, total = i + 1, 0
    if first < batch.num_rows:
        yield batch.slice(first)


def release(spark: SparkSession) -> None:
    """Lets Spark's cleaner delete the shuffle files of finished plans now, not when the driver happens to collect its garbage."""
    gc.collect()
    spark._jvm.System.gc()


def trim() -> None:
    """Gives freed memory back to the system, so a reused Python worker doesn't carry one stage's peak into the next."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # other C libraries have no such call
        ctypes.CDLL(None).malloc_trim(0)


def trimmed(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A task's function that trims memory when its input ends."""

    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        trim()

    return whole


def map_batches(df: DataFrame, make: Callable[[], Callable[[pa.RecordBatch], pa.RecordBatch]], schema: str, column: str, limit: int = 8 << 20) -> DataFrame:
    """mapInArrow over bounded pieces. make() runs once per task and returns the piece-wise function."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        step = make()
        for batch in batches:
            for piece in slices(batch, column, limit):
                yield step(piece)

    return df.mapInArrow(trimmed(run), schema)


def utf8(column: pa.Array) -> list[bytes]:
    """The column's texts as UTF-8 bytes, null as empty, without making Python strings."""
    return pc.fill_null(column.cast(pa.binary()), b"").to_pylist()
