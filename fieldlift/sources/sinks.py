"""Sinks for entities: one callable for each target, all taking (entity name, DataFrame)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame

Sink = Callable[[str, DataFrame], None]


def file_sink(folder: str, kind: str = "parquet", partition: str | None = "source") -> Sink:
    """parquet, json, csv or xml files under folder/entity, partitioned by source. Overwriting makes reruns idempotent."""

    def write(name: str, df: DataFrame) -> None:
        w = df.write.mode("overwrite")
        if kind == "xml":
            w.format("xml").option("rowTag", name).option("rootTag", f"{name}_list").save(f"{folder}/{name}")
            return
        w = w.partitionBy(partition) if partition and partition in df.columns else w
        w = w.option("header", True) if kind == "csv" else w
        w.format(kind).save(f"{folder}/{name}")

    return write


def jdbc_sink(url: str, properties: dict[str, str], batch_rows: int = 5000, mode: str = "append") -> Sink:
    """Pooled batch inserts, one transaction a task."""
    return lambda name, df: df.write.jdbc(url, name, mode, {**properties, "batchsize": str(batch_rows)})


def table_sink(bucket: str = "doc_id", buckets: int = 64) -> Sink:
    """Tables bucketed by document, so checks by document need no shuffle."""
    return lambda name, df: df.write.mode("overwrite").bucketBy(buckets, bucket).sortBy(bucket).saveAsTable(name)


def noop_sink() -> Sink:
    return lambda name, df: df.write.format("noop").mode("overwrite").save()
