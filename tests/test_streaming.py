"""Streaming flows run to the end of what is there; a second run adds nothing."""

from pyspark.sql import functions as F

from fieldlift.operators import archive
from fieldlift.streaming import flows


def items(spark, data):
    a = archive.archive_items(spark.read.parquet(f"{data}/pages.parquet")).select("url", "sha256", "source", F.col("item_id").cast("int").alias("i"))
    return a.withColumn("captured_at", F.timestamp_seconds(F.lit(1_000_000_000) + F.col("i") * 60))


def test_incremental_runs_are_idempotent(spark, data, tmp_path):
    df = items(spark, data)
    df.union(df).coalesce(1).write.parquet(f"{tmp_path}/in")
    seen = []
    for _ in range(2):
        stream = flows.incremental_archive(flows.file_stream(spark, f"{tmp_path}/in", df.schema))
        flows.run_available(stream, f"{tmp_path}/ck", lambda b, _: seen.append(b.count()))
    assert sum(seen) == df.select("url", "sha256").distinct().count()


def test_changed_content(spark, tmp_path):
    rows = spark.createDataFrame([("u", "a", 1), ("u", "a", 2), ("u", "b", 3), ("v", "c", 1)], "url string, sha256 string, t int").withColumn("captured_at", F.timestamp_seconds("t"))
    rows.coalesce(1).write.parquet(f"{tmp_path}/in")
    out = []
    stream = flows.changed_content(flows.file_stream(spark, f"{tmp_path}/in", rows.schema))
    flows.run_available(stream, f"{tmp_path}/ck", lambda b, _: out.extend(map(tuple, b.collect())))
    assert sorted(out) == [("u", "a", "new"), ("u", "b", "changed"), ("v", "c", "new")]


def test_volume_counts(spark, data, tmp_path):
    df = items(spark, data)
    df.coalesce(1).write.parquet(f"{tmp_path}/in")
    got = []
    stream = flows.crawl_volume(flows.file_stream(spark, f"{tmp_path}/in", df.schema), size="1 hour")
    flows.run_available(stream, f"{tmp_path}/ck", lambda b, _: got.extend(b.collect()), "update")
    assert sum(r.n for r in got) == df.count()
