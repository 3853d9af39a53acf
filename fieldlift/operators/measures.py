"""Measures over loaded databases and over pairings."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.shred import node_table
from .dictionary import _cut


def entry_counts(publications: DataFrame) -> DataFrame:
    return publications.groupBy("source").agg(F.count(F.lit(1)).alias("entries"))


def row_counts(entities: dict[str, DataFrame]) -> DataFrame:
    """(source, entity, rows), with 0 for a table a source left empty."""
    parts = [df.groupBy("source").agg(F.count(F.lit(1)).alias("rows")).select("source", F.lit(n).alias("entity"), "rows") for n, df in entities.items()]
    found = _cut(reduce(DataFrame.unionByName, parts))
    names = found.sparkSession.createDataFrame([(n,) for n in entities], "entity string")
    return found.select("source").distinct().join(F.broadcast(names), F.lit(True)).join(found, ["source", "entity"], "left").withColumn("rows", F.coalesce("rows", F.lit(0)).cast("long"))


def logical_sizes(entities: dict[str, DataFrame]) -> DataFrame:
    """(source, bytes): size of the rows as JSON text."""
    parts = [df.select("source", F.octet_length(F.to_json(F.struct(*[c for c in df.columns if c != "source"]))).alias("b")) for df in entities.values()]
    return reduce(DataFrame.unionByName, parts).groupBy("source").agg(F.sum("b").cast("long").alias("bytes"))


def stored_sizes(spark: SparkSession, path: str) -> DataFrame:
    """(source, bytes) of files written under source=<name> folders."""
    files = spark.read.format("binaryFile").option("recursiveFileLookup", "true").option("pathGlobFilter", "*.parquet").load(path).select("path", "length")
    return files.groupBy(F.url_decode(F.regexp_extract("path", r"/source=([^/]+)/", 1)).alias("source")).agg(F.sum("length").alias("bytes"))


def bytes_per_entry(sizes: DataFrame, counts: DataFrame) -> DataFrame:
    return sizes.join(counts, "source").withColumn("bytes_per_entry", F.col("bytes") / F.col("entries"))


def occupation(rows: DataFrame) -> DataFrame:
    """(source, entity, rows, r, balanced): a table's share of its database's rows; 1 / tables if all were alike."""
    w = Window.partitionBy("source")
    return rows.withColumns({"r": F.coalesce(F.col("rows") / F.nullif(F.sum("rows").over(w), F.lit(0)), F.lit(0.0)), "balanced": 1.0 / F.count(F.lit(1)).over(w)})


def occupation_skew(occupied: DataFrame) -> DataFrame:
    """(source, skew): population skewness of the ratios of a database."""
    return occupied.groupBy("source").agg(F.skewness("r").alias("skew"))


def occupation_matrix(occupied: DataFrame, entities: list[str]) -> DataFrame:
    return occupied.groupBy("source").pivot("entity", entities).agg(F.first("r"))


def top_k(df: DataFrame, metric: str, k: int = 5) -> DataFrame:
    """The k largest by a metric, ties included, with their rank."""
    return df.orderBy(F.col(metric).desc()).withColumn("rank", F.rank().over(Window.orderBy(F.col(metric).desc()))).filter(F.col("rank") <= k)


def fill_rate(entities: dict[str, DataFrame]) -> DataFrame:
    """(entity, field, filled, total)."""
    parts = []
    for name, df in entities.items():
        fields = [c for c in df.columns if c not in ("id", "doc_id", "source", "lang")]
        counts = df.agg(F.count(F.lit(1)).alias("total"), *[F.count(c).alias(c) for c in fields])
        parts.append(counts.select("total", F.inline(F.array(*[F.struct(F.lit(c).alias("field"), F.col(c).alias("filled")) for c in fields]))).select(F.lit(name).alias("entity"), "field", "filled", "total"))
    return reduce(DataFrame.unionByName, parts)


def score_pairs(found: DataFrame, truth: DataFrame) -> DataFrame:
    """(hits, found, true, precision, recall, f1) over (doc_id, key_id, value) multisets."""
    key = ["doc_id", "key_id", "value"]
    a, b = found.groupBy(*key).agg(F.count(F.lit(1)).alias("f")), truth.groupBy(*key).agg(F.count(F.lit(1)).alias("t"))
    both = a.join(b, key, "full_outer").select(F.coalesce("f", F.lit(0)).alias("f"), F.coalesce("t", F.lit(0)).alias("t"))
    sums = both.agg(F.coalesce(F.sum(F.least("f", "t")), F.lit(0)).alias("hits"), F.coalesce(F.sum("f"), F.lit(0)).alias("found"), F.coalesce(F.sum("t"), F.lit(0)).alias("true"))
    ratio = lambda x, y: F.coalesce(F.col(x) / F.nullif(F.col(y), F.lit(0)), F.lit(0.0))
    out = sums.withColumns({"precision": ratio("hits", "found"), "recall": ratio("hits", "true")})
    return out.withColumn("f1", F.coalesce(2 * F.col("precision") * F.col("recall") / F.nullif(F.col("precision") + F.col("recall"), F.lit(0.0)), F.lit(0.0)))


def text_sizes(entities: dict[str, DataFrame]) -> DataFrame:
    """(source, bytes): bytes of all columns beside the source as UTF-8 text."""
    parts = [df.select("source", reduce(lambda a, b: a + b, [F.coalesce(F.octet_length(F.col(c).cast("string")), F.lit(0)) for c in df.columns if c != "source"]).alias("b")) for df in entities.values()]
    return reduce(DataFrame.unionByName, parts).groupBy("source").agg(F.sum("b").cast("long").alias("bytes"))


def observed(df: DataFrame, **counters: Column) -> tuple[DataFrame, Observation]:
    """df with counters that are measured while it is computed, wherever in a plan it stands."""
    seen = Observation()
    return df.observe(seen, *[c.alias(k) for k, c in counters.items()]), seen


def work_counters(documents: DataFrame, shred: Callable[[DataFrame], DataFrame], evaluate: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """(docs, nodes, results): what went into the parser, came out of it and came out of the evaluation, observed as the plan runs."""
    docs, a = observed(documents, docs=F.count(F.lit(1)))
    nodes, b = observed(shred(docs), nodes=F.count(F.lit(1)))
    out, c = observed(evaluate(nodes), results=F.count(F.lit(1)))
    out.write.format("noop").mode("overwrite").save()
    return documents.sparkSession.createDataFrame([(a.get["docs"], b.get["nodes"], c.get["results"])], "docs long, nodes long, results long")


def count_parses(docs: DataFrame, paths: dict[str, str]) -> DataFrame:
    """(method, parsed): documents that reach the parser when results are cached and when each field parses anew."""
    from ..plans import baselines

    spark, rows = docs.sparkSession, []
    for method, run in (("parsed once", baselines.cached_fields), ("parsed for each field", baselines.reparse_each_field)):
        seen: list[Observation] = []

        def parse(d: DataFrame) -> DataFrame:
            counted, o = observed(d, n=F.count(F.lit(1)))
            seen.append(o)
            return node_table(counted, "body", ("doc_id", "source", "lang"), "xml", fields=("ord", "plain", "text"))

        run(parse, docs, paths).write.format("noop").mode("overwrite").save()
        rows.append((method, sum(o.get["n"] for o in seen)))
    return spark.createDataFrame(rows, "method string, parsed long")
