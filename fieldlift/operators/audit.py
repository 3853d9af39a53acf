"""Coverage validation: path inventories, mapped and unmapped sets, confidence, review queues, conversion rates, missing content."""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.columns import path_text

#: Bands of the mapped to unmapped ratio.
HIGH, LOW = 2.0, 0.5


def counted_nodes(nodes: DataFrame, attributes: bool = True, non_empty: bool = True) -> DataFrame:
    """The nodes that an inventory counts."""
    rows = nodes.filter(F.col("ord").isNotNull())
    rows = rows.filter(F.trim("text") != "") if non_empty else rows
    return rows if attributes else rows.filter(~F.startswith(F.element_at("plain", -1), F.lit("@")))


def path_counts(nodes: DataFrame, attributes: bool = True, non_empty: bool = True) -> DataFrame:
    """(source, path, n): the inventory without documents and examples. Documents are read once and only counts are shuffled."""
    rows = counted_nodes(nodes, attributes, non_empty).groupBy("source", "plain").agg(F.count(F.lit(1)).alias("m"))
    return rows.groupBy("source", path_text("plain").alias("path")).agg(F.sum("m").alias("n"))


def path_inventory(nodes: DataFrame, attributes: bool = True, non_empty: bool = True) -> DataFrame:
    """(source, path, n, n_docs, samples): every path with its count and two example documents.

    Paths are counted in each document first; the examples are the smallest document and the smallest after it,
    by bounded aggregates.
    """
    rows = counted_nodes(nodes, attributes, non_empty)
    per_doc = rows.groupBy("source", path_text("plain").alias("path"), "doc_id").agg(F.count(F.lit(1)).alias("m"))
    ranked = Window.partitionBy("source", "path").orderBy("doc_id")
    # the rank filter prunes before the shuffle, so the examples never gather a path's documents
    two = per_doc.withColumn("r", F.row_number().over(ranked)).filter("r <= 2").groupBy("source", "path").agg(F.array_sort(F.collect_list("doc_id")).alias("samples"))
    counts = per_doc.groupBy("source", "path").agg(F.sum("m").alias("n"), F.count(F.lit(1)).alias("n_docs"))
    return counts.join(two, ["source", "path"])


def split_by_mapping(inventory: DataFrame, mapped: DataFrame) -> DataFrame:
    """The inventory with a flag whether some mapped path (pattern) covers each path. The mapping is a driver-side list, so it is small."""
    paths = inventory.select("path").distinct()
    hit = paths.join(F.broadcast(mapped.select("pattern").distinct()), F.expr("path rlike pattern"), "left_semi").withColumn("is_mapped", F.lit(True))
    return inventory.join(hit, "path", "left").withColumn("is_mapped", F.coalesce("is_mapped", F.lit(False)))


def unmapped_paths(inventory: DataFrame, mapped: DataFrame) -> DataFrame:
    return split_by_mapping(inventory, mapped).filter(~F.col("is_mapped")).drop("is_mapped")


def coverage(inventory: DataFrame, mapped: DataFrame, high: float = HIGH, low: float = LOW) -> DataFrame:
    """(source, mapped, unmapped, mapped_mass, unmapped_mass, ratio, band)."""
    flagged = split_by_mapping(inventory, mapped)
    count = lambda test, what: F.sum(F.when(test, what).otherwise(0))
    yes = F.col("is_mapped")
    out = flagged.groupBy("source").agg(count(yes, 1).alias("mapped"), count(~yes, 1).alias("unmapped"), count(yes, F.col("n")).alias("mapped_mass"), count(~yes, F.col("n")).alias("unmapped_mass"))
    ratio = F.col("mapped") / F.nullif(F.col("unmapped"), F.lit(0))
    return out.withColumn("ratio", ratio).withColumn("band", F.when(F.col("ratio").isNull() | (F.col("ratio") >= high), "high").when(F.col("ratio") <= low, "low").otherwise("close"))


def review_queue(unmapped: DataFrame, k: int = 20, order: str = "frequency") -> DataFrame:
    """The k unmapped paths to look at next: most frequent, rarest, random (by hash) or weighted (exponential keys)."""
    keys = {
        "frequency": [F.col("n").desc(), "source", "path"],
        "tail": [F.col("n").asc(), "source", "path"],
        "random": [F.xxhash64("source", "path"), "path"],
        "weighted": [(-F.log((F.pmod(F.xxhash64("source", "path"), F.lit(1_000_003)) + 1) / 1_000_004.0) / F.col("n")).asc(), "path"],
    }
    return unmapped.orderBy(*keys[order]).limit(k)


def amend(inventory: DataFrame, mapped: DataFrame, reviewer: Callable[[DataFrame], tuple[DataFrame, DataFrame]], rounds: int = 5, k: int = 20) -> tuple[DataFrame, list[tuple[int, int, int]]]:
    """Review, add what matters, set aside what does not, until nothing is left or the rounds are over.

    The inventory is computed once; only the small set operations repeat. reviewer(queue) returns (relevant patterns, irrelevant paths).
    """
    history, ignored = [], None
    for r in range(rounds):
        left = unmapped_paths(inventory, mapped)
        left = left if ignored is None else left.join(ignored, "path", "left_anti")
        n = left.select("path").distinct().count()
        history.append((r, n, 0 if ignored is None else ignored.count()))
        if not n:
            break
        add, drop = reviewer(review_queue(left, k))
        mapped = mapped.select("pattern").unionByName(add.select("pattern")).distinct()
        ignored = drop.select("path") if ignored is None else ignored.union(drop.select("path")).distinct()
    return mapped, history


def sample_coverage(full: DataFrame, sample: DataFrame) -> DataFrame:
    """(source, paths, seen, share, mass_share): how much of the inventory a sample shows."""
    both = full.select("source", "path", "n").join(sample.select("source", "path", F.lit(1).alias("s")), ["source", "path"], "full_outer")
    return both.groupBy("source").agg(F.count("n").alias("paths"), F.count("s").alias("seen"), (F.count("s") / F.count("n")).alias("share"), (F.sum(F.when(F.col("s") == 1, F.col("n")).otherwise(0)) / F.sum("n")).alias("mass_share"))


def conversion_rate(scanned: DataFrame) -> DataFrame:
    """(source, nodes, converted, node_rate, char_rate, key_rate): converted are values; keys count by documents' distinct key lines that got a value."""
    value, key = F.col("role") == "value", F.col("role") == "key"
    chars = F.sum(F.when(~key, F.length("text")))
    per = scanned.groupBy("source").agg(
        F.count(F.when(~key, 1)).alias("nodes"), F.count(F.when(value, 1)).alias("converted"), F.sum(F.when(value, F.length("text"))).alias("cc"), chars.alias("ca"),
        F.countDistinct(F.when(key, F.struct("doc_id", "key_id"))).alias("kk"), F.countDistinct(F.when(value, F.struct("doc_id", "last_key.key_id"))).alias("kv"),
    )
    return per.select("source", "nodes", "converted", (F.col("converted") / F.col("nodes")).alias("node_rate"), (F.coalesce("cc", F.lit(0)) / F.col("ca")).alias("char_rate"), (F.col("kv") / F.col("kk")).alias("key_rate"))


def missing_report(scanned: DataFrame) -> DataFrame:
    """(doc_id, source, ord, key_ctx, text): unconverted text with the key it stands under."""
    return scanned.filter("role = 'unmatched'").select("doc_id", "source", "ord", F.concat(F.lit("after "), F.coalesce("last_key.key_id", F.lit("(start)"))).alias("key_ctx"), "text")


def write_inventory(inventory: DataFrame, path: str) -> None:
    """One JSON object for each source: path -> [count, examples]."""
    entry = F.map_from_entries(F.array_sort(F.collect_list(F.struct("path", F.struct("n", "samples")))))
    inventory.groupBy("source").agg(F.to_json(entry).alias("value")).select("value").write.mode("overwrite").text(path)


def audit_phases(phases: dict[str, DataFrame]) -> DataFrame:
    """(source, phase, paths, mass): each source's inventory under the phase that validates it (native records, converted ones)."""
    parts = [inv.groupBy("source").agg(F.count(F.lit(1)).alias("paths"), F.sum("n").alias("mass")).select("source", F.lit(name).alias("phase"), "paths", "mass") for name, inv in phases.items()]
    return reduce(DataFrame.unionByName, parts)


def rounds_to_coverage(inventory: DataFrame, order: str, k: int, share: float, most: int = 1000) -> int:
    """Rounds of k reviewed paths each until the seen paths hold the share of all occurrences."""
    total, seen, left = inventory.agg(F.sum("n")).first()[0] or 0, 0, inventory
    for r in range(1, most + 1):
        queue = review_queue(left, k, order).select("source", "path", "n").collect()  # k rows
        seen += sum(q["n"] for q in queue)
        if not queue or seen >= share * total:
            return r
        done = inventory.sparkSession.createDataFrame([(q["source"], q["path"]) for q in queue], "source string, path string")
        left = left.join(done, ["source", "path"], "left_anti")
    return most
