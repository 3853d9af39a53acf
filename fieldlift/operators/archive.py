"""Acquisition and archive: records, integrity, URLs, windows, limits, charsets, inventories, schedules."""

from __future__ import annotations

import codecs
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.columns import canonical_url, host, meta_charset, parse_content_type
from .dictionary import _cut


def archive_items(pages: DataFrame, captured: DataFrame | None = None) -> DataFrame:
    """(item_id, source, captured_at, url, content_type, body, sha256) of raw pages (page_id, url, html)."""
    body = F.encode(F.coalesce("html", F.lit("")), "UTF-8")
    out = pages.select(F.col("page_id").cast("string").alias("item_id"), host("url").alias("source"), "url", F.lit("text/html; charset=utf-8").alias("content_type"), body.alias("body"), F.sha2(body, 256).alias("sha256"))
    return out.join(captured, "item_id", "left") if captured is not None else out.withColumn("captured_at", F.lit(None).cast("timestamp_ntz"))


def verify_integrity(archive: DataFrame) -> DataFrame:
    """Items whose body no longer has its recorded hash."""
    return archive.withColumn("found", F.sha2("body", 256)).filter(~F.col("found").eqNullSafe(F.col("sha256"))).select("item_id", F.col("sha256").alias("recorded"), "found")


def id_range(spark: SparkSession, low: int, high: int, step: int = 1) -> DataFrame:
    return spark.range(low, high, step).withColumnRenamed("id", "item_id")


def enumerate_urls(template: str, ids: DataFrame) -> DataFrame:
    """One URL for each public id; the template has one %s."""
    return ids.select("item_id", F.format_string(template, F.col("item_id").cast("string")).alias("url"))


def harvest_ids(pages: DataFrame, pattern: str = r"/(\d+)(?:[/?#]|$)") -> DataFrame:
    """Distinct (source, item_id) found in already fetched URLs."""
    return pages.select(host("url").alias("source"), F.explode(F.regexp_extract_all("url", F.lit(pattern), F.lit(1))).alias("item_id")).select("source", F.col("item_id").cast("long").alias("item_id")).distinct()


def url_groups(pages: DataFrame) -> DataFrame:
    """(canonical, n): how many raw URLs have one canonical form."""
    return pages.groupBy(canonical_url("url").alias("canonical")).agg(F.count(F.lit(1)).alias("n"))


def assign_unique_url(archive: DataFrame) -> DataFrame:
    """A unique URL for each item: the first of a canonical form keeps it, others get their content hash appended.

    Items of one URL and one content stay apart by their number.
    """
    c = canonical_url("url")
    same = Window.partitionBy("_c").orderBy("item_id")
    twin = Window.partitionBy("_c", "sha256").orderBy("item_id")
    out = archive.withColumn("_c", c).withColumns({"_n": F.row_number().over(same), "_t": F.row_number().over(twin)})
    suffix = F.concat(F.lit("#"), F.substring("sha256", 1, 16), F.when(F.col("_t") > 1, F.concat(F.lit("."), F.col("_t").cast("string"))).otherwise(""))
    return out.withColumn("unique_url", F.when(F.col("_n") == 1, F.col("_c")).otherwise(F.concat("_c", suffix))).drop("_c", "_n", "_t")


def collect_links(pages: DataFrame) -> DataFrame:
    """(page_id, source, href) of every link."""
    return pages.select("page_id", host("url").alias("source"), F.explode(F.regexp_extract_all(F.coalesce("html", F.lit("")), F.lit(r"(?i)<a\s[^>]*href=\"([^\"]*)\""), F.lit(1))).alias("href"))


def crawl_closure(seed: DataFrame, links: DataFrame, max_rounds: int = 20) -> DataFrame:
    """(url, depth): what is reachable from the seed over links (src, dst), breadth first, each round cut off in the shared folder."""
    seen = _cut(seed.select("url").distinct().withColumn("depth", F.lit(0)))
    frontier = seen
    for depth in range(1, max_rounds + 1):
        step = frontier.join(links, frontier["url"] == links["src"]).select(F.col("dst").alias("url")).distinct().join(seen, "url", "left_anti").withColumn("depth", F.lit(depth))
        frontier = _cut(step)
        if not frontier.limit(1).count():
            break
        seen = _cut(seen.unionByName(frontier))
    return seen


def plan_windows(items: DataFrame, ts: str, cap: int, grains: tuple[str, ...] = ("year", "month", "day", "hour")) -> DataFrame:
    """(window_start, grain, n, resolved): the coarsest windows that stay within the cap of a capped search.

    One aggregation at the finest grain; coarser counts come from it. A window is used if its parent is over the cap.
    """
    counts = items.filter(F.col(ts).isNotNull()).groupBy(F.date_trunc(grains[-1], ts).alias("finest")).agg(F.count(F.lit(1)).alias("m"))
    for g in grains:
        counts = counts.withColumn(f"s_{g}", F.date_trunc(g, "finest"))
    for g in grains:
        counts = counts.withColumn(f"n_{g}", F.sum("m").over(Window.partitionBy(f"s_{g}")))
    used = [F.struct(F.col(f"s_{g}").alias("window_start"), F.lit(g).alias("grain"), F.col(f"n_{g}").alias("n")) for g in grains]
    pick = F.when(F.col(f"n_{grains[0]}") <= cap, used[0])
    for g, u in zip(grains[1:-1], used[1:-1]):
        pick = pick.when(F.col(f"n_{g}") <= cap, u)
    return counts.select(pick.otherwise(used[-1]).alias("w")).select("w.*").distinct().withColumns({"window_start": F.col("window_start").cast("timestamp_ntz"), "resolved": F.col("n") <= cap})


def flag_outages(items: DataFrame, must_have: tuple[str, ...], body: str = "html") -> DataFrame:
    """Items that lack expected content, although the server gave an answer."""
    text = F.lower(F.coalesce(F.col(body), F.lit("")))
    lacking = F.filter(F.array(*[F.when(~F.contains(text, F.lit(t.lower())), F.lit(t)) for t in must_have]), lambda x: x.isNotNull())
    return items.withColumn("lacking", lacking).withColumn("outage", F.size("lacking") > 0)


def outage_rate(events: DataFrame, unit: str = "day") -> DataFrame:
    return events.groupBy(F.date_trunc(unit, "ts").cast("timestamp_ntz").alias("at")).agg(F.count(F.lit(1)).alias("n"), F.count(F.when(F.col("event_type") == "error", 1)).alias("errors"))


def over_budget(events: DataFrame, seconds: int, limit: int) -> DataFrame:
    """(user_id, event_id, ts, n): requests that are beyond `limit` within the sliding window that ends with them."""
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    w = Window.partitionBy("user_id").orderBy("_us").rangeBetween(-seconds * 1_000_000, 0)
    return events.withColumn("_us", at).withColumn("n", F.count(F.lit(1)).over(w)).filter(F.col("n") > limit).select("user_id", "event_id", "ts", "n")


def sessions(events: DataFrame, gap_seconds: int) -> DataFrame:
    """(user_id, started, ended, n): runs of a user's events without a pause over the gap."""
    us = F.unix_micros(F.col("ts").cast("timestamp"))
    order = Window.partitionBy("user_id").orderBy("_us", "event_id")
    fresh = F.when(F.coalesce(F.col("_us") - F.lag("_us").over(order) > gap_seconds * 1_000_000, F.lit(True)), 1).otherwise(0)
    numbered = events.withColumn("_us", us).withColumn("_f", fresh).withColumn("_s", F.sum("_f").over(order.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy("user_id", "_s").agg(F.min("ts").alias("started"), F.max("ts").alias("ended"), F.count(F.lit(1)).alias("n")).drop("_s")


def decode_bytes(body: bytes, declared: str | None, meta: str | None, candidates: tuple[str, ...]) -> tuple[str, str, bool]:
    """(text, charset, agreed): header, then in-document name, then UTF-8, then the candidates; the first that decodes."""
    named = [c for c in (declared, meta) if c]
    agreed = len({codecs.lookup(c).name for c in named if _known(c)}) <= 1
    for name in [*named, "utf-8", *candidates]:
        if _known(name):
            try:
                return body.decode(name), codecs.lookup(name).name, agreed and (not named or name == named[0])
            except UnicodeDecodeError:
                continue
    return body.decode("utf-8", "replace"), "utf-8?", False


def _known(name: str) -> bool:
    try:
        return bool(codecs.lookup(name))
    except LookupError:
        return False


def resolve_charsets(archive: DataFrame, candidates: tuple[str, ...] = ("cp1252", "cp1251", "latin-1")) -> DataFrame:
    """(item_id, charset, agreed, text): bodies re-encoded to UTF-8 in one Arrow pass; no session setting is touched."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            got = [decode_bytes(x or b"", h, m, candidates) for x, h, m in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), b.column(3).to_pylist())]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([g[1] for g in got], pa.string()), pa.array([g[2] for g in got], pa.bool_()), pa.array([g[0] for g in got], pa.string())], ["item_id", "charset", "agreed", "text"])

    head = F.decode(F.substring("body", 1, 2048), "ISO-8859-1")
    rows = archive.select("item_id", "body", parse_content_type("content_type")["charset"].alias("h"), meta_charset(head).alias("m"))
    return rows.mapInArrow(run, "item_id string, charset string, agreed boolean, text string")


def crawl_inventory(items: DataFrame) -> DataFrame:
    """(source, n, first, last) of archived items."""
    return items.groupBy("source").agg(F.count(F.lit(1)).alias("n"), F.min("captured_at").alias("first"), F.max("captured_at").alias("last"))


def source_catalogue(nations: DataFrame, formats: dict[int, str], excluded: dict[int, str] | None = None) -> DataFrame:
    """(source, format, processed, reason) of the candidate sources."""
    key = F.col("n_nationkey").cast("int")
    pick = lambda m, t: F.try_element_at(F.create_map(*[F.lit(x) for kv in m.items() for x in kv]).cast(f"map<int,{t}>"), key) if m else F.lit(None).cast(t)
    reason = pick(excluded or {}, "string")
    return nations.select(F.col("n_name").alias("source"), pick(formats, "string").alias("format"), reason.isNull().alias("processed"), reason.alias("reason"))


def format_mix(catalogue: DataFrame) -> DataFrame:
    return catalogue.rollup("format", "processed").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("int").alias("level"))


def new_items(items: DataFrame, seen: DataFrame) -> DataFrame:
    """Items whose (url, content) is not in the archive yet."""
    return items.join(seen.select("url", "sha256").distinct(), ["url", "sha256"], "left_anti").select(*items.columns)


def due_sources(schedule: DataFrame, as_of: Column) -> DataFrame:
    """Sources (source, last_run, every_days) that are due at a time."""
    return schedule.withColumn("due_at", F.date_add(F.col("last_run").cast("date"), F.col("every_days"))).filter(F.col("due_at") <= as_of.cast("date"))


def brute_force_cost(ids: DataFrame) -> DataFrame:
    """(source, brute_force, harvested, hit_rate): requests of trying a source's whole id range against its known ids."""
    span = (F.max("item_id") - F.min("item_id") + 1).alias("brute_force")
    return ids.groupBy("source").agg(span, F.count(F.lit(1)).alias("harvested")).withColumn("hit_rate", F.col("harvested") / F.col("brute_force"))
