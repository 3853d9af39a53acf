"""Dictionary building: frequent key candidates, static values, synsets by fuzzy joins, edits, refinement."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions.columns import text_sim
from ..session import ensure_checkpoint_dir
from . import fuzzy


def lines_of(documents: DataFrame, low: int = 3, high: int = 60) -> DataFrame:
    """(doc_id, lang, text): distinct short lines of each document."""
    lines = F.array_distinct(F.transform(F.split("text", "\n"), lambda x: F.trim(x)))
    return documents.select("doc_id", "lang", F.explode(F.filter(lines, lambda x: F.length(x).between(low, high))).alias("text"))


def key_candidates(texts: DataFrame, min_docs: int = 3) -> DataFrame:
    """(lang, text, n_docs) of texts in at least min_docs documents; texts are distinct within a document."""
    return texts.groupBy("lang", "text").agg(F.count(F.lit(1)).alias("n_docs")).filter(F.col("n_docs") >= min_docs)


def heavy_candidates(texts: DataFrame, k: int = 50) -> DataFrame:
    """Approximate counterpart with bounded state: the k most frequent texts of each language."""
    return texts.groupBy("lang").agg(F.expr(f"approx_top_k(text, {k}, {20 * k})").alias("top")).select("lang", F.inline("top").alias("text", "n_docs"))


def drop_static(candidates: DataFrame, static: DataFrame) -> DataFrame:
    """Candidates without the expert's list of frequent values that are no keys (lang, text)."""
    return candidates.join(static, ["lang", "text"], "left_anti")


def template_signature(nodes: DataFrame) -> DataFrame:
    """(doc_id, template): hash of a document's distinct plain paths."""
    return nodes.groupBy("doc_id").agg(F.xxhash64(F.array_sort(F.collect_set(F.array_join("plain", "/")))).alias("template"))


def stratified_sample(docs: DataFrame, signatures: DataFrame, per_template: int) -> DataFrame:
    """per_template documents of each template, chosen by a hash of the id, so reruns agree."""
    order = Window.partitionBy("template").orderBy(F.xxhash64("doc_id"), "doc_id")
    chosen = signatures.withColumn("_r", F.row_number().over(order)).filter(F.col("_r") <= per_template).select("doc_id", "template")
    return docs.join(chosen, "doc_id")


def similar_pairs(candidates: DataFrame, theta: float = 0.8, blocked: bool = True) -> DataFrame:
    """(lang, a, b, sim) of different texts of one language with text_sim >= theta, a < b.

    Texts meet on segments (see fuzzy); the plain version compares all pairs and is the reference in the tests.
    """
    base = candidates.select("lang", "text").distinct()
    if blocked:
        met = fuzzy.near_pairs_within(base, theta)
    else:
        met = base.withColumnRenamed("text", "a").join(base.withColumnRenamed("text", "b"), "lang").filter("a < b").filter(fuzzy.within("a", "b", theta))
    return met.select("lang", "a", "b", text_sim("a", "b").alias("sim"))


def components(nodes: DataFrame, edges: DataFrame, checkpoint: bool = True) -> DataFrame:
    """(node, root): smallest node reachable over edges (a, b), by large-star and small-star rounds."""
    e = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u != v").distinct()
    e = _cut(e) if checkpoint else e
    was = None
    while True:
        both = e.union(e.select("v", "u"))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.filter("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct("u", F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.*").filter("u != v").distinct()
        e = _cut(small)
        now = tuple(e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if now == was:
            break
        was = now
    return nodes.join(e.select(F.col("u").alias("node"), F.col("v").alias("root")), "node", "left").select("node", F.coalesce("root", "node").alias("root"))


def _cut(df: DataFrame) -> DataFrame:
    """Materialise in the shared checkpoint folder."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint()


def build_synsets(candidates: DataFrame, pairs: DataFrame, merges: DataFrame | None = None, method: str = "components") -> DataFrame:
    """(lang, key_id, canonical, surface): groups of similar texts; merges (lang, a, b) are the expert's own links.

    components joins whatever is connected; leader takes texts by falling frequency and lets each join the first
    leader it is similar to. The canonical form is the most frequent surface, then the smallest.
    """
    links = pairs.select("lang", "a", "b")
    links = links.unionByName(merges.select("lang", "a", "b")) if merges is not None else links
    name = lambda lang, text: F.concat_ws("\u0001", lang, text)
    counts = candidates.select("lang", "text", "n_docs").withColumn("node", name("lang", "text"))
    if method == "leader":
        order = Window.partitionBy("lang").orderBy(F.col("n_docs").desc(), "text")
        ranked = counts.withColumn("rank", F.row_number().over(order))
        both = links.select("lang", "a", "b").union(links.select("lang", F.col("b"), F.col("a")))
        r = ranked.select("lang", "text", "rank")
        hops = both.join(r.select("lang", F.col("text").alias("a"), F.col("rank").alias("ra")), ["lang", "a"]).join(r.select("lang", F.col("text").alias("b"), F.col("rank").alias("rb")), ["lang", "b"]).filter("rb < ra")
        # a text leads unless an earlier leader is similar; decided in rounds, each settles the texts all of whose earlier mates are settled
        state = _cut(ranked.select("lang", "text", "rank", F.lit(None).cast("int").alias("lead")))
        while True:
            settled = state.filter("lead is not null").select("lang", F.col("text").alias("b"), F.col("lead"), F.lit(1).alias("known"))
            seen = hops.join(settled, ["lang", "b"], "left").groupBy("lang", F.col("a").alias("text")).agg(F.count(F.lit(1)).alias("n"), F.count("known").alias("k"), F.min(F.when(F.col("lead") == F.col("rb"), F.col("rb"))).alias("first"))
            nxt = state.join(seen, ["lang", "text"], "left").select("lang", "text", "rank", F.coalesce("lead", F.when(F.col("n").isNull(), F.col("rank")).when(F.col("n") == F.col("k"), F.coalesce("first", "rank"))).alias("lead"))
            state = _cut(nxt)
            if not state.filter("lead is null").limit(1).count():
                break
        rooted = state.join(ranked.select("lang", F.col("rank").alias("lead"), F.col("text").alias("root")), ["lang", "lead"]).join(counts.select("lang", "text", "n_docs"), ["lang", "text"])
    else:
        found = components(counts.select("node"), links.select(name("lang", "a").alias("a"), name("lang", "b").alias("b")))
        rooted = counts.join(found, "node")
    best = F.min(F.struct((-F.col("n_docs")).alias("f"), "text")).over(Window.partitionBy("lang", "root"))
    return rooted.withColumn("canonical", best["text"]).select("lang", F.substring(F.sha2(F.concat_ws("\u0001", "lang", "canonical"), 256), 1, 12).alias("key_id"), "canonical", F.col("text").alias("surface"))


def make_dictionary(synsets: DataFrame, names: DataFrame | None = None, version: str = "1") -> DataFrame:
    """Synsets with element names (lang, canonical, elem_name), else a name made from the canonical form."""
    made = F.regexp_replace(F.regexp_replace(F.lower("canonical"), r"[^\p{L}\p{N}]+", "_"), "^_|_$", "")
    named = synsets.join(names, ["lang", "canonical"], "left") if names is not None else synsets.withColumn("elem_name", F.lit(None).cast("string"))
    return named.select(F.lit(version).alias("version"), "lang", "key_id", F.lit(None).cast("string").alias("parent_key_id"), "surface", F.coalesce("elem_name", made).alias("elem_name"), F.lit(False).alias("is_static"))


def edit_dictionary(dictionary: DataFrame, edits: DataFrame) -> DataFrame:
    """Applies edits (op, lang, key_id, surface, target): add and remove a surface, merge one key into another, rename an element."""
    op = lambda name: edits.filter(F.col("op") == name)
    out = dictionary.join(op("remove").select("lang", "key_id", "surface"), ["lang", "key_id", "surface"], "left_anti").select(*dictionary.columns)
    merge = op("merge").select("lang", "key_id", F.col("target").alias("_into"))
    element = dictionary.groupBy("lang", F.col("key_id").alias("_into")).agg(F.min("elem_name").alias("_elem"))
    merge = merge.join(element, ["lang", "_into"], "left")  # a merged surface takes the other key's element
    out = out.join(merge, ["lang", "key_id"], "left").withColumns({"key_id": F.coalesce("_into", "key_id"), "elem_name": F.coalesce("_elem", "elem_name")}).select(*dictionary.columns)
    rename = op("rename").select("key_id", F.col("target").alias("_name")).distinct()
    out = out.join(rename, "key_id", "left").withColumn("elem_name", F.coalesce("_name", "elem_name")).select(*dictionary.columns)
    names = out.groupBy("key_id").agg(F.min("elem_name").alias("_n"))
    fresh = op("add").join(names, "key_id", "left")
    extra = {"version": F.lit(None).cast("string"), "parent_key_id": F.lit(None).cast("string"), "elem_name": F.coalesce("_n", "key_id"), "is_static": F.lit(False)}
    added = fresh.select(*[extra.get(c, F.col(c)).alias(c) if c in extra else F.col(c) for c in dictionary.columns])
    return out.unionByName(added).distinct()


def refine(measure: Callable[[DataFrame], float], dictionary: DataFrame, edits: list[DataFrame], target: float = 0.95, max_iter: int = 10) -> tuple[DataFrame, list[tuple[int, float]]]:
    """Edits the dictionary round by round until the measured rate reaches the target; returns it and the history."""
    history = [(0, measure(dictionary))]
    for k, edit in enumerate(edits[:max_iter], 1):
        if history[-1][1] >= target:
            break
        dictionary = edit_dictionary(dictionary, edit)
        history.append((k, measure(dictionary)))
    return dictionary, history


def classify_sources(nodes: DataFrame, pairs: DataFrame) -> DataFrame:
    """(source, n_templates, fields, labels_per_key, difficulty). Below 15 fields a document counts as simple."""
    paths = nodes.groupBy("source", "doc_id").agg(F.xxhash64(F.array_sort(F.collect_set(F.array_join("plain", "/")))).alias("t"))
    templates = paths.groupBy("source").agg(F.countDistinct("t").alias("n_templates"))
    per_doc = pairs.groupBy("source", "doc_id").agg(F.count(F.lit(1)).alias("n")).groupBy("source").agg(F.avg("n").alias("fields"))
    spread = pairs.groupBy("source", "key_id").agg(F.countDistinct("key_text").alias("n")).groupBy("source").agg(F.avg("n").alias("labels_per_key"))
    wide = templates.join(per_doc, "source", "left").join(spread, "source", "left")
    hard = (F.col("fields") >= 15).cast("int") + (F.col("labels_per_key") > 1.5).cast("int") + (F.col("n_templates") > 20).cast("int")
    return wide.withColumn("difficulty", F.element_at(F.array(*[F.lit(x) for x in ("simple", "medium", "difficult", "very difficult")]), hard + 1))
