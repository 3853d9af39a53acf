"""Alternatives that the main methods are compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.pairing import match_keys


def baseline_regex(docs: DataFrame, rules: dict[str, str], body: str = "body") -> DataFrame:
    """(doc_id, source, key_id, value): one hand-written pattern for each field; breaks when the template changes."""

    def named(key: str):
        return lambda v: F.struct(F.lit(key).alias("key_id"), v.alias("value"))

    hits = F.array(*[F.transform(F.regexp_extract_all(body, F.lit(p), F.lit(1)), named(k)) for k, p in rules.items()])
    return docs.select("doc_id", "source", F.inline(F.flatten(hits)))


def baseline_fixed_schema(docs: DataFrame, schema: str, projection: dict[str, str], body: str = "body") -> DataFrame:
    """A fixed XML schema and a projection, as a stylesheet would do it: one JVM parse, nothing adapts."""
    parsed = docs.select("doc_id", "source", F.from_xml(body, schema).alias("x"))
    return parsed.select("doc_id", "source", *[F.expr(e).alias(n) for n, e in projection.items()])


def reparse_each_field(nodes_of, docs: DataFrame, paths: dict[str, str]) -> DataFrame:
    """Extraction without cached path results: every field shreds its documents again."""
    from functools import reduce

    from .loader import first_hit

    parts = [first_hit(nodes_of(docs), [p]).select("doc_id", F.lit(f).alias("field"), "value") for f, p in paths.items()]
    return reduce(DataFrame.unionByName, parts)


def cached_fields(nodes_of, docs: DataFrame, paths: dict[str, str]) -> DataFrame:
    """The same with one parse: a path lookup gives each node its field."""
    from ..functions.columns import path_text

    names = F.create_map(*[F.lit(x) for f, p in paths.items() for x in (p, f)])
    rows = nodes_of(docs).withColumn("field", F.try_element_at(names, path_text("plain"))).filter("field is not null")
    return rows.groupBy("doc_id", "field").agg(F.min(F.struct("ord", "text"))["text"].alias("value"))


def split_at_separator(nodes: DataFrame, mark: str, dictionary: DataFrame, theta_key: float = 0.8) -> DataFrame:
    """(doc_id, key_id, value): lines cut at the first separator; what stands before must be a key of the dictionary."""
    at = F.instr("text", mark)
    cut = nodes.filter(at > 1).select("doc_id", "lang", F.trim(F.substring("text", F.lit(1), at - 1)).alias("text"), F.trim(F.substring("text", at + len(mark), F.length("text"))).alias("value"))
    return cut.join(match_keys(cut, dictionary, theta_key), ["lang", "text"]).filter("value <> ''").select("doc_id", "key_id", "value")
