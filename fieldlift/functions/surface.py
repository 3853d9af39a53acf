"""SQL surface: functions and table functions registered by name."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ..operators.stages import members
from .shred import html_nodes


@udtf(returnType="ord int, tag string, path string, text string")
class HtmlNodeRows:
    """html_node_rows(html): text-bearing nodes of a page."""

    def eval(self, html: str):
        for ord_, _, tag, plain, *_, text in html_nodes(html):
            yield ord_, tag, "/" + "/".join(plain), text


@udtf(returnType="member string, status string, body binary")
class UnpackMembers:
    """unpack_members(name, body): members of an archive."""

    def eval(self, name: str, body: bytes):
        yield from members(name or "", bytes(body or b""))


def register_all(spark: SparkSession) -> None:
    spark.udtf.register("html_node_rows", HtmlNodeRows)
    spark.udtf.register("unpack_members", UnpackMembers)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION text_similarity(a STRING, b STRING) RETURNS DOUBLE RETURN CASE WHEN greatest(length(a), length(b)) = 0 THEN 1D ELSE 1D - levenshtein(a, b) / greatest(length(a), length(b)) END")
