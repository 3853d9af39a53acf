"""Similarity joins of short texts by edit distance, on equal segments instead of all pairs.

Let e edits be allowed between a shorter text of length n and a longer one of length m; e follows from m and the threshold. The
shorter is cut into e + 1 segments, of which one must occur unchanged in the longer, shifted by few places: at most i places for
segment i, and at most what the later segments' edits allow. So texts meet on (n, m, i, segment), an equality join with as many
keys as there are segments, at any threshold above one half; below it, texts shorter than their edits meet by their lengths.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

_EPS = 1e-9


def edits(longer: Column, theta: float) -> Column:
    """Edits that texts of similarity theta may differ by."""
    return F.floor(longer * (1 - theta) + _EPS).cast("int")


def within(a: str, b: str, theta: float) -> Column:
    """text_sim(a, b) >= theta, decided by length first."""
    x, y = F.length(a), F.length(b)
    return (F.least(x, y) >= F.greatest(x, y) * theta - _EPS) & (F.levenshtein(a, b) <= F.greatest(x, y) * (1 - theta) + _EPS)


def _segment(n: Column, k: Column, i: Column) -> tuple[Column, Column]:
    """Start (from 0) and length of segment i of k in a text of length n; the last ones are the longer."""
    base, more = F.floor(n / k).cast("int"), i - (k - n % k)
    return i * base + F.greatest(F.lit(0), more), base + F.when(more >= 0, 1).otherwise(0)


def _key(n: Column, m: Column, i: Column, piece: Column) -> Column:
    return F.concat_ws("\u0001", n, m, i, piece)


def short_keys(text: str, theta: float) -> Column:
    """Keys of a text as the shorter one: its segments for every longer length."""
    n, t = F.length(text), F.col(text)
    lengths = F.sequence(n, F.floor(n / theta + _EPS).cast("int"))

    def of_length(m: Column) -> Column:
        k = edits(m, theta) + 1

        def piece(i: Column) -> Column:
            start, size = _segment(n, k, i)
            return _key(n, m, i, F.substring(t, start + 1, size))

        return F.when(n < k, F.array(_key(n, m, F.lit(-1), F.lit("")))).otherwise(F.transform(F.sequence(F.lit(0), k - 1), piece))

    return F.array_distinct(F.flatten(F.transform(lengths, of_length)))


def long_keys(text: str, theta: float) -> Column:
    """Keys of a text as the longer one: the substrings that may be a shorter text's segments."""
    m, t = F.length(text), F.col(text)
    e = edits(m, theta)
    lengths = F.sequence(F.greatest(F.lit(1), F.ceil(m * theta - _EPS).cast("int")), m)

    def of_length(n: Column) -> Column:
        more = m - n

        def of_segment(i: Column) -> Column:
            start, size = _segment(n, e + 1, i)
            low = F.greatest(F.lit(0), start - i, start + more - (e - i))
            high = F.least(m - size, start + i, start + more + (e - i))
            places = F.when(low <= high, F.sequence(low, high)).otherwise(F.array().cast("array<int>"))
            return F.transform(places, lambda p: _key(n, m, i, F.substring(t, p + 1, size)))

        return F.when(n < e + 1, F.array(_key(n, m, F.lit(-1), F.lit("")))).otherwise(F.flatten(F.transform(F.sequence(F.lit(0), e), of_segment)))

    return F.array_distinct(F.flatten(F.transform(lengths, of_length)))


def near_pairs(left: DataFrame, right: DataFrame, theta: float) -> DataFrame:
    """(lang, a, b): texts (lang, text) of two tables with text_sim >= theta, by segment keys; empty texts meet only empty ones."""
    def one_way(shorter: DataFrame, longer: DataFrame, names: tuple[str, str]) -> DataFrame:
        x = shorter.filter(F.length("text") > 0).select("lang", F.col("text").alias(names[0]), F.explode(short_keys("text", theta)).alias("key"))
        y = longer.filter(F.length("text") > 0).select("lang", F.col("text").alias(names[1]), F.explode(long_keys("text", theta)).alias("key"))
        return x.join(y, ["lang", "key"]).filter(within("a", "b", theta)).select("lang", "a", "b")

    blank = left.filter("text = ''").select("lang", F.col("text").alias("a")).join(right.filter("text = ''").select("lang", F.col("text").alias("b")), "lang")
    return one_way(left, right, ("a", "b")).union(one_way(right, left, ("b", "a"))).union(blank.select("lang", "a", "b")).distinct()


def near_pairs_within(texts: DataFrame, theta: float) -> DataFrame:
    """(lang, a, b) of different texts of one table with text_sim >= theta, a < b."""
    rows = texts.filter(F.length("text") > 0)
    x = rows.select("lang", F.col("text").alias("s"), F.explode(short_keys("text", theta)).alias("key"))
    y = rows.select("lang", F.col("text").alias("t"), F.explode(long_keys("text", theta)).alias("key"))
    met = x.join(y, ["lang", "key"]).filter(F.col("s") != F.col("t")).filter(within("s", "t", theta))
    return met.select("lang", F.least("s", "t").alias("a"), F.greatest("s", "t").alias("b")).distinct()
