"""Column functions: similarities, paths, content types, URLs, recoding, dates."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column
from pyspark.sql import functions as F


def col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


# similarity of strings and paths


def text_sim(a: Column | str, b: Column | str) -> Column:
    """1 - edit distance / longer length; two empty strings are equal."""
    a, b = col(a), col(b)
    longer = F.greatest(F.length(a), F.length(b))
    return F.when(longer == 0, 1.0).otherwise(1.0 - F.levenshtein(a, b) / longer)


def is_similar(a: Column | str, b: Column | str, theta: float) -> Column:
    """text_sim(a, b) >= theta, by length first and a bounded distance after."""
    a, b = col(a), col(b)
    longer, shorter = F.greatest(F.length(a), F.length(b)), F.least(F.length(a), F.length(b))
    return (shorter >= longer * theta) & (F.levenshtein(a, b) <= longer * (1 - theta) + 1e-9)


def path_prefix_sim(p: Column | str, q: Column | str, norm: str = "max") -> Column:
    """Length of the longest common prefix of two step lists over their longest, shortest or mean length."""
    p, q = col(p), col(q)
    same = F.zip_with(p, q, lambda a, b: a.eqNullSafe(b) & a.isNotNull())
    first = F.array_position(same, False)
    common = F.when(first == 0, F.size(same)).otherwise(first - 1)
    a, b = F.size(p), F.size(q)
    length = {"max": F.greatest(a, b), "min": F.least(a, b), "mean": (a + b) / 2}[norm]
    return F.when(F.greatest(a, b) == 0, 1.0).when(length == 0, 0.0).otherwise(common / length)


def path_edit_sim(p: Column | str, q: Column | str) -> Column:
    """1 - list edit distance / longer length. Steps become single characters of the pair's own alphabet, so the built-in
    string distance applies exactly (up to about 50,000 distinct steps in a pair)."""
    p, q = col(p), col(q)
    alphabet = F.array_distinct(F.concat(p, q))
    coded = lambda x: F.array_join(F.transform(x, lambda s: F.decode(F.unhex(F.lpad(F.hex(F.array_position(alphabet, s) + 0x3FF), 4, "0")), "UTF-16BE")), "")
    longer = F.greatest(F.size(p), F.size(q))
    return F.when(longer == 0, 1.0).otherwise(1.0 - F.levenshtein(coded(p), coded(q)) / longer)


def strip_numbering(c: Column | str) -> Column:
    """A label without a leading section number such as "II.1) " or "3.2.1 - "."""
    return F.trim(F.regexp_replace(col(c), r"^\s*(?:(?:[IVXLC]+|\d+)(?:\.(?:[IVXLC]+|\d+))*[.)]*)(?:\s*[-:)]\s*|\s+)(?=\S)", ""))


def fold_key(c: Column | str) -> Column:
    """The form in which labels are compared: unnumbered, lower case, without a closing separator."""
    return F.lower(F.regexp_replace(strip_numbering(c), r"\s*[:=→]\s*$", ""))


def path_text(steps: Column | str) -> Column:
    return F.concat(F.lit("/"), F.array_join(col(steps), "/"))


# archive and acquisition


def parse_content_type(c: Column | str) -> Column:
    """struct<mime, charset> of a Content-Type value, both lower case and null where absent."""
    c = F.lower(col(c))
    none = lambda x: F.nullif(F.trim(x), F.lit(""))
    return F.struct(none(F.regexp_extract(c, r"^\s*([^;\s]+)", 1)).alias("mime"), none(F.regexp_extract(c, r"charset\s*=\s*[\"']?([^\"';\s]+)", 1)).alias("charset"))


def meta_charset(c: Column | str) -> Column:
    return F.nullif(F.lower(F.regexp_extract(col(c), r"(?i)<meta[^>]+charset\s*=\s*[\"']?([A-Za-z0-9_-]+)", 1)), F.lit(""))


def canonical_url(c: Column | str) -> Column:
    """A URL without scheme, user part of the query, fragment and closing slash; host in lower case."""
    c = F.regexp_replace(F.regexp_replace(F.trim(col(c)), r"[?#].*$", ""), r"^[A-Za-z][A-Za-z0-9+.-]*://", "")
    host = F.lower(F.regexp_extract(c, r"^[^/]*", 0))
    return F.concat(host, F.regexp_replace(F.regexp_replace(c, r"^[^/]*", ""), r"/+$", ""))


def host(c: Column | str) -> Column:
    return F.lower(F.regexp_extract(col(c), r"^[A-Za-z][A-Za-z0-9+.-]*://([^/?#]*)", 1))


# conversion


def recode(c: Column | str, mapping: dict[str, str]) -> Column:
    """Mapped value, or the value itself where the map has none."""
    c = col(c)
    if not mapping:
        return c
    table = F.create_map(*[F.lit(x) for kv in mapping.items() for x in kv])
    return F.coalesce(F.try_element_at(table, c), c)


#: Words for yes and no by language.
BOOLEANS = {"en": ({"yes", "true", "y"}, {"no", "false", "n"}), "fr": ({"oui", "vrai"}, {"non", "faux"}), "de": ({"ja", "wahr"}, {"nein", "falsch"}), "es": ({"sí", "si", "verdadero"}, {"no", "falso"})}


def to_bool(c: Column | str, lang: Column | str) -> Column:
    """true, false or null by the words of the row's language."""
    c, lang = F.lower(F.trim(col(c))), col(lang)
    out = F.lit(None).cast("boolean")
    for code, (yes, no) in BOOLEANS.items():
        out = F.when((lang == code) & c.isin(sorted(yes)), True).when((lang == code) & c.isin(sorted(no)), False).otherwise(out)
    return out


def to_date_any(c: Column | str, formats: Sequence[str] = ("yyyy-MM-dd", "dd/MM/yyyy", "dd.MM.yyyy", "yyyyMMdd")) -> Column:
    """The first format that fits; null if none does."""
    return F.coalesce(*[F.try_to_timestamp(col(c), F.lit(f)) for f in formats]).cast("timestamp_ntz")


def date_from_parts(year: Column | str, month: Column | str, day: Column | str, hour: Column | str | None = None) -> Column:
    """A date whose parts stand in fields of their own; null if they are none."""
    whole = lambda c: col(c).try_cast("int")
    text = F.format_string("%04d-%02d-%02d %02d", whole(year), whole(month), whole(day), F.coalesce(whole(hour), F.lit(0)) if hour is not None else F.lit(0))
    return F.try_to_timestamp(text, F.lit("yyyy-MM-dd HH")).cast("timestamp_ntz")


def value_shape(c: Column | str) -> Column:
    """A value's outline: digit runs 9, upper-case runs A, lower-case runs a."""
    c = F.regexp_replace(col(c), "[0-9]+", "9")
    return F.regexp_replace(F.regexp_replace(c, r"\p{Lu}+", "A"), r"\p{Ll}+", "a")
