"""Licence scans: exact phrases and fuzzy short notices.

A notice of length L may differ by up to k edits (k grows with L; a few short ones allow none). By the pigeonhole principle one of k + 1
pieces of the notice must then occur unchanged, so piece occurrences, found by plain substring search, are the
only places where the regex library's bounded-error matching has to run; there it tries every run of whole words of a fitting
length. Matches may not change a digit (versions), may not be another known notice, may not put another licence's name in and may
change at most one letter of a distinguishing word of up to 3 letters.

Defined cases: null text is empty and gives 0 words, empty labels, null positions, score 0; only ASCII letters are
lower-cased; repeated rows give repeated results; texts are scanned whole; columns of other names are not read.
"""

from __future__ import annotations

import re

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .common import map_batches, utf8

#: Base phrases and their labels.
BASE = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}
#: Further notices that the method looks for and their labels.
OWN = {
    "permission is hereby granted free of charge to any person obtaining a copy": "mit",
    "redistribution and use in source and binary forms": "bsd",
    "permission to use copy modify and or distribute this software for any purpose": "isc",
    "licensed under the apache license": "apache",
    "gnu general public license version 2": "gpl-2",
    "gnu general public license version 3": "gpl-3",
    "gnu lesser general public license": "lgpl",
    "gnu affero general public license": "agpl",
    "mozilla public license version 2": "mpl-2",
    "eclipse public license version 2": "epl-2",
    "boost software license version 1": "bsl-1",
    "free and unencumbered software released into the public domain": "unlicense",
    "creative commons attribution sharealike": "cc-by-sa",
    "cc by sa": "cc-by-sa",
    "cc by nd": "cc-by-nd",
}
#: Phrases looked for unchanged only: one more edit makes them other notices or plain words.
EXACT = frozenset(("cc by sa", "cc by nd"))
#: Word runs near one of the above that mean something else.
OTHER = frozenset(("cc by na", "cc by no"))
#: Names of other licences and their authors: a changed word that is one of them is no misspelling.
NAMES = frozenset("afl agpl apl apsl artistic bsd bsl cc0 cddl cecill cern cpal cpl ecl ecos efl epl eupl fdl gfdl gpl ibm ipl isc lgpl lppl miros mitre mpl mspl msrl ms ncsa nist nosl npl ntp odbl ofl osl php pil psf ql rpl sil sspl upl vim w3c wtfpl x11 zlib zpl".split())
#: The short words that tell a phrase's licence from others.
TELLING = frozenset(("mit", "cc", "by", "nc", "gnu"))
#: Bytes that separate words become blanks; A-Z become a-z.
_SPLIT = bytes(c if c >= 0x80 or chr(c).isdigit() or 97 <= c <= 122 else c + 32 if 65 <= c <= 90 else 32 for c in range(256))


#: All phrases; none of them is a misspelling of another.
KNOWN = frozenset((*BASE, *OWN))


def allowed_edits(phrase: str) -> int:
    return 0 if phrase in EXACT else 1 if len(phrase) < 12 else 2 if len(phrase) < 48 else 3


class Notice:
    def __init__(self, phrase: str, label: str, base: bool):
        self.phrase, self.label, self.base, self.k = phrase, label, base, allowed_edits(phrase)
        n = self.k + 1
        cuts = [round(i * len(phrase) / n) for i in range(n + 1)]
        self.seeds = [(phrase[a:b].encode(), a) for a, b in zip(cuts, cuts[1:])]
        self.exact = f" {phrase} ".encode()
        self.fuzzy = regex.compile(rf"(?b)(?:{regex.escape(phrase, literal_spaces=True)}){{e<={self.k}}}")
        self.words = phrase.split()
        self.short = [(i, regex.compile(rf"(?:{w}){{e<=1}}")) for i, w in enumerate(self.words) if w in TELLING]
        self.digits = re.sub(r"\D", "", phrase)

    def places(self, text: bytes) -> list[int]:
        """Byte offsets of exact occurrences; occurrences may share a border blank."""
        found, at = [], text.find(self.exact)
        while at >= 0:
            found.append(at + 1)
            at = text.find(self.exact, at + 1)
        return found

    def near(self, text: bytes) -> list[tuple[int, int, int]]:
        """(start, end, edits) of inexact matches, the best at each start."""
        if not self.k:
            return []
        reach = 4 * self.k  # an edit moves a place by at most one character of 4 bytes
        tried: set[tuple[int, int]] = set()
        out: dict[int, tuple[int, int]] = {}
        for seed, offset in self.seeds:
            at = text.find(seed)
            while at >= 0:
                starts = word_starts(text, at - offset - reach, at - offset + reach)
                for start in starts:
                    for end in word_ends(text, start + len(self.phrase) - self.k, start + len(self.phrase) + reach):
                        if (start, end) not in tried:
                            tried.add((start, end))
                            edits = self.edits(text[start:end].decode("utf-8", "replace"))
                            if edits and edits < out.get(start, (0, 99))[1]:
                                out[start] = (end, edits)
                at = text.find(seed, at + 1)
        return [(s, e, k) for s, (e, k) in sorted(out.items())]

    def edits(self, got: str) -> int:
        """Edits of an inexact notice, 0 if the words are none."""
        if abs(len(got) - len(self.phrase)) > self.k or got in OTHER or got in KNOWN or self.phrase in got or re.sub(r"\D", "", got) != self.digits:
            return 0
        m = self.fuzzy.fullmatch(got)
        words = got.split(" ")
        if not m or any(w in NAMES for w in words if w not in self.words):
            return 0
        if len(words) == len(self.words) and not all(near.fullmatch(words[i]) for i, near in self.short):
            return 0
        return sum(m.fuzzy_counts)


def word_starts(text: bytes, a: int, b: int) -> list[int]:
    """Places in a..b where a word starts; words are separated by single blanks, also before the first and after the last."""
    return [i for i in range(max(1, a), min(b, len(text) - 2) + 1) if text[i - 1] == 32]


def word_ends(text: bytes, a: int, b: int) -> list[int]:
    """Places in a..b behind the end of a word."""
    return [i for i in range(max(1, a), min(b, len(text) - 1) + 1) if text[i] == 32]


def notices() -> list[Notice]:
    return [Notice(p, label, True) for p, label in BASE.items()] + [Notice(p, label, False) for p, label in OWN.items()]


def scan_text(raw: bytes, known: list[Notice]) -> tuple[int, list[tuple[str, int, int, int, bool, float]]]:
    """(number of words, findings as (label, first word, last word, edits, base, score)); the score falls with the edits a letter."""
    words = raw.translate(_SPLIT).split()
    text = b" " + b" ".join(words) + b" "
    found = []
    for n in known:
        exact = n.places(text)
        spans = [(s, s + len(n.phrase), 0) for s in exact]
        for s, e, k in n.near(text):
            if not any(a < e and s < b for a, b, _ in spans[: len(exact)]):
                spans.append((s, e, k))
        for s, e, k in spans:
            first = text.count(b" ", 0, s) - 1
            found.append((n.label, first, first + text.count(b" ", s, e), k, n.base and not k, 1.0 - k / len(n.phrase)))
    return len(words), sorted(found, key=lambda x: (x[1], x[0], x[2]))


SCHEMA = "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, findings array<struct<label:string,first_word:bigint,last_word:bigint,edits:int,base:boolean,score:double>>"


def scan_licences(docs: DataFrame) -> DataFrame:
    """One row per document with its summary and findings (label, word span, edits)."""
    kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.string(), pa.float64(), pa.list_(pa.struct([("label", pa.string()), ("first_word", pa.int64()), ("last_word", pa.int64()), ("edits", pa.int32()), ("base", pa.bool_()), ("score", pa.float64())]))]
    names = [x.split()[0] for x in SCHEMA.split(", ")]

    def make():
        known = notices()

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            rows = []
            for raw in utf8(batch.column(1)):
                n_words, found = scan_text(raw, known)
                base = [x for x in found if x[4]]
                score = max([0.0, *(x[5] for x in found)])
                rows.append((n_words, len(base), min((x[1] for x in base), default=None), max((x[1] for x in base), default=None), ",".join(sorted({x[0] for x in base})), ",".join(sorted({x[0] for x in found})), score, [dict(zip(("label", "first_word", "last_word", "edits", "base", "score"), x)) for x in found]))
            columns = [pa.array(c, k) for c, k in zip(zip(*rows) if rows else [[]] * 8, kinds[1:])]
            return pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), *columns], names)

        return step

    return map_batches(docs.select("doc_id", "text"), make, SCHEMA, "text")
