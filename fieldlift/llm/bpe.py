"""Byte-pair encoding and decoding by batched numpy merge rounds.

The vocabulary file's own normalisation (NFC, white space, lower case by character) and word pattern are applied
per distinct white-space chunk. All new words of a batch then lie in one flat symbol array; each round finds every
adjacent pair's rank by binary search over the sorted pair keys, takes the lowest rank of each word and merges it
left to right, until no word has a known pair. The ids of a chunk are kept in a bounded table, so
frequent chunks are merged once per task.

Defined cases: null text is empty and encodes to no ids (the decoded text is empty); strings of added tokens in a
text become their ids, as in the library; texts are encoded whole, whatever their length; repeated rows repeat;
other columns are not read.
"""

from __future__ import annotations

import functools
import hashlib
import json
import re
import unicodedata

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .common import map_batches

#: Chunks kept in a task's table before it is cleared.
TABLE = 200_000
_PLAIN = re.compile(r"[\x1c-\x1f]")
#: Unicode White_Space.
_BLANK = re.compile("[" + "".join(map(chr, (*range(9, 14), 32, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000))) + "]+")
_NONE = np.iinfo(np.int64).max


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte: visible Latin-1 stands for itself, the rest follows from 256 on."""
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = iter(range(256, 512))
    return [chr(b) if b in set(shown) else chr(next(rest)) for b in range(256)]


class WordCoder:
    def __init__(self, vocabulary: str):
        with open(vocabulary, encoding="utf-8") as f:
            spec = json.load(f)
        model = spec["model"]
        self.vocab: dict[str, int] = model["vocab"]
        self.suffix: str = model.get("end_of_word_suffix") or ""
        self.added = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.special = re.compile("(" + "|".join(map(re.escape, sorted(self.added, key=len, reverse=True))) + ")") if self.added else None
        kinds = spec["pre_tokenizer"]["pretokenizers"]
        self.words = regex.compile(next(k["pattern"]["Regex"] for k in kinds if k["type"] == "Split"))
        self.letters = byte_letters()
        size = max(max(self.vocab.values()), *self.added.values()) + 1
        self.tokens = [""] * size
        for token, i in [*self.vocab.items(), *self.added.items()]:
            self.tokens[i] = token
        self.token_bytes = [t.encode() for t in self.tokens]
        # symbols are numbered as in the vocabulary; a pair's key is left * size + right
        self.size = size
        keys, into = [], []
        for pair in model["merges"]:
            left, right = pair.split(" ") if isinstance(pair, str) else pair
            keys.append(self.vocab[left] * size + self.vocab[right])
            into.append(self.vocab[left + right])
        order = np.argsort(np.array(keys, np.int64), kind="stable")
        self.keys, self.ranks, self.into = np.array(keys, np.int64)[order], order.astype(np.int64), np.array(into, np.int64)
        self.first = np.array([self.vocab[c] for c in self.letters], np.int64)
        self.last = np.array([self.vocab[c + self.suffix] for c in self.letters], np.int64)
        self.table: dict[str, bytes] = {}
        self.coded: dict[str, bytes] = {}

    def merge(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of many words at once, end to end, and where each word's ids begin (and the last end)."""
        lengths = np.array([len(w) for w in words], np.int64)
        flat = np.frombuffer(b"".join(words), np.uint8)
        symbols = self.first[flat]
        ends = np.cumsum(lengths) - 1
        symbols[ends] = self.last[flat[ends]]
        word = np.repeat(np.arange(len(words)), lengths)
        done_symbols, done_words = [], []
        while len(symbols):
            same = word[:-1] == word[1:]
            key = symbols[:-1] * self.size + symbols[1:]
            at = np.minimum(np.searchsorted(self.keys, key), len(self.keys) - 1)
            rank = np.where(same & (self.keys[at] == key), self.ranks[at], _NONE)
            starts = np.flatnonzero(np.r_[True, ~same])
            best = np.minimum.reduceat(np.r_[rank, _NONE], starts)
            counts = np.diff(np.r_[starts, len(symbols)])
            open_word = np.repeat(best < _NONE, counts)
            if not open_word.all():
                done_symbols.append(symbols[~open_word])
                done_words.append(word[~open_word])
            if not open_word.any():
                break
            hit = np.r_[rank, _NONE] == np.repeat(best, counts)
            hit &= open_word
            # in a run of overlapping hits (a a a) every second one, from the left, is merged
            where = np.flatnonzero(hit)
            run = np.cumsum(np.r_[True, np.diff(where) > 1]) - 1
            start = where[np.flatnonzero(np.r_[True, np.diff(where) > 1])]
            where = where[(where - start[run]) % 2 == 0]
            symbols = symbols.copy()
            symbols[where] = self.into[rank[where]]
            keep = open_word
            keep[where + 1] = False
            symbols, word = symbols[keep], word[keep]
        symbols, word = np.concatenate(done_symbols), np.concatenate(done_words)
        order = np.argsort(word, kind="stable")
        return symbols[order], np.searchsorted(word[order], np.arange(len(words) + 1))

    def chunk_words(self, chunk: str) -> list[str]:
        if not chunk.isascii():
            chunk = unicodedata.normalize("NFC", chunk).replace("\u03a3", "\u03c3")
        chunk = chunk.lower()
        if chunk.isalpha():  # the letters of the word pattern are exactly these
            return [chunk]
        if chunk[-1:] in (".", ",") and chunk[:-1].isalpha():
            return [chunk[:-1], chunk[-1]]
        return self.words.findall(chunk)

    def learn(self, chunks: list[str]) -> None:
        """Fills the table for new chunks: one numpy merge over all their words that are new too."""
        split = [self.chunk_words(c) for c in chunks]
        if len(self.coded) > TABLE:
            self.coded.clear()
        coded = self.coded
        if new := sorted({w for ws in split for w in ws if w not in coded}):
            symbols, starts = self.merge([w.encode() for w in new])
            ids, at = symbols.astype("<u4").tobytes(), (4 * starts).tolist()
            coded.update((w, ids[a:b]) for w, a, b in zip(new, at, at[1:]))
        for c, ws in zip(chunks, split):
            self.table[c] = coded[ws[0]] if len(ws) == 1 else b"".join([coded[w] for w in ws])

    def pieces(self, text: str) -> list[str]:
        """White-space chunks; a chunk that is an added token's string stands for its id."""
        if self.special is not None and "<|" in text:
            out = []
            for part in self.special.split(text):
                out += [part] if part in self.added else self.blank(part)
            return out
        return self.blank(text)

    @staticmethod
    def blank(text: str) -> list[str]:
        return [c for c in _BLANK.split(text) if c] if _PLAIN.search(text) else text.split()

    def encode_batch(self, texts: list[str]) -> list[bytes]:
        """Each text's ids as little-endian unsigned 32-bit integers."""
        split = [self.pieces(t or "") for t in texts]
        if len(self.table) > TABLE:
            self.table.clear()
        for token, i in self.added.items():
            self.table[token] = np.array([i], "<u4").tobytes()
        distinct = set().union(*split)
        if new := distinct.difference(self.table):
            self.learn(list(new))
        get = {c: self.table[c] for c in distinct}.__getitem__  # small, so it stays near the processor
        return [b"".join(map(get, s)) for s in split]

    def decode(self, ids: bytes) -> bytes:
        """UTF-8 of the ids' tokens, parted by blanks, as the library joins them where a file names no decoder."""
        return b" ".join(map(self.token_bytes.__getitem__, np.frombuffer(ids, "<u4").tolist()))


@functools.lru_cache(2)
def coder(vocabulary: str) -> WordCoder:
    return WordCoder(vocabulary)


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


def encode_texts(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """(doc_id, ids array<int>, decoded string): the operator's real outputs."""
    path = vocabulary or default_vocabulary()

    def make():
        code = coder(path)

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            got = code.encode_batch(batch.column(1).to_pylist())
            return pa.RecordBatch.from_arrays([batch.column(0).cast(pa.int64()), pa.array([np.frombuffer(g, "<i4") for g in got], pa.list_(pa.int32())), pa.array([code.decode(g).decode() for g in got], pa.string())], ["doc_id", "ids", "decoded"])

        return step

    return map_batches(docs.select("doc_id", "text"), make, "doc_id long, ids array<int>, decoded string", "text", 2 << 20)


def encode_digest(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256); the decoded text is built from the ids."""
    path = vocabulary or default_vocabulary()

    def make():
        code = coder(path)

        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            got = code.encode_batch(batch.column(1).to_pylist())
            return pa.RecordBatch.from_arrays(
                [
                    batch.column(0).cast(pa.int64()),
                    pa.array([len(g) // 4 for g in got], pa.int64()),
                    pa.array([hashlib.sha256(g).hexdigest() for g in got], pa.string()),
                    pa.array([hashlib.sha256(code.decode(g)).hexdigest() for g in got], pa.string()),
                ],
                ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
            )

        return step

    return map_batches(docs.select("doc_id", "text"), make, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string", "text", 2 << 20)
