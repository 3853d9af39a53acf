"""Token-id files with a minimal perfect hash index for keyed access.

Documents are dealt by range of their key, so shard files follow ascending doc_id. A shard is one row of a Parquet
table in the shared folder: raw little-endian ids (16 bits where the vocabulary allows it), and an index of a minimal
perfect hash over its keys (levels of collision-free bits, ranked by population counts) with, per slot, a 32-bit
fingerprint that rejects absent keys, the offset and the length. A key's ids are found in constant time once its shard is
known from the key range. Spark's writer commits the files, so lost executors only repeat their own tasks.

Encoding cuts a text at blanks that follow a non-blank (no token of the byte-level pattern spans such a place), encodes each
distinct piece once with the tokenizers library and keeps its ids in a bounded table.

Defined cases: null text is empty and gets only the end id; null doc_id sorts first; repeated doc_ids follow each other in (doc_id,
text hash) order over as many shards as they need, told apart by shard and an occurrence number inside it; an empty table
gives no shard and no rows; other columns are not read.
"""

from __future__ import annotations

import functools
import re
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import ensure_checkpoint_dir, slices

END_ID = 2
#: Payload bytes at which a shard is closed, pieces kept in an encoder's table.
SHARD_BYTES, TABLE = 4 << 20, 800_000
#: Marks a piece without a blank before it; as a lone surrogate it can't be in a text.
_BARE = "\ud800"
_LINE = _BARE + "\n"


def default_vocabulary() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


class PieceEncoder:
    """Whole-text encoding through the library, one call for all new pieces of a batch."""

    _odd = re.compile(r"[ \n]\s")
    _cut = re.compile(r"(?<=\S)(?= )")
    _blank = re.compile(r"\s")
    _signs = ".,;:!?%&*#$)"

    def __init__(self, vocabulary: str):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(vocabulary)
        self.tokenizer.no_truncation()
        self.tokenizer.no_padding()
        self.line_id = self.tokenizer.encode("\n", add_special_tokens=False).ids[0]
        self.width = "<u2" if self.tokenizer.get_vocab_size() <= 1 << 16 else "<u4"
        # only a word's first token can hold the blank before it
        size = self.tokenizer.get_vocab_size()
        self.opens = np.array([(self.tokenizer.id_to_token(i) or "").startswith("\u0120") for i in range(size)])
        self.table: dict[str, bytes] = {}

    def pieces(self, text: str) -> list[str]:
        """Pieces of a text: lines, line ends, and words. Words that follow a blank stand without it, others behind a mark."""
        if self._odd.search(text):
            return [p[1:] if p[0] == " " else _BARE + p for p in self._cut.split(text)]
        out: list[str] = []
        for line in text.split("\n"):
            words = line.split(" ")
            words[0] = _BARE + words[0]
            out += words
            out.append(_LINE)
        del out[-1]
        return out

    def cut_at(self, text: str, starts: np.ndarray | None) -> list[bytes]:
        """Ids of a joined text, cut before the tokens flagged in starts, or at line ends."""
        ids = np.array(self.tokenizer.encode_batch_fast([text], add_special_tokens=False)[0].ids, self.width)
        size, data = ids.itemsize, ids.tobytes()
        if starts is not None:
            at = (np.flatnonzero(starts[ids]) * size).tolist()
            return [data[a:b] for a, b in zip(at, [*at[1:], len(data)])]
        cuts = np.flatnonzero(ids == self.line_id)
        return [data[a:b] for a, b in zip([0, *((cuts + 1) * size).tolist()], [*(cuts * size).tolist(), len(data)])]

    def learn(self, new: set[str]) -> None:
        """Fills the table for new pieces with two calls of the library.

        A word's letters and a closing run of signs are two tokens of the pattern whatever stands around them. Words of
        letters are joined by blanks, which begin their tokens; other pieces without white space are joined by line ends, which are
        tokens of their own.
        """
        table, signs = self.table, self._signs
        words: set[str] = set()
        tails: list[tuple[str, str, str]] = []
        rest: set[str] = set()
        for p in new:
            if p.isalpha():
                words.add(p)
                continue
            core = p.rstrip(signs)
            if core.isalpha() and core != p:
                tail = _BARE + p[len(core) :]
                tails.append((p, core, tail))
                if core not in table:
                    words.add(core)
                if tail not in table:
                    rest.add(tail)
            else:
                rest.add(p)
        if words:
            ordered = list(words)
            table.update(zip(ordered, self.cut_at(" " + " ".join(ordered), self.opens), strict=True))
        full = {p: p[1:] if p[:1] == _BARE else " " + p for p in rest}
        easy = [p for p, f in full.items() if f.strip() and not self._blank.search(f, 1) and not (f[0].isspace() and f[0] != " ") and "<|" not in f]
        if easy:
            table.update(zip(easy, self.cut_at("\n".join([full[p] for p in easy]), None), strict=True))
        for p, f in full.items():
            if p not in table:
                table[p] = np.array(self.tokenizer.encode(f, add_special_tokens=False).ids, self.width).tobytes()
        table.update((p, table[core] + table[tail]) for p, core, tail in tails)

    def encode(self, texts: list[str]) -> list[bytes]:
        if len(self.table) > TABLE:
            self.table.clear()
        split = [self.pieces(t) if t else [] for t in texts]
        if new := set().union(*split).difference(self.table):
            self.learn(new)
        get = self.table.__getitem__
        return [b"".join(map(get, s)) for s in split]


@functools.lru_cache(2)
def encoder(vocabulary: str) -> PieceEncoder:
    return PieceEncoder(vocabulary)


def mixed(keys: np.ndarray, seed: int) -> np.ndarray:
    """A 64-bit finaliser over key words."""
    with np.errstate(over="ignore"):
        z = keys + np.uint64((seed * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) % (1 << 64))
        z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return z ^ (z >> np.uint64(31))


def key_words(ids: np.ndarray, missing: np.ndarray, occurrence: np.ndarray) -> np.ndarray:
    """One 64-bit word for (doc_id or null, occurrence)."""
    return mixed(ids.astype(np.int64).view(np.uint64) ^ mixed(occurrence.astype(np.uint64) * np.uint64(2) + missing.astype(np.uint64), 99), 98)


class PerfectHash:
    """Minimal perfect hash: at each level, keys that land alone on a bit are placed; the rest go one level down.

    words are the levels' bits in order, ranks the number of set bits before each word.
    """

    def __init__(self, sizes: list[int], words: np.ndarray, ranks: np.ndarray):
        self.sizes, self.words, self.ranks = sizes, words, ranks

    @classmethod
    def build(cls, keys: np.ndarray) -> PerfectHash:
        sizes, levels, left = [], [], keys
        while len(left):
            if len(sizes) > 200:
                raise ValueError("two keys have one word")
            size = max(8, 2 * len(left))
            at = (mixed(left, len(sizes)) % np.uint64(size)).astype(np.int64)
            alone = np.bincount(at, minlength=size) == 1
            levels.append(alone)
            sizes.append(size)
            left = left[~alone[at]]
        bits = np.concatenate(levels) if levels else np.empty(0, bool)
        packed = np.packbits(bits, bitorder="little")
        words = np.frombuffer(packed.tobytes() + bytes(-len(packed) % 8), "<u8")
        ones = np.cumsum(np.bitwise_count(words), dtype=np.int64)
        return cls(sizes, words, np.r_[0, ones[:-1]].astype(np.uint32) if len(ones) else np.empty(0, np.uint32))

    def slots(self, keys: np.ndarray) -> np.ndarray:
        """Slot of each key (0 to n - 1), or -1 if no level places it. The work depends on the keys asked for only."""
        out, open_keys, start = np.full(len(keys), -1, np.int64), np.arange(len(keys)), 0
        for level, size in enumerate(self.sizes):
            if not len(open_keys):
                break
            at = np.uint64(start) + mixed(keys[open_keys], level) % np.uint64(size)
            word, bit = (at >> np.uint64(6)).astype(np.int64), at & np.uint64(63)
            held = self.words[word]
            hit = (held >> bit) & np.uint64(1) == 1
            below = held & ((np.uint64(1) << bit) - np.uint64(1))
            out[open_keys[hit]] = (self.ranks[word] + np.bitwise_count(below))[hit]
            open_keys = open_keys[~hit]
            start += size
        return out


def prints_of(words: np.ndarray) -> np.ndarray:
    return (mixed(words, 777) >> np.uint64(32)).astype(np.uint32)


SHARD = pa.schema(
    [("part", pa.int32()), ("shard", pa.int32()), ("before", pa.int64()), ("n_docs", pa.int64()), ("n_ids", pa.int64()), ("n_missing", pa.int64()), ("first_key", pa.int64()), ("last_key", pa.int64()), ("width", pa.int32()),
     ("payload", pa.binary()), ("keys", pa.binary()), ("missing", pa.binary()), ("level_sizes", pa.list_(pa.int64())), ("level_bits", pa.binary()), ("ranks", pa.binary()), ("prints", pa.binary()), ("offsets", pa.binary()), ("lengths", pa.binary())]
)
SHARD_SQL = "part int, shard int, before long, n_docs long, n_ids long, n_missing long, first_key long, last_key long, width int, payload binary, keys binary, missing binary, level_sizes array<bigint>, level_bits binary, ranks binary, prints binary, offsets binary, lengths binary"


def occurrences(ids: np.ndarray, missing: np.ndarray) -> np.ndarray:
    """Number of equal keys before each (keys are sorted)."""
    n = len(ids)
    fresh = np.r_[True, (ids[1:] != ids[:-1]) | (missing[1:] != missing[:-1])] if n else np.empty(0, bool)
    start = np.maximum.accumulate(np.where(fresh, np.arange(n), 0)) if n else np.empty(0, np.int64)
    return np.arange(n) - start


def shard_row(part: int, shard: int, before: int, ids: list[int | None], payloads: list[bytes], width: str) -> dict:
    missing = np.array([i is None for i in ids])
    keys = np.array([i or 0 for i in ids], np.int64)
    size = np.dtype(width).itemsize
    lengths = np.array([len(p) // size for p in payloads], np.int64)
    offsets = np.cumsum(lengths) - lengths
    words = key_words(keys, missing, occurrences(keys, missing))
    hashed = PerfectHash.build(words)
    slot = hashed.slots(words)
    by_slot = np.empty(len(keys), np.int64)
    by_slot[slot] = np.arange(len(keys))
    return {
        "part": part, "shard": shard, "before": before, "n_docs": len(keys), "n_ids": int(lengths.sum()), "n_missing": int(missing.sum()), "first_key": next((i for i in ids if i is not None), None), "last_key": ids[-1], "width": size,
        "payload": b"".join(payloads), "keys": keys.tobytes(), "missing": missing.tobytes(), "level_sizes": hashed.sizes, "level_bits": hashed.words.tobytes(), "ranks": hashed.ranks.tobytes(),
        "prints": prints_of(words)[by_slot].tobytes(), "offsets": offsets[by_slot].tobytes(), "lengths": lengths[by_slot].tobytes(),
    }


def write_ids(docs: DataFrame, path: str, vocabulary: str | None = None, end_id: int = END_ID, shard_bytes: int = SHARD_BYTES) -> None:
    """Encodes all texts and writes the shards as a Parquet table at path."""
    vocab = vocabulary or default_vocabulary()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code, part = encoder(vocab), TaskContext.get().partitionId()
        end = np.array([end_id], code.width).tobytes()
        shard = before = size = 0
        ids: list[int | None] = []
        payloads: list[bytes] = []

        def close() -> pa.RecordBatch:
            nonlocal shard, before, size
            row = shard_row(part, shard, before, ids, payloads, code.width)
            shard, before, size = shard + 1, before + row["n_ids"], 0
            ids.clear()
            payloads.clear()
            return pa.RecordBatch.from_pylist([row], SHARD)

        for batch in batches:
            for piece in slices(batch, "text", 2 << 20):
                keys, coded = piece.column(0).to_pylist(), code.encode(piece.column(1).to_pylist())
                for key, data in zip(keys, coded):
                    if size >= shard_bytes:
                        yield close()
                    ids.append(key)
                    payloads.append(data + end)
                    size += len(data)
        if ids:
            yield close()

    order = [F.col("doc_id").asc_nulls_first(), F.xxhash64(F.coalesce("text", F.lit("")))]
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").repartitionByRange(*order).sortWithinPartitions(*order)
    rows.mapInArrow(run, SHARD_SQL).write.parquet(path)


def open_shard(row: dict) -> tuple[PerfectHash, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Views of a shard's index and payload; nothing is unpacked."""
    hashed = PerfectHash(list(row["level_sizes"]), np.frombuffer(row["level_bits"], "<u8"), np.frombuffer(row["ranks"], np.uint32))
    kinds = (("prints", np.uint32), ("offsets", np.int64), ("lengths", np.int64))
    return hashed, *[np.frombuffer(row[k], t) for k, t in kinds], np.frombuffer(row["payload"], "<u2" if row["width"] == 2 else "<u4")


def lookup(row: dict, keys: list[int | None], occurrence: int = 0) -> list[np.ndarray | None]:
    """Ids of keys in one shard in constant time each; None for absent keys."""
    hashed, prints, offsets, lengths, payload = open_shard(row)
    missing = np.array([k is None for k in keys], bool)
    words = key_words(np.array([k or 0 for k in keys], np.int64), missing, np.full(len(keys), occurrence))
    slots = hashed.slots(words)
    known = (slots >= 0) & (prints[np.maximum(slots, 0)] == prints_of(words)) if len(prints) else np.zeros(len(keys), bool)
    return [payload[offsets[s] : offsets[s] + lengths[s]] if ok else None for s, ok in zip(slots, known)]


def get(spark: SparkSession, path: str, keys: list[int | None]) -> DataFrame:
    """(doc_id, part, shard, occurrence, ids) of every document with one of the keys, from the files at path.

    Only shards whose key range holds a key are read; a fingerprint lets about one absent key in 2**32 pass.
    """
    given = sorted({k for k in keys if k is not None})
    held = F.lit(False)
    if given:
        inside = F.exists(F.array(*map(F.lit, given)), lambda k: k.between(F.col("first_key"), F.col("last_key")))
        held = F.col("first_key").isNotNull() & (F.col("first_key") <= given[-1]) & (F.col("last_key") >= given[0]) & inside
    if None in keys:
        held = held | (F.col("n_missing") > 0)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                row = batch.slice(k, 1).to_pylist()[0]
                asked = [x for x in given if row["first_key"] is not None and row["first_key"] <= x <= row["last_key"]] + [None] * (None in keys and row["n_missing"] > 0)
                found, turn = [], 0
                while asked:
                    got = [(x, ids) for x, ids in zip(asked, lookup(row, asked, turn)) if ids is not None]
                    found += [(x, row["part"], row["shard"], turn, ids) for x, ids in got]
                    asked, turn = [x for x, _ in got], turn + 1
                if found:
                    columns = [pa.array(c, t) for c, t in zip(zip(*found), (pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.list_(pa.int64())))]
                    yield pa.RecordBatch.from_arrays(columns, ["doc_id", "part", "shard", "occurrence", "ids"])

    return spark.read.schema(SHARD_SQL).parquet(path).filter(held).mapInArrow(run, "doc_id long, part int, shard int, occurrence int, ids array<bigint>")


def read_back(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document, from the files, through their index."""
    shards = spark.read.schema(SHARD_SQL).parquet(path)
    totals = shards.groupBy("part").agg(F.sum("n_ids").alias("n"))
    earlier = F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))
    starts = totals.select("part", F.coalesce(earlier, F.lit(0)).alias("part_start"))
    # one small row for each writing task, so the broadcast is bounded by the number of tasks
    placed = shards.join(F.broadcast(starts), "part")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for k in range(batch.num_rows):
                row = batch.slice(k, 1).to_pylist()[0]
                hashed, prints, offsets, lengths, payload = open_shard(row)
                keys, missing = np.frombuffer(row["keys"], np.int64), np.frombuffer(row["missing"], bool)
                words = key_words(keys, missing, occurrences(keys, missing))
                slots = hashed.slots(words)
                if (slots < 0).any() or (prints[slots] != prints_of(words)).any():
                    raise ValueError("a key of the shard is not in its index")
                at, n = offsets[slots], lengths[slots]
                crc = [zlib.crc32(payload[a : a + m].astype("<u4").tobytes()) for a, m in zip(at.tolist(), n.tolist())]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(keys, mask=missing), pa.array(row["part_start"] + row["before"] + at), pa.array(n), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"]
                )

    return placed.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def encode_to_files(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """Writes the corpus' id files into the shared folder and reads them back."""
    spark = docs.sparkSession
    ensure_checkpoint_dir(spark)
    path = f"{spark.sparkContext.getCheckpointDir()}/ids-{uuid.uuid4().hex}"
    write_ids(docs, path, vocabulary)
    return read_back(spark, path)
