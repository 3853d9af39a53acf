"""N-gram Jaccard join with adaptive multi-match prefixes, and the connected components of its links.

A document's set is its distinct 5-word shingles; two documents link when 100 * intersection >= 75 * union.
All sets are put in one global token order, rarest first: a count sketch of fixed size, summed over all tasks, estimates every
token's frequency, so the order doesn't depend on how the rows are dealt. If two sets link, then for any l they share l tokens
among their first size - ceil(0.75 * size) + l tokens. Each set picks its own l where reading its tokens' lists plus checking the
candidates that l leaves is estimated to cost least; a pair is checked when it shares as many prefix tokens as the smaller of its
two l, at places in both prefixes that leave room behind them for the common tokens that a link of the two sizes still needs.
The sketch steers only the order; results are exact with any.

Tokens whose lists hold the same sets are one token with a weight (told by a hash of the list; a collision only adds
candidates), so copies of a passage or of a whole text are read once and not once for each shingle.

Only links between different components can still matter, so the pairs of a token's list are never all made: rounds of
stars verify exactly, for every set, a few promising sets of other components, with other centres in every round, until a round
links nothing; the last round verifies every remaining pair between components. Equal sets are one class from the start.

Defined cases: A-Z are lower-cased, words are split at ASCII white space; fewer than 5 words are one shingle; null, empty and
blank texts have an empty set and link with nothing; repeated rows and ids are rows (a repeated doc_id gives its row
each time); null doc_ids are kept and take part, but can't name a component; extra columns are not read.
"""

from __future__ import annotations

import math
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructField, StructType
from pyspark.sql.window import Window

from .common import cut, free_name, release, slices, trimmed, utf8

#: Words of a shingle, similarity in hundredths.
WORDS, PERCENT = 5, 75
#: Parameters: largest l, cost of verifying a candidate in units of reading a list entry, most star rounds, centres of a list and mates of a set verified in a round.
MOST, CHECK_COST, ROUNDS, CENTRES, MATES = 8, 20.0, 2, 6, 4
#: Count sketch: rows, cells of a row, cells of a shipped piece. Its size bounds what is broadcast (one byte a cell).
SKETCH_ROWS, CELLS, PIECE = 2, 1 << 21, 1 << 14
#: Lists of tokens estimated to be longer than LONG are dealt over so many salts.
LONG, SALTS = 2048, 64
#: Prefix tokens that meet in a bucket, about, and that a task packs at a time.
BUCKET, PACKED = 1_000_000, 500_000
#: Sets of a round whose keys are few enough to be broadcast (8 bytes each).
FEW = 20_000
#: Ratio of the sizes that share a bucket in the last round; a set's partners lie in some twenty buckets.
SIZE_STEP = 1.03
#: Bits of the filter of wanted documents.
FILTER_BITS = 1 << 23

_FACTORS = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F], np.uint64)


def scramble(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xD6E8FEB86659FD93)
    x = (x ^ (x >> np.uint64(32))) * np.uint64(0xCA5A826395121157)
    return x ^ (x >> np.uint64(32))


class Shingler:
    """Sorted distinct 64-bit shingle hashes of a text."""

    def __init__(self):
        self.known: dict[bytes, int] = {}

    def __call__(self, raw: bytes) -> np.ndarray:
        words = raw.lower().split()
        if not words:
            return np.empty(0, np.uint64)
        known = self.known
        if new := set(words).difference(known):
            if len(known) > 150_000:
                known.clear()
                new = set(words)
            known.update((w, xxhash.xxh64_intdigest(w)) for w in new)
        h = np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
        with np.errstate(over="ignore"):
            if len(h) < WORDS:
                return scramble((h * _FACTORS[: len(h)]).sum(keepdims=True) + np.uint64(len(h)))
            n = len(h) - WORDS + 1
            total = h[:n] * _FACTORS[0]
            for k in range(1, WORDS):
                total += scramble(h[k : k + n] + _FACTORS[k])
            return np.unique(scramble(total))


def set_key(tokens: np.ndarray) -> int:
    """One 63-bit key for equal sets; 0 is the empty set."""
    if not len(tokens):
        return 0
    return xxhash.xxh3_64_intdigest(tokens.tobytes()) >> 1 or 1


def sketch_cells(tokens: np.ndarray) -> list[np.ndarray]:
    """The cell of each token in each row of the sketch."""
    mask = np.uint64(CELLS - 1)
    return [((tokens >> np.uint64(21 * row + 1)) & mask).astype(np.int64) for row in range(SKETCH_ROWS)]


def profile(docs: DataFrame) -> DataFrame:
    """(kind, id, n, key, counts): kind 0 is a document with its set's size and key, kind 1 a piece (id) of a task's count sketch.

    A task counts each of its sets once; counts are shipped as compressed 16-bit planes, saturated.
    """
    NAMES = ["kind", "id", "n", "key", "counts"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingle, seen = Shingler(), set()
        table = np.zeros(SKETCH_ROWS * CELLS, np.uint32)
        for batch in batches:
            for part in slices(batch, "text", 2 << 20):
                sets = [shingle(r) for r in utf8(part.column(1))]
                keys = [set_key(s) for s in sets]
                n = len(sets)
                yield pa.RecordBatch.from_arrays([pa.array(np.zeros(n, np.int32)), part.column(0).cast(pa.int64()), pa.array([len(s) for s in sets], pa.int64()), pa.array(keys, pa.int64()), pa.nulls(n, pa.binary())], NAMES)
                fresh = []
                for s, k in zip(sets, keys):
                    if len(s) and k not in seen:
                        seen.add(k)
                        fresh.append(s)
                if fresh:
                    for row, cells in enumerate(sketch_cells(np.concatenate(fresh))):
                        np.add.at(table, row * CELLS + cells, np.uint32(1))
        pieces = [(k, p) for k, p in enumerate(table.reshape(-1, PIECE)) if p.any()]
        if pieces:
            n = len(pieces)
            packed = [zlib.compress(b"".join((x & 255).astype(np.uint8).tobytes() for x in (q, q >> 8)), 1) for q in (np.minimum(p, 65535) for _, p in pieces)]
            yield pa.RecordBatch.from_arrays([pa.array(np.ones(n, np.int32)), pa.array([k for k, _ in pieces], pa.int64()), pa.nulls(n, pa.int64()), pa.nulls(n, pa.int64()), pa.array(packed, pa.binary())], NAMES)

    return docs.select("doc_id", "text").mapInArrow(trimmed(run), "kind int, id long, n long, key long, counts binary")


class Frequencies:
    """Estimated list lengths from the summed sketch; cells hold eighths of octaves."""

    def __init__(self, codes: np.ndarray, noise: float):
        self.codes, self.noise = codes, noise

    def __call__(self, tokens: np.ndarray) -> np.ndarray:
        least = None
        for row, cells in enumerate(sketch_cells(tokens)):
            got = self.codes[row * CELLS + cells]
            least = got if least is None else np.minimum(least, got)
        return np.maximum(np.exp2(least / 8.0) - 1.0 - self.noise, 1.0)


def frequencies(profiled: DataFrame) -> Frequencies:
    """Sums the tasks' sketches piece by piece, streaming; what reaches the driver has the sketch's fixed size."""

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total: dict[int, np.ndarray] = {}
        for batch in batches:
            for k, raw in zip(batch.column(0).to_pylist(), batch.column(1)):
                low, high = np.frombuffer(zlib.decompress(raw.as_buffer()), np.uint8).astype(np.int64).reshape(2, PIECE)
                if k not in total:
                    total[k] = np.zeros(PIECE, np.int64)
                total[k] += low + (high << 8)
        ids = sorted(total)
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([np.rint(8 * np.log2(total[k] + 1)).astype(np.uint8).tobytes() for k in ids], pa.binary()), pa.array([int(total[k].sum()) for k in ids], pa.int64())], ["id", "codes", "n"])

    rows = profiled.filter("kind = 1").select("id", "counts").repartition("id").mapInArrow(trimmed(add), "id long, codes binary, n long").collect()
    codes = np.zeros(SKETCH_ROWS * CELLS, np.uint8)
    for r in rows:
        codes[r["id"] * PIECE : (r["id"] + 1) * PIECE] = np.frombuffer(r["codes"], np.uint8)
    load = sum(r["n"] for r in rows) / (SKETCH_ROWS * CELLS)
    return Frequencies(codes, load + 3 * load**0.5)


def bucket_count(profiled: DataFrame) -> int:
    """Buckets of at most some BUCKET prefix tokens, and enough of them for all cores."""
    n, sets = profiled.filter("kind = 0 and key != 0").agg(F.sum("n"), F.count(F.lit(1))).first()
    return max(-(-((100 - PERCENT) * (n or 0) // 100 + MOST * sets) // BUCKET), 2 * profiled.sparkSession.sparkContext.defaultParallelism)


def choose_prefix(tokens: np.ndarray, frequency: np.ndarray) -> tuple[np.ndarray, np.ndarray, int]:
    """(prefix tokens in global order, their estimated list lengths, l) of one set."""
    n = len(tokens)
    order = np.lexsort((tokens, np.log2(frequency).astype(np.int64)))  # octaves, so noise doesn't scatter equal tokens
    base = n - -(-PERCENT * n // 100)
    best, best_cost = 1, np.inf
    lists = np.cumsum(frequency[order[: base + MOST]])
    for l in range(1, MOST + 1):
        if base + l > n:
            break
        read = lists[base + l - 1]
        # each of the list entries beyond the set's own may be a candidate's l-th match
        cost = read + CHECK_COST * max(0.0, read - base - l) / l
        if cost < best_cost:
            best, best_cost = l, cost
    prefix = order[: base + best]
    return tokens[prefix], frequency[prefix], best


def packed_columns(*columns: np.ndarray) -> bytes:
    """Integers byte by byte, all lowest bytes of a column first (the upper ones are mostly zero), compressed."""
    return pa.compress(b"".join(x.view(np.uint8).reshape(len(x), x.itemsize).T.tobytes() for x in columns), "zstd", asbytes=True)


def unpacked_columns(raw: pa.Buffer, *kinds: tuple[int, type]) -> list[np.ndarray]:
    """The columns of the given lengths and types."""
    widths = [np.dtype(kind).itemsize for _, kind in kinds]
    out, at = [], 0
    flat = np.frombuffer(pa.decompress(raw, sum(n * w for (n, _), w in zip(kinds, widths)), "zstd"), np.uint8)
    for (n, kind), w in zip(kinds, widths):
        out.append(flat[at : at + n * w].reshape(w, n).T.copy().view(kind).reshape(n))
        at += n * w
    return out


def pack_tokens(token: np.ndarray, owner: np.ndarray, place: np.ndarray, long: np.ndarray, keys: np.ndarray, heads: np.ndarray, buckets: int) -> Iterator[tuple[int, int, int, bytes, bytes]]:
    """(bucket, tokens, sets, packed tokens, packed rest): tokens of sets (owner is a set's number) in order, so differences are short.

    Each set's key and head (size and l) stand once in a bucket, however many of its tokens are there.
    """
    deal = np.where(long, scramble(token + (keys[owner] % SALTS).astype(np.uint64) * _FACTORS[0]), token)
    order = np.argsort(deal)
    ends = np.searchsorted(deal[order] >> np.uint64(32), (np.arange(buckets + 1, dtype=np.uint64) << np.uint64(32)) // np.uint64(buckets))
    number = np.zeros(len(keys), np.uint32)
    for k in range(buckets):
        part = order[ends[k] : ends[k + 1]]
        if len(part):
            used = np.zeros(len(keys), bool)
            used[owner[part]] = True
            number[used] = np.arange(used.sum(), dtype=np.uint32)
            rest = packed_columns(number[owner[part]], ((place[part] << 1) + long[part]).astype(np.uint32), keys[used], heads[used])
            yield k, len(part), int(used.sum()), packed_columns(np.diff(token[part], prepend=np.uint64(0))), rest


def postings(docs: DataFrame, known: Frequencies, buckets: int) -> DataFrame:
    """(bucket, n, m, tokens, rest): prefix tokens of every set, each set once a task, n of m sets packed into one row by buckets of tokens.

    Long lists are dealt over SALTS parts by their sets' keys; all equal tokens of a part are in one bucket.
    """
    shared = docs.sparkSession.sparkContext.broadcast(known)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingle, seen, often = Shingler(), set(), shared.value
        token, owner, place, length, keys, heads = [], [], [], [], [], []

        def flush() -> Iterator[pa.RecordBatch]:
            columns = np.concatenate(token), np.repeat(np.arange(len(keys)), owner), np.concatenate(place), np.concatenate(length) > LONG, np.array(keys, np.int64), np.array(heads, np.int64)
            for row in pack_tokens(*columns, buckets):
                yield pa.RecordBatch.from_arrays([pa.array([x], kind) for x, kind in zip(row, (pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary()))], ["bucket", "n", "m", "tokens", "rest"])
            for x in (token, owner, place, length, keys, heads):
                x.clear()

        for batch in batches:
            for part in slices(batch, "text", 1 << 20):
                sets, fresh = [], []
                for raw in utf8(part.column(0)):
                    s = shingle(raw)
                    key = set_key(s)
                    if len(s) and key not in seen:
                        seen.add(key)
                        sets.append(s)
                        fresh.append(key)
                if not sets:
                    continue
                every = np.split(often(np.concatenate(sets)), np.cumsum([len(s) for s in sets])[:-1])
                for s, f, key in zip(sets, every, fresh):
                    t, f, l = choose_prefix(s, f)
                    token.append(t)
                    length.append(f)
                    owner.append(len(t))
                    place.append(np.arange(1, len(t) + 1, dtype=np.int64))
                    keys.append(key)
                    heads.append((len(s) << 4) + l)
                if sum(owner) >= PACKED:
                    yield from flush()
        if keys:
            yield from flush()

    return docs.select("text").mapInArrow(trimmed(run), "bucket int, n int, m int, tokens binary, rest binary")


def shared_tokens(rows: list[tuple[int, int, pa.Buffer, pa.Buffer]]) -> pa.RecordBatch | None:
    """(token, salt, cls, packed, sign) of one bucket's tokens that two sets have, and of all parts of long lists; each set once.

    packed holds size, place in the prefix and l; sign is a hash of the part's sets. Rows are unpacked one by one.
    """
    every, first = np.empty(sum(n for n, *_ in rows), np.uint64), 0
    for n, _, tokens, _ in rows:
        np.cumsum(unpacked_columns(tokens, (n, np.uint64))[0], out=every[first : first + n])
        first += n
    order = np.argsort(every)
    twice = np.flatnonzero(np.diff(every[order]) == 0)
    kept = np.zeros(len(every), bool)
    kept[order[twice]] = True
    kept[order[twice + 1]] = True
    del order
    first, token, cls, place, head, long = 0, [], [], [], [], []
    for n, m, _, rest in rows:
        number, where, keys, heads = unpacked_columns(rest, (n, np.uint32), (n, np.uint32), (m, np.int64), (m, np.int64))
        k = kept[first : first + n] | (where & np.uint32(1) == 1)
        token.append(every[first : first + n][k])
        cls.append(keys[number[k]])
        head.append(heads[number[k]])
        place.append(where[k] >> np.uint32(1))
        long.append(where[k] & np.uint32(1) == 1)
        first += n
    token, cls, place, head, long = (np.concatenate(x) for x in (token, cls, place, head, long))
    if not len(token):
        return None
    salt = np.where(long, cls % SALTS, -1).astype(np.int32)
    order = np.lexsort((cls, salt, token))
    token, cls, place, head, salt = (x[order] for x in (token, cls, place, head, salt))
    fresh = np.append(True, (token[1:] != token[:-1]) | (salt[1:] != salt[:-1]))
    once = fresh | np.append(True, cls[1:] != cls[:-1])  # tasks may have had the same set
    token, cls, place, head, salt, fresh = (x[once] for x in (token, cls, place, head, salt, fresh))
    starts = np.flatnonzero(fresh)
    sizes = np.diff(np.append(starts, len(token)))
    sign = np.repeat(np.bitwise_xor.reduceat(scramble(cls.view(np.uint64)), starts), sizes)
    k = (np.repeat(sizes, sizes) > 1) | (salt >= 0)
    packed = ((head >> 4) << 32) + (place.astype(np.int64) << 4) + (head & 15)
    return pa.RecordBatch.from_arrays([pa.array(token[k].view(np.int64)), pa.array(salt[k]), pa.array(cls[k]), pa.array(packed[k]), pa.array(sign[k].view(np.int64))], ["token", "salt", "cls", "packed", "sign"])


def shared_postings(raw: DataFrame, buckets: int) -> DataFrame:
    """(token, salt, cls, packed, sign) of all buckets; a task holds one bucket at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, rows = None, []
        for batch in batches:
            for k, n, m, tokens, rest in zip(*(batch.column(j).to_pylist() for j in range(3)), batch.column(3), batch.column(4)):
                if k != now and rows:
                    if (out := shared_tokens(rows)) is not None:
                        yield out
                    rows = []
                now = k
                rows.append((n, m, tokens.as_buffer(), rest.as_buffer()))
        if rows and (out := shared_tokens(rows)) is not None:
            yield out

    return raw.repartition(buckets, "bucket").sortWithinPartitions("bucket").mapInArrow(trimmed(run), "token long, salt int, cls long, packed long, sign long")


def wanted_filter(ids: DataFrame, hashed: bool = False) -> np.ndarray:
    """A fixed-size bit filter of ids (hashed: they are hashes already), built on the executors; false positives only cost time."""
    h = F.pmod("id" if hashed else F.xxhash64("id"), F.lit(FILTER_BITS)) + 1  # the bitmap functions count from 1
    rows = ids.select(h.alias("h")).groupBy(F.bitmap_bucket_number("h").alias("b")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("h")).alias("bits")).collect()
    out = np.zeros(FILTER_BITS // 8 + 8192, np.uint8)
    for r in rows:
        at = (r["b"] - 1) * 4096
        part = np.frombuffer(bytes(r["bits"]), np.uint8)
        out[at : at + len(part)] |= part
    return out


def sets_of(docs: DataFrame, ids: DataFrame, keys: DataFrame) -> DataFrame:
    """(cls, tokens): sets of the documents whose ids and keys pass the two filters, each set once a task."""
    shared = docs.sparkSession.sparkContext.broadcast((wanted_filter(ids), wanted_filter(keys.select(F.col("cls").alias("id")), True)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingle, seen, (bits, named) = Shingler(), set(), shared.value
        for batch in batches:
            at = batch.column(0).to_numpy(zero_copy_only=False)
            batch = batch.filter(pa.array((bits[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1))
            for part in slices(batch, "text", 1 << 20):
                keys, sets = [], []
                for raw in utf8(part.column(1)):
                    s = shingle(raw)
                    key = set_key(s)
                    place = key % FILTER_BITS
                    if len(s) and key not in seen and named[place >> 3] >> (place & 7) & 1:
                        seen.add(key)
                        keys.append(key)
                        sets.append(s.view(np.int64))
                if keys:
                    yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(sets, pa.list_(pa.int64()))], ["cls", "tokens"])

    rows = docs.select(F.pmod(F.xxhash64(F.col("doc_id").cast("long")), F.lit(FILTER_BITS)).alias("h"), "text")
    return rows.mapInArrow(trimmed(run), "cls long, tokens array<bigint>")


def endpoints(pairs: DataFrame) -> DataFrame:
    """(cls) of all sets that pairs name; each side is made distinct before they meet."""
    return pairs.select(F.col("a").alias("cls")).distinct().union(pairs.select(F.col("b").alias("cls")).distinct()).distinct()


def linked(pairs: DataFrame, sets: DataFrame, named: DataFrame) -> DataFrame:
    """pairs (a, b) with the exact answer in column `link`. Only the sets that some pair names are shuffled.

    Sets that several tasks gave are made one by the exchange that also brings them to their pairs.
    """
    sets = sets.join(F.broadcast(named.limit(FEW)), "cls", "left_semi") if named.limit(FEW + 1).count() <= FEW else sets
    sets = sets.groupBy("cls").agg(F.first("tokens").alias("tokens"))
    full = pairs.join(sets.select(F.col("cls").alias("a"), F.col("tokens").alias("x")), "a").join(sets.select(F.col("cls").alias("b"), F.col("tokens").alias("y")), "b")
    counted = full.select("a", "b", F.size(F.array_intersect("x", "y")).cast("long").alias("both"), (F.size("x") + F.size("y")).cast("long").alias("sizes"))
    return counted.select("a", "b", (100 * F.col("both") >= PERCENT * (F.col("sizes") - F.col("both"))).alias("link"))


def components(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """(cls, comp): comp is the smallest cls of the component; nodes without edges are their own.

    Alternating large-star and small-star rounds; each is linear in the edges and their number is logarithmic.
    """
    e, was = cut(edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).filter("u != v").distinct()), None
    while True:
        both = e.union(e.select(F.col("v"), F.col("u")))
        low = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = both.filter("v > u").join(low, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(low, "u").select(F.explode(F.array(F.struct(F.col("u").alias("u"), F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e")).select("e.*").filter("u != v").distinct()
        e = cut(small)
        now = tuple(e.agg(F.count(F.lit(1)), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if now == was:
            break
        was = now
        release(e.sparkSession)
    return nodes.join(e.select(F.col("u").alias("cls"), F.col("v").alias("comp")), "cls", "left").select("cls", F.coalesce("comp", "cls").alias("comp"))


def near(n: str, m: str):
    """The sizes of two sets allow a link."""
    return F.least(n, m) * 100 >= F.greatest(n, m) * PERCENT


def needed(n: str, l: str, m: str, k: str):
    """Prefix tokens that two linking sets of sizes n and m with multiplicities l and k must share.

    All common tokens up to the earlier prefix's end lie in both prefixes, and at most the rest of one set follows. So the
    intersection is at most the shared prefix tokens plus the longer rest, and a link needs 75 / 175 of both sizes.
    """
    both = F.ceil(PERCENT * (F.col(n) + F.col(m)) / (100.0 + PERCENT) - 1e-9)
    rest = lambda size, least: F.ceil(PERCENT * F.col(size) / 100.0 - 1e-9) - F.col(least)
    return F.greatest(F.least(l, k), both - F.greatest(rest(n, l), rest(m, k)))


def merged_lists(raw: DataFrame, buckets: int) -> DataFrame:
    """(token, cls, n, l, p, w): prefix tokens with at least two sets; those with equal lists are one, w of them in the set, the first at place p.

    A long list's hash is put together from its salts and goes back to each of them, so no list meets in one task.
    """
    # most tokens have one set: they go where the packed rows meet, before there are rows of single tokens
    shared = cut(shared_postings(raw, buckets))
    release(raw.sparkSession)  # the packed rows' shuffle, the largest, goes before the lists are written
    long = shared.filter("salt >= 0").groupBy("token").agg(F.bit_xor(F.xxhash64("cls")).alias("whole"), F.min("cls").alias("lo"), F.max("cls").alias("hi"), F.collect_set("salt").alias("salts"))
    long = long.select("token", F.explode("salts").alias("salt"), "whole", "lo", "hi")
    # lists without salts are whole already, so only the salted rows are shuffled to meet their list's hash
    salted = shared.filter("salt >= 0").join(long.filter("lo != hi"), ["token", "salt"]).select(F.col("whole").alias("token"), "cls", "packed")
    signed = shared.filter("salt < 0").select(F.col("sign").alias("token"), "cls", "packed").unionByName(salted)
    merged = signed.groupBy("token", "cls").agg(F.min("packed").alias("packed"), F.count(F.lit(1)).cast("int").alias("w"))
    n, place, least = F.shiftright("packed", 32), F.shiftright("packed", 4).bitwiseAND(F.lit((1 << 28) - 1)), F.col("packed").bitwiseAND(F.lit(15))
    return cut(merged.select("token", "cls", n.cast("int").alias("n"), least.cast("int").alias("l"), place.cast("int").alias("p"), "w"))


def star_pairs(live: DataFrame, done: DataFrame | None, turn: int) -> DataFrame:
    """For each set the MATES untried sets of other components that share most prefix tokens with it, among CENTRES of each list.

    Centres are sets of a list's largest components, first in as many hash orders, and one of its smallest; the orders change
    with the turn, so sets left out are tried against ever new sets of a large component.
    """
    fields, group = ("comp", "cls", "n", "l", "w"), Window.partitionBy("token")
    end = lambda k, sign: F.min(F.struct((sign * F.col("members")).alias("rank"), F.xxhash64("cls", F.lit(turn * CENTRES + k)).alias("order"), *fields)).over(group)
    # one exchange of thin rows by token, before the structs are made: every row sees its list's centres without a join
    lists = live.select("token", "members", *fields).repartition("token").withColumns({"lo": F.min("comp").over(group), "hi": F.max("comp").over(group), **{f"o{k}": end(k, -1 if k else 1) for k in range(CENTRES)}}).filter("lo != hi")
    plain = [F.struct(*[F.col(f"o{k}.{c}").alias(c) for c in fields]) for k in range(CENTRES)]
    tries = lists.select(*fields, F.explode(F.array_distinct(F.array(*plain))).alias("o")).filter((F.col("comp") != F.col("o.comp")) & near("n", "o.n"))
    counted = tries.groupBy("cls", F.col("o.cls").alias("mate")).agg(F.sum(F.least("w", "o.w")).alias("c"), F.min(needed("n", "l", "o.n", "o.l")).alias("need")).filter("c >= need")
    counted = counted.select("cls", "mate", "c", F.least("cls", "mate").alias("a"), F.greatest("cls", "mate").alias("b"))
    if done is not None:
        counted = counted.join(done, ["a", "b"], "left_anti")
    best = Window.partitionBy("cls").orderBy(F.col("c").desc(), "mate")
    return counted.withColumn("k", F.row_number().over(best)).filter(F.col("k") <= MATES).select("a", "b").distinct()


def hopeful(live: DataFrame) -> DataFrame:
    """(cls, comp, n, l, token, p, w, bucket, near, far) of the tokens by which a set can still meet partners of the size bucket `near`.

    For each bucket of partners' sizes the set's tokens that also a set of another component in that bucket has are weighed
    together. Where they weigh less than any link with the bucket needs, the bucket is hopeless. Else a partner's first common
    token leaves at least the needed weight from there on, so tokens with more than the excess before them are `far`: they can
    be common ones but not first. All rows are thin, at most one for each bucket of a token.
    """
    whole = 100 + PERCENT
    # one exchange of thin rows by token: a list's buckets, some hundreds at most, come to its rows without a join
    rows = live.select("cls", "comp", "n", "l", "token", "p", "w", F.floor(F.log(F.col("n").cast("double")) / math.log(SIZE_STEP)).cast("int").alias("bucket")).repartition("token")
    alike = Window.partitionBy("token", "bucket")
    bounds = {"lo": F.min("comp"), "hi": F.max("comp"), "least": F.min("n"), "most": F.max("n"), "k": F.min("l"), "v": F.max("w")}
    rows = rows.withColumns({c: x.over(alike) for c, x in bounds.items()}).withColumn("lists", F.collect_set(F.struct(F.col("bucket").alias("near"), *bounds)).over(Window.partitionBy("token")))
    fits = lambda x: ((x["lo"] != F.col("comp")) | (x["hi"] != F.col("comp"))) & (PERCENT * x["least"].cast("long") <= 100 * F.col("n").cast("long")) & (PERCENT * F.col("n").cast("long") <= 100 * x["most"].cast("long"))
    # rows meet by sets before there is one for each bucket, and stay there until they are distinct
    rows = rows.select("cls", "comp", "n", "l", "token", "p", "w", "bucket", F.transform(F.filter("lists", fits), lambda x: F.struct(*[x[c].alias(c) for c in ("near", "least", "most", "k", "v")])).alias("lists")).filter(F.size("lists") > 0).repartition("cls")
    met = rows.select("cls", "comp", "n", "l", "token", "p", "w", "bucket", F.inline("lists"))
    group = Window.partitionBy("cls", "near")
    weight, before = F.least("w", "v").cast("long"), group.orderBy("p", "token").rowsBetween(Window.unboundedPreceding, -1)
    met = met.withColumns({"c": F.sum(weight).over(group), "before": F.coalesce(F.sum(weight).over(before), F.lit(0)), "least": F.min("least").over(group), "most": F.max("most").over(group), "k": F.min("k").over(group)})
    up = lambda x: f"({PERCENT} * cast({x} as long) + 99) div 100"
    both = f"({PERCENT} * (cast(n as long) + least) + {whole - 1}) div {whole}"
    met = met.withColumn("need", F.expr(f"greatest(least(l, k), {both} - greatest({up('n')} - l, {up('most')} - k))")).filter("c >= need")
    return met.select("cls", "comp", "n", "l", "token", "p", "w", "bucket", "near", (F.col("before") > F.col("c") - F.col("need")).alias("far"))


def cross_pairs(live: DataFrame, done: DataFrame | None) -> DataFrame:
    """Every pair of different components that shares enough prefix tokens and is not done.

    A pair is found by its first common token: a link of sizes n <= m needs o common tokens, of which o - 1 are behind the first
    in both sets, so its places are at most n - o + 1 and m - o + 1. Rare tokens come first: sets with too many tokens of their
    own have no common ones there and make no rows. Two passes of thin rows leave the sets and tokens that can share enough
    with partners of some size; only what can be a first common token, with a set that can meet it there, then carries its set's remaining prefix, so the join
    itself makes a pair only at the first token that both have, and only if their prefixes share as many tokens as a link needs.
    """
    whole = 100 + PERCENT
    once = cut(hopeful(live).select("cls", "comp", "n", "l", "token", "p", "w").distinct())
    release(live.sparkSession)
    met = cut(hopeful(once))
    # both sides of a pair have the same key, so joins by it need no exchange for each side
    key = F.xxhash64("token", F.least("bucket", "near"), F.greatest("bucket", "near"))
    heads = met.filter(~F.col("far") & F.expr(f"p <= n - cast(ceil({PERCENT} * cast(n as long) / 100.0) as long) + 1")).select("cls", "comp", "n", "l", "token", "p", "bucket", "near", key.alias("key"))
    o = f"({PERCENT} * (cast(n as long) + n2) + {whole - 1}) div {whole}"
    places = F.expr(f"p <= n - {o} + 1 and p2 <= n2 - {o} + 1")
    # no equalities beside the key's: the joins would want them in the exchange, where the two sides differ
    same = F.expr("(token ^ token2) = 0 and bucket - near2 = 0 and near - bucket2 = 0")
    meet = (F.col("key") == F.col("key2")) & same & (F.col("comp") != F.col("comp2")) & near("n", "n2") & places
    heads = heads.join(heads.select(*[F.col(c).alias(f"{c}2") for c in heads.columns]), meet, "left_semi")
    # tokens that two sets share are among those that each of them has for the other's size, so only these are carried
    prefixes = met.groupBy("cls", "near").agg(F.array_sort(F.collect_list(F.struct("p", "token", "w"))).alias("pre"))
    prefixes = prefixes.select("cls", "near", F.col("pre.token").alias("tokens"), F.col("pre.w").alias("ws"))
    first = heads.join(prefixes, ["cls", "near"]).select(*heads.columns, "tokens", "ws").repartition("key")
    first = first.withColumns({"at": F.map_from_arrays("tokens", "ws"), "prev": F.expr("slice(tokens, 1, cast(array_position(tokens, token) as int) - 1)")}).drop("tokens", "ws")
    other = first.select(*[F.col(c).alias(f"{c}2") for c in first.columns])
    ordered = F.expr("n < n2 or (n = n2 and cls < cls2)")
    shared = F.aggregate(F.array_intersect(F.map_keys("at"), F.map_keys("at2")), F.lit(0), lambda c, t: c + F.least(F.element_at("at", t), F.element_at("at2", t)))
    found = first.join(other, meet & ordered & ~F.arrays_overlap("prev", "prev2") & (shared >= needed("n", "l", "n2", "l2"))).select(F.least("cls", "cls2").alias("a"), F.greatest("cls", "cls2").alias("b"))
    return found if done is None else found.join(done, ["a", "b"], "left_anti")


def place_classes(docs: DataFrame, rounds: int = ROUNDS) -> tuple[DataFrame, DataFrame]:
    """(doc_id, n_shingles, cls) of every row; (cls, least, comp) of every set that isn't empty, least being its smallest doc_id."""
    profiled = cut(profile(docs))
    rows = cut(profiled.filter("kind = 0").select(F.col("id").alias("doc_id"), F.col("n").alias("n_shingles"), F.col("key").alias("cls")))
    known, buckets, profiled = frequencies(profiled), bucket_count(profiled), None
    release(docs.sparkSession)  # the tasks' sketches are summed up and go, too
    lists = merged_lists(postings(docs, known, buckets), buckets)
    release(docs.sparkSession)
    nodes = cut(lists.select("cls").distinct())
    comp = nodes.withColumn("comp", F.col("cls"))
    first = rows.filter("cls != 0").groupBy("cls").agg(F.min("doc_id").alias("id"))
    done = links = sets = had = None
    k, stars = 0, rounds > 0
    while True:
        if k:
            live = lists.join(comp.join(comp.groupBy("comp").agg(F.count(F.lit(1)).alias("members")), "comp"), "cls")
        else:
            live = lists.withColumn("comp", F.col("cls")).withColumn("members", F.lit(1).cast("long"))
        pairs = cut(star_pairs(live, done, k) if stars else cross_pairs(live, done))
        release(docs.sparkSession)  # the driver, too, is small
        named = cut(endpoints(pairs))
        asked = named if had is None else cut(named.join(had, "cls", "left_anti"))
        if asked.limit(1).count():
            more = cut(sets_of(docs, first.join(asked, "cls", "left_semi").select("id"), asked))
            sets, had = (more, asked) if sets is None else (sets.unionByName(more), had.unionByName(asked))
        found = False
        if sets is not None:
            release(docs.sparkSession)
            tested = cut(linked(pairs, sets, named))
            release(docs.sparkSession)
            done = tested.select("a", "b") if done is None else done.union(tested.select("a", "b"))
            fresh = tested.filter("link").select("a", "b")
            links = fresh if links is None else links.union(fresh)
            found = fresh.limit(1).count() > 0
            if found:
                comp = cut(components(nodes, links))
        if not stars:
            break
        release(docs.sparkSession)
        k, stars = k + 1, found and k + 1 < rounds
    of_class = rows.filter("cls != 0").groupBy("cls").agg(F.min("doc_id").alias("least"))
    return rows, of_class.join(comp, "cls", "left").withColumn("comp", F.coalesce("comp", "cls"))


def join_documents(docs: DataFrame, rounds: int = ROUNDS) -> DataFrame:
    """(doc_id, n_shingles, component_id) of every row."""
    rows, placed = place_classes(docs, rounds)
    named = placed.join(placed.groupBy("comp").agg(F.min("least").alias("component_id")), "comp").select("cls", "component_id")
    return rows.join(named, "cls", "left").select("doc_id", "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))


def with_class(docs: DataFrame, name: str) -> DataFrame:
    """docs with the key of each row's set in a column of the given name."""
    at = docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingle = Shingler()
        for batch in batches:
            for part in slices(batch, "text", 4 << 20):
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array([set_key(shingle(r)) for r in utf8(part.column(at))], pa.int64())], [*part.schema.names, name])

    return docs.mapInArrow(trimmed(run), StructType([*docs.schema.fields, StructField(name, LongType())]))


def first_of_components(docs: DataFrame) -> DataFrame:
    """One row of each component: smallest doc_id (null last), then smallest class key, then the first by text and rest.

    Sets without words link with nothing: one of their rows stays for each doc_id, and all of those without an id.
    A doc_id that occurs once names its row; only for repeated and null ids the rows' class keys are needed.
    """
    rows, placed = place_classes(docs)
    cls, kept_id, kept_key, place = (free_name(docs, x) for x in ("cls", "kept_id", "kept_key", "place"))
    best = placed.groupBy("comp").agg(F.min(F.struct(F.col("least").isNull().alias("none"), "least", "cls")).alias("w"))
    blank = rows.filter("cls = 0").select(F.col("doc_id").alias(kept_id), F.col("cls").alias(kept_key)).distinct()
    keep = cut(best.select(F.col("w.least").alias(kept_id), F.col("w.cls").alias(kept_key)).union(blank))
    repeated = rows.filter("doc_id is not null").groupBy("doc_id").agg(F.count(F.lit(1)).alias("k")).filter("k > 1").select("doc_id")
    names = docs.columns
    once = docs.join(keep.select(F.col(kept_id).alias("doc_id")), "doc_id", "left_semi").join(repeated, "doc_id", "left_anti").select(*names)
    keyed = with_class(docs.join(repeated, "doc_id", "left_semi").select(*names).unionByName(docs.filter("doc_id is null")), cls)
    nameless = keyed.filter(F.col("doc_id").isNull() & (F.col(cls) == 0)).select(*names)
    # the limit on the place prunes each task's rows before they are shuffled
    order = Window.partitionBy("doc_id", cls).orderBy(F.xxhash64(F.coalesce("text", F.lit(""))), *[F.col(f"`{c}`") for c in names if c not in ("doc_id", "text")])
    again = keyed.filter(F.col("doc_id").isNotNull() | (F.col(cls) != 0)).withColumn(place, F.row_number().over(order)).filter(F.col(place) <= 1)
    again = again.join(keep, F.col("doc_id").eqNullSafe(F.col(kept_id)) & (F.col(cls) == F.col(kept_key)), "left_semi").select(*names)
    return once.unionByName(nameless).unionByName(again)
