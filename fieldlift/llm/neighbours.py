"""Approximate nearest neighbours by a hash-prefix forest.

Each tree gives a vector a long bit string of random-hyperplane signs; a tree is the array of its sorted strings. A query
descends in every tree to its longest matching prefix and then ascends in all trees at the same level until the
nodes reached together hold at least `breadth` vectors; those are compared exactly. Largest inner product is
reduced to the angle by one more coordinate that brings all indexed vectors to the largest norm.

The indexed vectors are dealt by hash over blocks of about `shard` vectors, the queries over tiles of bounded size. A block keeps
the sorted arrays of its part of every tree; codes are made inside it, so vectors are shuffled once for each tile and not for each
tree. The number of strings that share a prefix adds up over the blocks: the first pass sums these counts by level, which gives
each query its stop level; the second compares its distinct candidates block by block. So the blocks' size never changes a
result. Equal vectors are one class with its smallest ids; what a query can return of a class is bounded, so a vector shared by a
third of the rows costs no more than any other.

Defined cases: vectors that are null, empty, zero or hold null or non-finite components take no part, neither as queries
nor as candidates; shorter vectors count as padded with zeros; of rows that share a vec_id each is a query and a candidate of
the others; ties go to the smaller vec_id; an empty table gives no rows.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import cut

#: Parameters: trees, bits of a string, least entries at which the synchronous ascent stops, vectors of a block, queries of a tile.
TREES, BITS, BREADTH, SHARD, TILE = 24, 32, 32_000, 1 << 13, 1 << 13
#: Entries at which the ascent stops as a share of the indexed vectors: what keeps recall at 0.9 where vectors have no structure.
SHARE = 0.5


def usable(vectors: DataFrame) -> DataFrame:
    """(vec_id, embedding as array<double>) of the rows that take part."""
    e = F.col("embedding")
    fine = F.forall(e, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return vectors.select(F.col("vec_id").cast("long").alias("vec_id"), e.cast("array<double>").alias("embedding")).filter(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & fine & F.exists("embedding", lambda x: x != 0.0))


def class_key() -> Column:
    """A 64-bit key of equal vectors."""
    return F.xxhash64("embedding")


def classes_of(rows: DataFrame, keep: int) -> DataFrame:
    """(cid, embedding, least, ids): equal vectors once, with their keep smallest ids. The filter on the rank prunes before the shuffle."""
    first = Window.partitionBy("embedding").orderBy("vec_id")
    return (
        rows.withColumn("place", F.row_number().over(first)).filter(F.col("place") <= keep)
        .groupBy("embedding").agg(F.array_sort(F.collect_list("vec_id")).alias("ids"))
        .select(class_key().alias("cid"), "embedding", F.element_at("ids", 1).alias("least"), "ids")
    )


def planes(trees: int, bits: int, dim: int, seed: int = 5) -> np.ndarray:
    return np.random.default_rng(seed).standard_normal((trees * bits, dim))


def matrix(vectors: pd.Series, dim: int) -> np.ndarray:
    out = np.zeros((len(vectors), dim))
    for i, v in enumerate(vectors):
        out[i, : len(v)] = v
    return out


def hash_strings(x: np.ndarray, top: float | None, trees: int, bits: int) -> np.ndarray:
    """(tree, vector) codes; indexed vectors are brought to the norm `top` by one more coordinate, queries have 0 there."""
    normals = planes(trees, bits, x.shape[1] + 1).T
    weights = 1 << np.arange(bits - 1, -1, -1, dtype=np.int64)
    out = np.empty((trees, len(x)), np.int64)
    for at in range(0, len(x), 512):
        part = x[at : at + 512]
        rest = np.zeros((len(part), 1)) if top is None else np.sqrt(np.maximum(0.0, top * top - (part * part).sum(axis=1, keepdims=True)))
        out[:, at : at + 512] = ((np.hstack([part, rest]) @ normals > 0).reshape(len(part), trees, bits) @ weights).T
    return out


def node_bounds(codes: np.ndarray, wanted: np.ndarray, bits: int, level: int | np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Range in the sorted codes that shares the first `level` bits with each wanted code."""
    drop = bits - np.asarray(level, np.int64)
    low = (wanted >> drop) << drop
    return np.searchsorted(codes, low, "left"), np.searchsorted(codes, low + (np.int64(1) << drop), "left")


def search(vectors: DataFrame, k: int = 20, every: int = 20, trees: int = TREES, bits: int = BITS, breadth: int | None = None, shard: int = SHARD) -> DataFrame:
    """(query_id, rank, vec_id, score, n_compared): the k nearest found for every row whose vec_id is divisible by `every`.

    n_compared is the number of distinct vectors that the query was compared with, its own included.
    The breadth follows the number of indexed vectors unless it is given; it is never too small for k candidates.
    """
    rows = usable(vectors)
    classes = cut(classes_of(rows, k + 1))
    norm = F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x * x))
    n, dim, top = classes.agg(F.count(F.lit(1)), F.max(F.size("embedding")), F.max(norm)).first()
    if not n:
        return vectors.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double, n_compared long")
    breadth = max(BREADTH, math.ceil(SHARE * n)) if breadth is None else breadth
    breadth = max(breadth, trees * (k + 1))  # so one tree alone gives k vectors beside the query
    queries = cut(rows.filter(F.col("vec_id") % every == 0).select("vec_id", class_key().alias("cid"), "embedding"))
    asked = cut(queries.groupBy("cid").agg(F.first("embedding").alias("embedding")))
    n_blocks, n_tiles = math.ceil(n / shard), max(1, math.ceil(asked.count() / TILE))
    deal = lambda count, salt: F.pmod(F.xxhash64("cid", F.lit(salt)), F.lit(count)).cast("int")
    every_one = lambda count: F.explode(F.sequence(F.lit(0), F.lit(count - 1)))
    blocks = classes.select("cid", "embedding", "least", deal(n_blocks, 1).alias("block")).withColumn("tile", every_one(n_tiles)).groupBy("block", "tile")

    def tiles(of: DataFrame):
        return of.withColumn("tile", deal(n_tiles, 2)).withColumn("block", every_one(n_blocks)).groupBy("block", "tile")

    def count_levels(inside: pd.DataFrame, q: pd.DataFrame) -> pd.DataFrame:
        counts = np.zeros((len(q), bits + 1), np.int64)
        if len(inside) and len(q):
            codes = np.sort(hash_strings(matrix(inside["embedding"], dim), top, trees, bits), axis=1)
            for tree, wanted in zip(codes, hash_strings(matrix(q["embedding"], dim), None, trees, bits)):
                order = np.argsort(wanted)
                for level in range(bits + 1):
                    lo, hi = node_bounds(tree, wanted[order], bits, level)
                    if level and not (hi > lo).any():
                        break
                    counts[order, level] += hi - lo
        return pd.DataFrame({"cid": q["cid"], "counts": pd.Series(list(counts), dtype=object)})

    depth = blocks.cogroup(tiles(asked)).applyInPandas(count_levels, "cid long, counts array<bigint>")
    sums = depth.groupBy("cid").agg(*[F.sum(F.element_at("counts", i + 1)).alias(f"c{i}") for i in range(bits + 1)])
    # all trees stop at one level: the deepest whose nodes together hold the breadth
    stop = F.coalesce(*[F.when(F.col(f"c{i}") >= breadth, F.lit(i)) for i in reversed(range(bits + 1))], F.lit(0))
    reached = cut(sums.select("cid", stop.cast("int").alias("stop")))

    def nearest(inside: pd.DataFrame, q: pd.DataFrame) -> pd.DataFrame:
        out: list[tuple[np.ndarray, ...]] = []
        if len(inside) and len(q):
            ids, least, x = inside["cid"].to_numpy(np.int64), inside["least"].to_numpy(np.int64), matrix(inside["embedding"], dim)
            wanted = matrix(q["embedding"], dim)
            codes = hash_strings(x, top, trees, bits)
            order = np.argsort(codes, axis=1, kind="stable")
            level = q["stop"].to_numpy(np.int64)
            bounds = [node_bounds(codes[t][order[t]], c, bits, level) for t, c in enumerate(hash_strings(wanted, None, trees, bits))]
            for i, cid in enumerate(q["cid"].to_numpy(np.int64)):
                reachable = np.zeros(len(ids), bool)
                for places, (lo, hi) in zip(order, bounds):
                    reachable[places[lo[i] : hi[i]]] = True
                at = np.flatnonzero(reachable)
                if not len(at):
                    continue
                rough = x[at] @ wanted[i]
                # rounding may reorder near-ties, so a few more than k + 1 get the exact score
                near = np.argpartition(-rough, k + 8)[: k + 9] if len(at) > k + 9 else np.arange(len(at))
                score = np.add.accumulate(x[at[near]] * wanted[i], axis=1)[:, -1]
                best = np.lexsort((least[at[near]], -score))[: k + 1]
                chosen = at[near[best]]
                out.append((np.full(len(best), cid), ids[chosen], least[chosen], score[best], np.r_[len(at), np.zeros(len(best) - 1, np.int64)]))
        columns = [np.concatenate(c) for c in zip(*out)] if out else [np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0), np.empty(0, np.int64)]
        return pd.DataFrame(dict(zip(("cid", "found", "least", "score", "compared"), columns)))

    hits = cut(blocks.cogroup(tiles(asked.join(reached, "cid"))).applyInPandas(nearest, "cid long, found long, least long, score double, compared long"))
    compared = hits.groupBy("cid").agg(F.sum("compared").alias("n_compared"))
    best = Window.partitionBy("cid").orderBy(F.col("score").desc(), "least", "found")
    hits = hits.withColumn("r", F.row_number().over(best)).filter(F.col("r") <= k + 1)
    found = hits.join(classes.select(F.col("cid").alias("found"), "ids"), "found").groupBy("cid").agg(F.collect_list(F.struct("score", "ids")).alias("near")).join(compared, "cid")
    # at most (k + 1) classes of (k + 1) ids each for a query
    own = queries.select(F.col("vec_id").alias("query_id"), "cid").join(found, "cid")
    candidates = F.flatten(F.transform("near", lambda c: F.transform(c["ids"], lambda v: F.struct((-c["score"]).alias("s"), v.alias("v")))))
    # one place of the query's own id is its own row; other rows of that id are candidates like any
    mine = F.array_position(F.transform(candidates, lambda c: c["v"]), F.col("query_id"))
    others = F.when(mine > 0, F.concat(F.slice(candidates, F.lit(1), mine - 1), F.slice(candidates, mine + 1, F.size(candidates)))).otherwise(candidates)
    ranked = F.slice(F.array_sort(others), 1, k)
    return own.select("query_id", "n_compared", F.posexplode(ranked).alias("pos", "c")).select("query_id", (F.col("pos") + 1).cast("int").alias("rank"), F.col("c.v").alias("vec_id"), (-F.col("c.s")).alias("score"), "n_compared")
