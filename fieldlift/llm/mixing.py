"""Mixing sources to target weights by entropy balancing (DataFrame functions only).

Every document starts at rate 1. Under the constraint that a source's expected words equal its target
and that no rate exceeds CAP, the rates closest in relative entropy are min(CAP, exp(lambda * x)) with
x = size / mean size of the source. The dual in lambda is convex and separable by source; all sources
take one safeguarded Newton step per pass over the (source, size) histogram, never over the documents.
Rates become copies by systematic rounding along the size order, so a source's error stays below about
half of its largest document, and by a hash order within equal sizes, so reruns agree.

Defined cases: null or empty text has size 0; a null source is a source of its own, ranked last; repeated
rows are rows; an empty table gives an empty result; other columns are carried in a struct, so any name is left alone.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import WORD, cut, numbered, release

#: Fixed values of the mix: weights repeating over the sources in code-point order, share, largest rate.
WEIGHTS = (3.0, 1.0, 2.0)
SHARE = 1.5
CAP = 2.0
#: Hash buckets within one (source, size): no window sees more than this fraction of an equal-size group.
BUCKETS = 4096


def with_size(docs: DataFrame, carry: bool = False) -> DataFrame:
    """doc_id, _size (words), _skey (null-safe source key) and _bucket; with carry the whole row as a struct beside them."""
    return docs.select(
        *([F.struct("*").alias("_whole")] if carry else []),
        "doc_id",
        F.regexp_count(F.coalesce("text", F.lit("")), F.lit(WORD)).cast("long").alias("_size"),
        F.coalesce(F.concat(F.lit("="), F.col("source")), F.lit("-")).alias("_skey"),
        F.pmod(F.xxhash64(F.col("doc_id")), F.lit(BUCKETS)).alias("_bucket"),
    )


def source_targets(hist: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, cap: float = CAP) -> DataFrame:
    """(_skey, _total, _target): targets by weight, stopped at cap times the source's size, excess reshared.

    The reshared fixed point is a water level: target = min(cap * total, weight * level). Each round is one
    aggregate over the source table whose result is two numbers.
    """
    totals = hist.groupBy("_skey").agg(F.sum(F.col("_size") * F.col("_n")).alias("_total"), F.sum("_n").alias("_docs"))
    ranked = numbered(totals, [F.when(F.col("_skey") == "-", 1).otherwise(0), F.col("_skey").asc()], "_rank")
    pick = F.element_at(F.array(*[F.lit(w) for w in weights]), (F.col("_rank") % len(weights) + 1).cast("int"))
    src = cut(ranked.withColumn("_w", pick).withColumn("_room", F.col("_total") * F.lit(cap)))
    whole = src.agg(F.sum("_total")).first()[0] or 0
    level, goal = 0.0, share * whole
    while whole:
        full = F.col("_room") < F.col("_w") * F.lit(level)
        used, free = src.agg(F.sum(F.when(full, F.col("_room"))), F.sum(F.when(~full, F.col("_w")))).first()
        if not free or (raised := (goal - (used or 0.0)) / free) <= level:
            break
        level = raised
    return src.select("_skey", "_total", "_docs", F.least(F.col("_room"), F.col("_w") * F.lit(level)).alias("_target"))


def newton_rates(hist: DataFrame, targets: DataFrame, cap: float = CAP, tolerance: float = 1e-7, rounds: int = 60) -> DataFrame:
    """(_skey, _lam, _mean, _full): the dual optimum of each source, by distributed safeguarded Newton steps."""
    state = targets.select(
        "_skey",
        "_target",
        (F.col("_total") / F.col("_docs")).alias("_mean"),
        (F.col("_target") >= F.col("_total") * F.lit(cap * (1 - 1e-12))).alias("_full"),
        F.lit(0.0).alias("_lam"),
        F.lit(-700.0).alias("_lo"),
        F.lit(700.0).alias("_hi"),
        F.lit(1.0).alias("_off"),
    )
    state = cut(state)
    x = F.col("_size") / F.col("_mean")
    rate = F.least(F.lit(cap), F.exp(F.least(F.col("_lam") * x, F.lit(50.0))))
    mass = F.col("_n") * F.col("_size")
    sums = [
        F.sum(mass * rate).alias("_value"),
        F.sum(F.when(rate < cap, mass * x * rate).otherwise(0.0)).alias("_slope"),
        *[F.first(c).alias(c) for c in ("_target", "_mean", "_full", "_lam", "_lo", "_hi")],
    ]
    for _ in range(rounds):
        gap = F.col("_value") - F.col("_target")
        lo, hi = F.when(gap < 0, F.col("_lam")).otherwise(F.col("_lo")), F.when(gap > 0, F.col("_lam")).otherwise(F.col("_hi"))
        step = F.col("_lam") - gap / F.nullif(F.col("_slope"), F.lit(0.0))
        inside = (step > lo) & (step < hi)
        wider = F.when(lo <= -700.0, hi * F.when(hi > 0, 0.5).otherwise(2.0) - 1).when(hi >= 700.0, lo * F.when(lo < 0, 0.5).otherwise(2.0) + 1).otherwise((lo + hi) / 2)
        off = F.abs(gap) / F.greatest(F.col("_target"), F.lit(1.0))
        settled = F.col("_full") | (off <= tolerance)
        state = cut(
            hist.filter(F.col("_size") > 0).join(state.drop("_off"), "_skey").groupBy("_skey").agg(*sums).select(
                "_skey", "_target", "_mean", "_full",
                F.when(settled, F.col("_lam")).when(inside, step).otherwise(wider).alias("_lam"),
                lo.alias("_lo"), hi.alias("_hi"), F.when(settled, 0.0).otherwise(off).alias("_off"),
            )
        )
        if not (state.agg(F.max("_off")).first()[0] or 0.0):
            break
        release(state.sparkSession)
    return state.select("_skey", "_lam", "_mean", "_full")


def cell_copies(cells: DataFrame, hist: DataFrame, targets: DataFrame, dual: DataFrame, cap: float = CAP) -> DataFrame:
    """Copies to hand out in each (source, size, bucket) cell: _base for every row, one more for the first _extra."""
    x = F.col("_size") / F.col("_mean")
    rate = F.when(F.col("_full"), F.lit(cap)).when(F.col("_size") == 0, F.lit(1.0)).otherwise(F.least(F.lit(cap), F.exp(F.least(F.col("_lam") * x, F.lit(50.0)))))
    along = Window.partitionBy("_skey").orderBy(F.col("_size").desc())
    ideal = F.sum(F.col("_n") * F.coalesce("_rate", F.lit(0.0))).over(along.rowsBetween(Window.unboundedPreceding, 0))
    # the rounded running sum may pass one size's limit by one copy; least() keeps every document within cap
    group = (
        hist.join(dual, "_skey", "left").withColumn("_rate", rate)
        .withColumn("_upto", F.floor(ideal + 0.5 + 1e-9))
        .withColumn("_k", F.col("_upto") - F.coalesce(F.lag("_upto").over(along), F.lit(0)))
        .withColumn("_k", F.greatest(F.lit(0), F.least(F.col("_k"), F.col("_n") * F.lit(int(cap)))))
        .select("_skey", "_size", "_n", "_k")
    )
    inside = Window.partitionBy("_skey", "_size").orderBy("_bucket")
    upto = F.sum("_m").over(inside.rowsBetween(Window.unboundedPreceding, 0))
    spare = F.col("_k") - F.floor(F.col("_k") / F.col("_n")) * F.col("_n")
    return (
        cells.join(group, ["_skey", "_size"])
        .withColumn("_base", F.floor(F.col("_k") / F.col("_n")))
        .withColumn("_to", F.floor(spare * upto / F.col("_n")))
        .withColumn("_extra", F.col("_to") - F.coalesce(F.lag("_to").over(inside), F.lit(0)))
        .join(targets.select("_skey", "_total", "_target"), "_skey")
        .select("_skey", "_size", "_bucket", "_base", "_extra", "_total", "_target")
    )


def plan_mix(sized: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, cap: float = CAP) -> DataFrame:
    """Allocation per cell for rows that carry _size, _skey, _bucket."""
    cells = cut(sized.groupBy("_skey", "_size", "_bucket").agg(F.count(F.lit(1)).alias("_m")))
    hist = cut(cells.groupBy("_skey", "_size").agg(F.sum("_m").alias("_n")))
    targets = cut(source_targets(hist, weights, share, cap))
    return cell_copies(cells, hist, targets, newton_rates(hist, targets, cap), cap)


def deal(sized: DataFrame, plan: DataFrame) -> DataFrame:
    """Adds _copies to each row; rows of a cell are taken in hash order."""
    w = Window.partitionBy("_skey", "_size", "_bucket").orderBy(F.xxhash64(F.col("doc_id"), F.lit(7)), F.col("doc_id"))
    return (
        sized.withColumn("_row", F.row_number().over(w))
        .join(plan, ["_skey", "_size", "_bucket"])
        .withColumn("_copies", (F.col("_base") + F.when(F.col("_row") <= F.col("_extra"), 1).otherwise(0)).cast("long"))
    )


def mix_plan(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, cap: float = CAP) -> DataFrame:
    """One row per document: doc_id, size, source_size, target, taken, copies."""
    sized = cut(with_size(docs))
    return deal(sized, plan_mix(sized, weights, share, cap)).select(
        "doc_id", F.col("_size").alias("size"), F.col("_total").alias("source_size"), F.col("_target").cast("double").alias("target"),
        (F.col("_copies") * F.col("_size")).alias("taken"), F.col("_copies").alias("copies"),
    )


def mix_documents(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, cap: float = CAP) -> DataFrame:
    """The mixed corpus itself: every row as often as the plan takes it, columns unchanged."""
    plan = plan_mix(with_size(docs), weights, share, cap)
    dealt = deal(with_size(docs, carry=True), plan).filter(F.col("_copies") > 0)
    return dealt.select("_whole", F.explode(F.sequence(F.lit(1), F.col("_copies").cast("int")))).select("_whole.*")
