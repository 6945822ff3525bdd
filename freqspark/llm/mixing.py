"""Mixing sources to target weights by subset sums over length counts.

Per source the documents are counted by exact length. Whole repeats cover the target's integer part; of the rest, every
length gives its even share, and a bounded knapsack over the remaining copies closes the gap to the token. Which
documents stand for a length is decided by a seeded hash.

Defined cases: null text has size 0; a null source is a source of its own, last in order; rows of size 0 are never
taken; an empty table gives an empty mix; repeated rows count once each. If no subset meets the rest exactly a near
sum is taken (see choose_counts), so a source's words differ from its target by less than its longest document.
"""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import use_library
from .common import documents, written

CAP = 3


def sizes(df: DataFrame, text: str = "text") -> DataFrame:
    """``df`` with ``size``: its number of words."""
    return df.withColumn("size", F.expr(f"CAST(regexp_count(coalesce({text}, ''), '[^\\\\x20\\\\x09-\\\\x0D]+') AS BIGINT)"))


def targets(per_source: DataFrame, weights: tuple[int, ...] = (1, 2, 3), share: float = 1.0, cap: int = CAP) -> DataFrame:
    """Adds ``weight`` and ``target`` to one row per source (source, source_size).

    Sources by code point, null last, weigh as ``weights`` repeating. Targets above ``cap`` sizes stop there and their
    excess goes to the others by weight. A source is capped exactly if its size per weight is at most that of the
    last capped one, so one ordering by size per weight finds the level: no iteration.
    """
    n = len(weights)
    by_name = Window.orderBy(F.col("source").isNull().cast("int"), "source")
    ranked = per_source.withColumn("weight", F.element_at(F.array(*[F.lit(w) for w in weights]), (F.row_number().over(by_name) - 1) % n + 1).cast("long"))
    by_need = Window.orderBy(F.col("source_size") / F.col("weight"), F.col("source").isNull().cast("int"), "source")
    before = by_need.rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.orderBy(F.lit(1)).rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    levels = (
        ranked.withColumn("_size_before", F.coalesce(F.sum("source_size").over(before), F.lit(0)))
        .withColumn("_weight_before", F.coalesce(F.sum("weight").over(before), F.lit(0)))
        .withColumn("_all", F.sum("source_size").over(whole))
        .withColumn("_weights", F.sum("weight").over(whole))
        .withColumn("_rank", F.row_number().over(by_need))
        # the level if all sources before this one are capped and none from here on
        .withColumn("_level", (F.col("_all") * F.lit(float(share)) - F.lit(float(cap)) * F.col("_size_before")) / (F.col("_weights") - F.col("_weight_before")))
        .withColumn("_open", F.col("weight") * F.col("_level") <= F.lit(float(cap)) * F.col("source_size"))
        .withColumn("_first", F.min(F.when(F.col("_open"), F.struct("_rank", "_level"))).over(whole))
        .withColumn("target", F.least(F.lit(float(cap)) * F.col("source_size"), F.coalesce(F.col("weight") * F.col("_first._level"), F.lit(float(cap)) * F.col("source_size"))))
    )
    return levels.select("source", "source_size", "weight", "target")


def _knapsack(lengths: list[int], free: list[int], order: list[int], left: int) -> tuple[list[int], int]:
    """Copies within ``free`` whose lengths' sum comes nearest to ``left``, and how far it stays off."""
    top = left + lengths[order[0]]
    mask = (1 << (top + 1)) - 1
    take, reach, steps = [0] * len(lengths), 1, []
    for i in order:
        rest, piece = min(free[i], top // lengths[i]), 1
        while rest > 0:
            n = min(piece, rest)
            steps.append((i, n, reach))
            reach |= reach << (n * lengths[i]) & mask
            rest -= n
            piece *= 2
        if reach >> left & 1:
            break
    below = (reach & ((1 << (left + 1)) - 1)).bit_length() - 1
    above = reach >> (left + 1)
    at = below
    if above:
        over = left + (above & -above).bit_length()
        at = over if over - left < left - below else below
    off = abs(at - left)
    for i, n, was in reversed(steps):
        if not was >> at & 1:
            take[i] += n
            at -= n * lengths[i]
    return take, off


def choose_counts(lengths: list[int], counts: list[int], goal: int, work: int = 200_000_000) -> list[int]:
    """How many documents of each length to take so that the sum comes nearest to ``goal``.

    Every length first gives its even share but ``width`` copies, rounds of one more of each, longest first, close most of
    the gap, and a bounded knapsack over the copies still free closes the rest, with reachable sums as the bits of one
    integer. Width starts at one and doubles until the sum is exact, or as near as the lengths' common divisor allows, or
    all copies are free, when it is the nearest of all sums. ``work`` (sums times lengths) ends the widening earlier where
    a table would grow too large; the sum is then the nearest found, less than the longest document off.
    """
    total = sum(a * b for a, b in zip(lengths, counts, strict=True))
    if goal <= 0 or not total:
        return [0] * len(lengths)
    if goal >= total:
        return list(counts)
    order = sorted((i for i in range(len(lengths)) if lengths[i] > 0 and counts[i] > 0), key=lambda i: -lengths[i])
    longest, divisor = lengths[order[0]], math.gcd(*(lengths[i] for i in order))
    least_off = min(goal % divisor, divisor - goal % divisor)
    best, width = None, 1
    while True:
        take = [max(0, c * goal // total - width) for c in counts]
        left, moved = goal - sum(a * b for a, b in zip(lengths, take, strict=True)), True
        while moved:
            moved = False
            for i in order:
                if counts[i] > take[i] and left - lengths[i] >= 2 * width * longest:
                    take[i] += 1
                    left -= lengths[i]
                    moved = True
        if best is not None and (left + longest) * len(order) > work:
            return best[1]
        extra, off = _knapsack(lengths, [c - t for c, t in zip(counts, take, strict=True)], order, left)
        if best is None or off < best[0]:
            best = off, [t + e for t, e in zip(take, extra, strict=True)]
        if best[0] <= least_off or not any(take):
            return best[1]
        width *= 2


def _plan(pdf: pd.DataFrame) -> pd.DataFrame:
    pdf = pdf.sort_values("size")
    target, size = float(pdf["target"].iloc[0]), int(pdf["source_size"].iloc[0])
    whole = min(int(target // size), CAP) if size else 0
    lengths, counts = [int(x) for x in pdf["size"]], [int(x) for x in pdf["n"]]
    extra = choose_counts(lengths, counts, round(target - whole * size)) if whole < CAP else [0] * len(lengths)
    return pd.DataFrame({"source": pdf["source"], "size": lengths, "whole": whole, "extra": extra})


def mix(df: DataFrame, key: str = "doc_id", source: str = "source", weights: tuple[int, ...] = (1, 2, 3), share: float = 1.0, cap: int = CAP, seed: int = 7) -> DataFrame:
    """(key columns of ``df``, size, source_size, target, copies): how often the mix takes each document.

    Shuffled rows hold ids and numbers, never texts. Length counts are pre-aggregated in the map tasks; choosing
    documents of one (source, length) ranks only the one hash bin where the count is reached, not the whole group.
    """
    if cap > CAP:
        raise ValueError(f"cap is at most {CAP}")
    use_library(df.sparkSession)
    rows = sizes(df).select(F.col(key).alias("doc_id"), F.col(source).alias("source"), "size", F.xxhash64(F.lit(seed), F.col(key), F.xxhash64("text")).alias("draw"))
    rows = written(rows.withColumn("bin", F.shiftrightunsigned("draw", 56).cast("int")), "mixing-sizes")
    counts = written(rows.groupBy("source", "size", "bin").agg(F.count(F.lit(1)).alias("n")), "mixing-counts")
    histogram = counts.groupBy("source", "size").agg(F.sum("n").alias("n"))
    per_source = targets(histogram.groupBy("source").agg(F.sum(F.col("size") * F.col("n")).alias("source_size")), weights, share, cap)
    same = lambda a, b: F.col(a).eqNullSafe(F.col(b))
    mine = per_source.select(F.col("source").alias("of"), "source_size", "target")
    todo = histogram.join(mine, same("source", "of")).drop("of")
    plan = todo.groupBy("source").applyInPandas(_plan, "source string, size long, whole int, extra long")
    p = plan.select(F.col("source").alias("of"), F.col("size").alias("of_size"), "whole", "extra")
    reached = Window.partitionBy("source", "size").orderBy("bin").rowsBetween(Window.unboundedPreceding, -1)
    bins = (
        counts.join(p, same("source", "of") & (F.col("size") == F.col("of_size"))).drop("of", "of_size")
        .withColumn("upto", F.coalesce(F.sum("n").over(reached), F.lit(0)))
        .withColumn("room", F.greatest(F.lit(0), F.least(F.col("n"), F.col("extra") - F.col("upto"))))
    )
    b = bins.select(F.col("source").alias("of"), F.col("size").alias("of_size"), F.col("bin").alias("of_bin"), "n", "whole", "room")
    known = rows.join(b, same("source", "of") & (F.col("size") == F.col("of_size")) & (F.col("bin") == F.col("of_bin"))).drop("of", "of_size", "of_bin")
    clear = known.filter("room = 0 OR room = n").withColumn("copies", F.col("whole") + (F.col("room") > 0).cast("int"))
    rank = F.row_number().over(Window.partitionBy("source", "size", "bin").orderBy("draw", "doc_id"))
    split = known.filter("room > 0 AND room < n").withColumn("rank", rank).withColumn("copies", F.col("whole") + (F.col("rank") <= F.col("room")).cast("int"))
    chosen = clear.select("doc_id", "source", "size", "draw", "copies").unionByName(split.select("doc_id", "source", "size", "draw", "copies"))
    return chosen.join(mine, same("source", "of")).drop("of")


def mixed_documents(df: DataFrame, **options) -> DataFrame:
    """The rows of ``df``, each as often as the mix takes it. Rows equal in id and text are interchangeable."""
    plan = mix(df, **options).filter("copies > 0")
    drawn = df.withColumn("__draw", F.xxhash64(F.lit(options.get("seed", 7)), F.col("doc_id"), F.xxhash64("text")))
    per = written(plan.groupBy(F.col("doc_id").alias("__id"), F.col("draw").alias("__of")).agg(F.sum("copies").alias("__copies"), F.count(F.lit(1)).alias("__rows")), "mixing-copies")
    if per.filter("__rows > 1").take(1):  # equal rows share a draw: their copies are summed and dealt to one of them
        drawn = drawn.dropDuplicates(["doc_id", "__draw"])
    joined = drawn.join(per, F.col("doc_id").eqNullSafe(F.col("__id")) & (F.col("__draw") == F.col("__of")))
    return joined.withColumn("__n", F.explode(F.sequence(F.lit(1), F.col("__copies").cast("int")))).select(*df.columns)


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents with the words the mix takes of each."""
    out = mix(documents(spark, sf_dir))
    return out.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("copies")).cast("long").alias("taken"))


QUERIES = {"op5_mixing": op5_mixing}
ORACLES: dict[str, str] = {}
