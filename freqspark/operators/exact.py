"""Exact counts, verification of candidates, iceberg queries and the majority vote."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..spec import FrequentSpec, threshold_col


def _weight(weight: str | None):
    return F.sum(F.col(weight).cast("long")) if weight else F.count(F.lit(1))


def exact_counts(df: DataFrame, item: str, by: tuple[str, ...] = (), weight: str | None = None, nulls: str = "skip") -> DataFrame:
    rows = df.filter(F.col(item).isNotNull()) if nulls == "skip" else df
    return rows.groupBy(*by, F.col(item).alias("item")).agg(_weight(weight).alias("cnt"))


def exact_frequent(df: DataFrame, item: str, k: int, by: tuple[str, ...] = (), weight: str | None = None, nulls: str = "skip", with_meta: bool = False) -> DataFrame:
    """Every item with more than n / k occurrences; n is summed from the counts themselves, in one row per group."""
    counts = exact_counts(df, item, by, weight, nulls)
    n = counts.groupBy(*by).agg(F.sum("cnt").alias("n")).withColumn("threshold", threshold_col("n", k))
    joined = null_safe_join(counts, n, by) if by else counts.crossJoin(F.broadcast(n))
    out = joined.filter("cnt >= threshold")
    return out if with_meta else out.drop("n", "threshold")


def null_safe_join(left: DataFrame, right: DataFrame, keys: tuple[str, ...], how: str = "inner") -> DataFrame:
    """Join on equal keys where null equals null; the left side's keys stay."""
    named = right.withColumnsRenamed({c: f"_{c}" for c in keys})
    same = F.lit(True)
    for c in keys:
        same = same & F.col(c).eqNullSafe(F.col(f"_{c}"))
    return left.join(named, same, how).drop(*[f"_{c}" for c in keys])


def verify(df: DataFrame, item: str, candidates: DataFrame, k: int, weight: str | None = None, nulls: str = "skip", by: tuple[str, ...] = ()) -> DataFrame:
    """Exact counts of the candidates (at most the summary's counters per group) by a second scan; false ones go.

    ``candidates`` (by, item, n) are unique, so an inner join against their broadcast keeps the scan's own partial
    aggregation small; n is the number of items of the group.
    """
    rows = df.select(*by, F.col(item).alias("item"), *([weight] if weight else []))
    rows = rows.filter("item IS NOT NULL") if nulls == "skip" else rows
    names = candidates.select(*by, "item", "n")
    names = names if by else F.broadcast(names)  # without groups there are at most k candidates
    counts = null_safe_join(rows, names, (*by, "item")).groupBy(*by, "item", "n").agg(_weight(weight).alias("cnt"))
    return counts.filter(F.col("cnt") >= threshold_col("n", k)).select(*by, "item", "cnt", "n")


def candidate_filter(df: DataFrame, item: str, candidates: DataFrame, literals: int = 1000) -> DataFrame:
    """``df`` restricted to candidate items by a literal list where they are few, which Parquet statistics can use."""
    values = [r["item"] for r in candidates.select("item").limit(literals + 1).collect()]
    if len(values) <= literals:
        return df.filter(F.col(item).isin([v for v in values if v is not None]))
    return df.join(F.broadcast(candidates.select(F.col("item").alias(item))), item, "left_semi")


def iceberg(df: DataFrame, keys: list[str], min_count: int | None = None, share: float | None = None, approx: bool = False, kernel: str = "batched") -> DataFrame:
    """Groups above a count or a share of all rows; ``approx`` finds them with a summary and a second scan."""
    from ..plans.engine import frequent_items

    if (min_count is None) == (share is None):
        raise ValueError("give one of min_count and share")
    if not approx:
        counts = df.groupBy(*keys).agg(F.count(F.lit(1)).alias("cnt"))
        if min_count is not None:
            return counts.filter(F.col("cnt") >= min_count)
        total = counts.agg(F.sum("cnt").alias("_n"))
        return counts.crossJoin(F.broadcast(total)).filter(F.col("cnt") > F.lit(share) * F.col("_n")).drop("_n")
    if min_count is not None:
        n = df.count()  # answered from file footers for Parquet
        k = max(2, n // min_count + 1)
    else:
        k = max(2, -int(-1 // share) + 1)
    names = [f"k{j}" for j in range(len(keys))]
    rows = df.select(F.struct(*[F.col(c).alias(j) for c, j in zip(keys, names, strict=True)]).alias("item"))  # typed: no key passes through text
    found = frequent_items(rows, "item", FrequentSpec(k, kernel=kernel, nulls="item"), with_meta=True)
    enough = F.col("cnt") >= min_count if min_count is not None else F.col("cnt") > F.lit(share) * F.col("n")
    return found.filter(enough).select(*[F.col(f"item.{j}").alias(c) for c, j in zip(keys, names, strict=True)], "cnt")


def majority(df: DataFrame, item: str, verify_: bool = True, **options) -> DataFrame:
    """The item with more than half of all votes, or no row; unverified, the one candidate that could have it."""
    from ..plans.engine import frequent_items

    return frequent_items(df, item, FrequentSpec(2, setting="verified" if verify_ else "one_pass", **options))
