"""Operators around frequent items: reports over days, sets, cubes, and Spark's own relatives of the methods."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .exact import exact_counts


def top_items(df: DataFrame, k: int, item: str = "item") -> DataFrame:
    return exact_counts(df, item).orderBy(F.col("cnt").desc(), "item").limit(k).select("item")


def common_items(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("item").intersect(b.select("item"))


def lost_items(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("item").subtract(b.select("item"))


def all_items(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("item").unionByName(b.select("item")).distinct()


def daily(df: DataFrame, ts: str, item: str) -> DataFrame:
    return df.groupBy(F.to_date(ts).cast("string").alias("day"), F.col(item).alias("item")).agg(F.count(F.lit(1)).alias("cnt"))


def previous_report(report: DataFrame) -> DataFrame:
    """Each day's count beside the item's last reported one before it."""
    return report.withColumn("before", F.lag("cnt").over(Window.partitionBy("item").orderBy("day")))


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """``left`` with the latest ``value`` of ``right`` at or before its time: one shuffle by key, no range join."""
    marked = left.withColumn("_left", F.lit(1)).withColumn(value, F.lit(None).cast(right.schema[value].dataType)).unionByName(right.withColumn("_left", F.lit(0)), allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy(at, "_left").rowsBetween(Window.unboundedPreceding, 0)
    return marked.withColumn(value, F.last(value, ignorenulls=True).over(w)).filter("_left = 1").drop("_left")


def pivoted(report: DataFrame, values: list[str]) -> DataFrame:
    return report.groupBy("day").pivot("item", values).agg(F.sum("cnt")).na.fill(0)


def cube_counts(df: DataFrame, keys: list[str]) -> DataFrame:
    return df.cube(*keys).agg(F.count(F.lit(1)).alias("cnt"))


def grouping_sets_counts(df: DataFrame, keys: list[str]) -> DataFrame:
    """Counts by each key alone in one pass."""
    return df.groupingSets([[F.col(k)] for k in keys], *[F.col(k) for k in keys]).agg(F.count(F.lit(1)).alias("cnt"))


def top_per_group(counts: DataFrame, keys: list[str], k: int) -> DataFrame:
    w = Window.partitionBy(*keys).orderBy(F.col("cnt").desc(), "item")
    return counts.withColumn("_rank", F.row_number().over(w)).filter(F.col("_rank") <= k).drop("_rank")


def builtin_top_k(df: DataFrame, item: str, k: int) -> DataFrame:
    """Spark's approximate top k, for comparison."""
    return df.select(F.explode(F.expr(f"approx_top_k({item}, {k})")).alias("t")).select("t.item", F.col("t.count").alias("cnt"))


def builtin_freq_items(df: DataFrame, item: str, support: float) -> DataFrame:
    return df.stat.freqItems([item], support).select(F.explode(f"{item}_freqItems").alias("item"))


def builtin_count_min(df: DataFrame, item: str, eps: float = 0.001, confidence: float = 0.99, seed: int = 1) -> DataFrame:
    return df.agg(F.count_min_sketch(F.col(item), F.lit(eps), F.lit(confidence), F.lit(seed)).alias("sketch"))


def sample_estimate(df: DataFrame, item: str, fraction: float, seed: int) -> DataFrame:
    """Counts from a sample, scaled: what a sketch is to be compared with."""
    return exact_counts(df.sample(fraction, seed), item).withColumn("est", F.round(F.col("cnt") / F.lit(fraction)).cast("long")).select("item", "est")
