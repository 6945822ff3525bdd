"""Dealing rows to blocks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..session import scratch


def by_index(df: DataFrame, key: str, p: int, n: int | Column) -> DataFrame:
    """``block`` of a dense 0-based index: p contiguous blocks whose sizes differ by at most one."""
    size = F.lit(n) if isinstance(n, int) else n
    x = (F.col(key) + 1) * F.lit(p) - 1
    return df.withColumn("block", ((x - x % size) / size).cast("long"))


def by_split(df: DataFrame) -> DataFrame:
    """``block`` is the input split the row comes from: no shuffle."""
    return df.withColumn("block", F.spark_partition_id().cast("long"))


def by_hash(df: DataFrame, p: int, *cols: str) -> DataFrame:
    return df.withColumn("block", F.pmod(F.xxhash64(*(cols or df.columns)), F.lit(p)))


def by_order(df: DataFrame, cols: list[str], p: int) -> DataFrame:
    """Contiguous blocks of an ordering without a dense key: range partitions, cut exactly by their row counts.

    One range shuffle. Range bounds are sampled anew by every job, so the numbered rows are written once and both the counts
    and the result come from that table; the driver sees one count per partition.
    """
    spark = df.sparkSession
    ranged = df.repartitionByRange(p, *cols).sortWithinPartitions(*cols).withColumn("_part", F.spark_partition_id())
    numbered = ranged.withColumn("_at", F.monotonically_increasing_id() % F.lit(1 << 33))
    path = scratch(spark, "order")
    numbered.write.parquet(path)
    numbered = spark.read.schema(numbered.schema).parquet(path)
    counts = {r["_part"]: r["n"] for r in numbered.groupBy("_part").agg(F.count(F.lit(1)).alias("n")).collect()}
    n, before, offsets = sum(counts.values()), 0, []
    for part in sorted(counts):
        offsets.append((part, before))
        before += counts[part]
    table = spark.createDataFrame(offsets or [(0, 0)], "_part int, _before long")
    indexed = numbered.join(F.broadcast(table), "_part").withColumn("_index", F.col("_before") + F.col("_at"))
    return by_index(indexed, "_index", p, max(n, 1)).drop("_part", "_at", "_before", "_index")


def grouped(df: DataFrame, g: int) -> DataFrame:
    """``worker``: the group of g neighbouring blocks that merges among itself first."""
    return df.withColumn("worker", F.expr(f"block div {g}"))


def per_core(df: DataFrame, c: int) -> DataFrame:
    """c splits per core: neighbouring splits are joined without a shuffle where there are more, rows dealt anew where fewer."""
    want, now = c * df.sparkSession.sparkContext.defaultParallelism, splits_of(df)
    return df if now == want else df.coalesce(want) if now > want else df.repartition(want)


def splits_of(df: DataFrame) -> int:
    """Splits of the physical plan; nothing runs."""
    return df._jdf.queryExecution().toRdd().getNumPartitions()
