"""Readers of items and the store of summaries."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import use_library

_FORMATS = ("parquet", "orc", "csv", "json", "text")


def read_items(spark: SparkSession, path: str, item: str | Column, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """One column ``item``; the scan reads only what the expression needs. CSV and JSON need a schema."""
    if fmt not in _FORMATS:
        raise ValueError(f"fmt is {fmt!r}; it must be one of {', '.join(_FORMATS)}")
    if fmt in ("csv", "json") and schema is None:
        raise ValueError(f"reading {fmt} needs an explicit schema")
    reader = spark.read.format(fmt).options(**options)
    df = (reader.schema(schema) if schema else reader).load(path)
    return df.select((F.col(item) if isinstance(item, str) else item).alias("item"))


def read_items_sql(spark: SparkSession, query: str) -> DataFrame:
    """The first column of any SQL text, as ``item``."""
    df = spark.sql(query)
    return df.select(F.col(df.columns[0]).alias("item"))


def stream_items(spark: SparkSession, path: str, schema, item: str | Column, fmt: str = "parquet", keep: tuple[str, ...] = (), **options) -> DataFrame:
    """A stream of items from files; a single file is named by a glob."""
    df = spark.readStream.format(fmt).schema(schema).options(**options).load(path)
    return df.select(*keep, (F.col(item) if isinstance(item, str) else item).alias("item"))


def zipf_source(spark: SparkSession, n: int, rho: float, universe: int = 1_000_000, seed: int = 1, partitions: int | None = None) -> DataFrame:
    """n Zipf items for benches, drawn by inverse distribution; each partition has its own seeded stream."""
    use_library(spark)
    weights = np.cumsum(np.arange(1, universe + 1, dtype=np.float64) ** -rho)
    edges = spark.sparkContext.broadcast(weights / weights[-1])

    def draw(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                rng = np.random.Generator(np.random.PCG64([seed, b.column(0)[0].as_py()]))
                yield pa.RecordBatch.from_arrays([pa.array(np.searchsorted(edges.value, rng.random(b.num_rows)) + 1)], names=["item"])

    return spark.range(0, n, 1, partitions or spark.sparkContext.defaultParallelism).mapInArrow(draw, "item long")


def save_summary(summary: DataFrame, path: str, day: str, mode: str = "overwrite") -> None:
    """Write one day's long summary as its own partition; a rerun replaces that day only."""
    summary.withColumn("day", F.lit(day)).write.mode(mode).option("partitionOverwriteMode", "dynamic").partitionBy("day").parquet(path)


def load_summary(spark: SparkSession, path: str, days: list[str] | None = None) -> DataFrame:
    """Saved summaries, each day's one as one block; days are pruned by partition."""
    df = spark.read.option("recursiveFileLookup", "false").parquet(path).withColumn("day", F.col("day").cast("string"))
    df = df.filter(F.col("day").isin(days)) if days else df
    return df.withColumn("block", F.xxhash64("day", "block")).drop("day")
