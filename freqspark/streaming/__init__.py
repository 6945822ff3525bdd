"""The one-pass setting over streams: running, windowed and keyed summaries, with exact counts to compare."""

from __future__ import annotations

from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..kernels.batched import merge_pair
from ..kernels.scalar import Summary, scalar_kernel
from ..operators.merge import merge_flat
from ..plans.engine import release, summarise
from ..session import use_library
from ..spec import FrequentSpec


class SummaryStore:
    """A summary per micro-batch version under one folder; replaying a batch writes the same version again."""

    def __init__(self, spark: SparkSession, path: str) -> None:
        self.spark, self.path = spark, path.rstrip("/")

    def versions(self) -> list[int]:
        jvm = self.spark.sparkContext._jvm
        at = jvm.org.apache.hadoop.fs.Path(self.path)
        fs = at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration())
        if not fs.exists(at):
            return []
        names = [s.getPath().getName() for s in fs.listStatus(at)]
        done = [n for n in names if n.startswith("v") and fs.exists(jvm.org.apache.hadoop.fs.Path(f"{self.path}/{n}/_SUCCESS"))]
        return sorted(int(n[1:]) for n in done)

    def read(self, version: int) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/v{version}")

    def latest(self) -> DataFrame:
        return self.read(self.versions()[-1])

    def write(self, version: int, summary: DataFrame, keep: int = 2) -> None:
        """Write a version and drop all but the last ``keep`` finished ones before it: a replay needs one of them."""
        summary.write.mode("overwrite").parquet(f"{self.path}/v{version}")
        jvm = self.spark.sparkContext._jvm
        for old in [v for v in self.versions() if v < version][:-keep]:
            at = jvm.org.apache.hadoop.fs.Path(f"{self.path}/v{old}")
            at.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def stream_frequent(sdf: DataFrame, item: str, spec: FrequentSpec, store: SummaryStore):
    """A stream writer whose every batch is summarised, merged with the version before it and stored under its batch id."""

    def fold(batch: DataFrame, number: int) -> None:
        fresh = summarise(batch, item, spec)
        before = [v for v in store.versions() if v < number]
        both = fresh.withColumn("block", F.lit(1).cast("long"))
        if before:
            both = both.unionByName(store.read(before[-1]).withColumn("block", F.lit(0).cast("long")))
        store.write(number, merge_flat(both, spec.size, "tight", tuple(spec.by)))
        release(fresh)

    return sdf.writeStream.foreachBatch(fold)


def window_frequent(sdf: DataFrame, ts: str, item: str, spec: FrequentSpec, store: SummaryStore, width: str, slide: str | None = None):
    """A stream writer of one bounded summary per tumbling or sliding window (column ``start``), merged batch by batch.

    A window's state is its counters, whatever the number of its items. Naive timestamps are read as UTC.
    """
    at = F.col(ts).cast("timestamp")
    window = F.window(at, width, slide) if slide else F.window(at, width)
    rows = sdf.select(window.alias("w"), F.col(item).alias("item"), *([spec.weight] if spec.weight else [])).withColumn("start", F.col("w.start")).drop("w")
    return stream_frequent(rows, "item", replace(spec, by=("start", *spec.by)), store)


def window_counts(sdf: DataFrame, ts: str, item: str, width: str, slide: str | None = None, late: str = "0 seconds") -> DataFrame:
    """Exact counts per window and item, the baseline whose state grows with the items.

    Naive timestamps are read as UTC: event time in a stream must be an instant.
    """
    at = sdf.withColumn("_ts", F.col(ts).cast("timestamp")).withWatermark("_ts", late)
    w = F.window("_ts", width, slide) if slide else F.window("_ts", width)
    return at.groupBy(w.alias("w"), F.col(item).alias("item")).agg(F.count(F.lit(1)).alias("cnt")).select(F.col("w.start").alias("start"), "item", "cnt")


def session_counts(sdf: DataFrame, ts: str, key: str, gap: str, late: str = "0 seconds") -> DataFrame:
    at = sdf.withColumn("_ts", F.col(ts).cast("timestamp")).withWatermark("_ts", late)
    return at.groupBy(F.session_window("_ts", gap).alias("w"), key).agg(F.count(F.lit(1)).alias("cnt")).select(key, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "cnt")


def deduplicated_counts(sdf: DataFrame, ts: str, key: str, item: str, late: str = "1 day") -> DataFrame:
    """Counts after dropping repeated keys inside the watermark."""
    at = sdf.withColumn("_ts", F.col(ts).cast("timestamp")).withWatermark("_ts", late)
    return at.dropDuplicatesWithinWatermark([key]).groupBy(F.col(item).alias("item")).agg(F.count(F.lit(1)).alias("cnt"))


_STATE = "n long, floor long, items array<string>, ests array<long>, errs array<long>"


def keyed_summaries(sdf: DataFrame, by: str, item: str, k: int) -> DataFrame:
    """One bounded summary per key in the stream's state; every update gives the key's counters anew (update mode)."""
    use_library(sdf.sparkSession)
    kind = sdf.schema[by].dataType.simpleString()

    def step(key, frames, state):
        s = Summary()
        if state.exists:
            n, floor, items, ests, errs = state.get
            s = Summary(n, floor, {i: [e, r] for i, e, r in zip(items, ests, errs, strict=True)})
        for pdf in frames:
            s = merge_pair(s, scalar_kernel(pdf["item"].tolist(), k), k)
        rows = s.rows()
        state.update((s.n, s.floor, [r[0] for r in rows], [r[1] for r in rows], [r[2] for r in rows]))
        yield pd.DataFrame({"key": [key[0]] * len(rows), "item": [r[0] for r in rows], "est": [r[1] for r in rows], "err": [r[2] for r in rows], "n": [s.n] * len(rows)})

    rows = sdf.select(F.col(by).alias("key"), F.col(item).cast("string").alias("item"))
    return rows.groupBy("key").applyInPandasWithState(step, f"key {kind}, item string, est long, err long, n long", _STATE, "update", "NoTimeout")


def to_files(sdf: DataFrame, path: str, mode: str) -> DataFrame:
    """Run a stream over all available data into Parquet, a folder per micro-batch, which a replay writes again.

    In complete mode the last batch is the result; in update mode rows of all batches come with their ``_batch``.
    """
    spark = sdf.sparkSession

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/out/n={number}")

    query = sdf.writeStream.foreachBatch(write).outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{path}/offsets").start()
    query.awaitTermination()
    out = spark.read.schema(sdf.schema.add("n", "long")).option("basePath", f"{path}/out").parquet(f"{path}/out")
    if mode != "complete":
        return out.withColumnRenamed("n", "_batch")
    last = out.agg(F.max("n").alias("n")).first()["n"]
    return out.filter(F.col("n") == F.lit(last)).drop("n")


def counted_and_late(sdf: DataFrame, path: str) -> tuple[int, int]:
    """Rows counted and rows dropped behind the watermark by a tumbling count (column ``cnt``) over all available data.

    Spark's own metric counts dropped rows after their partial aggregation, so late rows are those read and not counted.
    A batch is held against the watermark that the batch before it started with.
    """
    spark = sdf.sparkSession

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/out/n={number}")

    query = sdf.writeStream.foreachBatch(write).outputMode("update").trigger(availableNow=True).option("checkpointLocation", f"{path}/offsets").start()
    query.awaitTermination()
    read = sum(p["numInputRows"] for p in query.recentProgress)
    rows = spark.read.schema(sdf.schema.add("n", "long")).option("basePath", f"{path}/out").parquet(f"{path}/out")
    last = rows.groupBy("start", "item").agg(F.max_by("cnt", "n").alias("cnt"))
    counted = int(last.agg(F.sum("cnt").alias("c")).first()["c"] or 0)
    return counted, read - counted


def to_memory(sdf: DataFrame, name: str, mode: str, checkpoint: str | None = None) -> DataFrame:
    """Run a stream over all available data into a memory table and return that table."""
    writer = sdf.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    query = (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()
    query.awaitTermination()
    return sdf.sparkSession.table(name)


__all__ = ["SummaryStore", "stream_frequent", "window_counts", "window_frequent", "session_counts", "to_files", "counted_and_late", "deduplicated_counts", "keyed_summaries", "to_memory"]
