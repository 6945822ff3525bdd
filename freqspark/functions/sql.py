"""The same from SQL: packed summaries, aggregate and table functions, helpers of built-in expressions.

A packed summary is STRUCT<n, k, floor, counters ARRAY<STRUCT<item, est, err>>> with counters by descending estimate.
"""

from __future__ import annotations

from typing import Any

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..kernels.batched import merge_pair
from ..kernels.scalar import Summary, _order, scalar_kernel
from ..session import use_library

PACKED = "struct<n:bigint,k:int,floor:bigint,counters:array<struct<item:{0},est:bigint,err:bigint>>>"


def pack(summary: DataFrame, k: int, keys: tuple[str, ...] = ("block",)) -> DataFrame:
    """One packed summary per group of a long summary; a group has k counters at most."""
    entry = F.struct((-F.col("est")).alias("o"), "item", "est", "err")
    got = summary.groupBy(*keys).agg(
        F.max(F.when(F.col("kind") == "block", F.col("n"))).alias("n"),
        F.max(F.when(F.col("kind") == "block", F.col("floor"))).alias("floor"),
        F.sort_array(F.collect_list(F.when(F.col("kind") == "item", entry))).alias("c"),
    )
    counters = F.transform("c", lambda x: F.struct(x["item"].alias("item"), x["est"].alias("est"), x["err"].alias("err")))
    return got.select(*keys, F.struct("n", F.lit(k).alias("k"), "floor", counters.alias("counters")).alias("summary"))


def unpack(packed: DataFrame, column: str = "summary", keys: tuple[str, ...] = ()) -> DataFrame:
    """The long shape, each row of ``packed`` as one block."""
    at = packed.withColumn("block", F.monotonically_increasing_id())
    head = at.select(*keys, "block", F.lit("block").alias("kind"), f"{column}.n", f"{column}.floor", F.expr(f"{column}.counters[0].item").alias("item"), F.lit(None).cast("long").alias("est"), F.lit(None).cast("long").alias("err"))
    head = head.withColumn("item", F.when(F.lit(False), F.col("item")))
    rows = at.select(*keys, "block", F.lit("item").alias("kind"), f"{column}.n", f"{column}.floor", F.explode(f"{column}.counters").alias("c")).select(*keys, "block", "kind", "n", "floor", "c.item", "c.est", "c.err")
    return head.unionByName(rows)


def freq_floor(summary: str) -> Column:
    return F.col(f"{summary}.floor")


def freq_estimate(summary: str, item: Column) -> Column:
    """Estimate of one item; without a counter the floor."""
    own = F.filter(f"{summary}.counters", lambda c: c["item"] == item)
    return F.coalesce(F.get(own, F.lit(0))["est"], F.col(f"{summary}.floor"))


def freq_candidates(summary: str) -> Column:
    """Counters that reach the threshold of the summary's own n and k."""
    return F.filter(f"{summary}.counters", lambda c: c["est"] >= F.expr(f"({summary}.n div {summary}.k) + 1"))


def _packed(s: Summary, k: int) -> dict:
    rows = sorted(s.rows(), key=lambda r: (-r[1], _order(r[0])))
    return {"n": s.n, "k": k, "floor": s.floor, "counters": [{"item": i, "est": e, "err": r} for i, e, r in rows]}


def freq_summary(kind: str = "string"):
    """Aggregate function (items, k) -> packed summary, for items of one type.

    Spark gives Python aggregates no partial stage, so a group travels whole: for small groups and SQL only.
    """
    from pyspark.sql.functions import arrow_udf

    @arrow_udf(PACKED.format(kind))
    def summarise(item: pa.Array, k: pa.Array) -> Any:
        size = k[0].as_py() if len(k) else 2
        values = [x for x in item.to_pylist() if x is not None]
        return _packed(scalar_kernel(values, size), size)

    return summarise


def freq_merge(kind: str = "string"):
    """Aggregate function over packed summaries."""
    from pyspark.sql.functions import arrow_udf

    @arrow_udf(PACKED.format(kind))
    def roll_up(summary: pa.Array) -> Any:
        out, k = Summary(), 2
        for p in summary.to_pylist():
            k = p["k"]
            out = merge_pair(out, Summary(p["n"], p["floor"], {c["item"]: [c["est"], c["err"]] for c in p["counters"]}), k)
        return _packed(out, k)

    return roll_up


def register(spark: SparkSession) -> None:
    """Functions for SQL text: freq_summary, freq_summary_long, freq_merge, freq_merge_long, frequent_local, tokenize."""
    from pyspark.sql.functions import udtf

    use_library(spark)
    for name, kind in (("", "string"), ("_long", "bigint")):
        spark.udf.register(f"freq_summary{name}", freq_summary(kind))
        spark.udf.register(f"freq_merge{name}", freq_merge(kind))

    @udtf(returnType="item string, est bigint, err bigint, n bigint")
    class Local:
        """Local summary of each partition of a table argument whose first column is the item."""

        def __init__(self) -> None:
            self.summary = Summary()
            self.items: list = []
            self.k = 2

        def _fold(self) -> None:
            self.summary = merge_pair(self.summary, scalar_kernel(self.items, self.k), self.k) if self.summary.n else scalar_kernel(self.items, self.k)
            self.items = []

        def eval(self, row, k: int):
            self.k = k
            if row[0] is not None:
                self.items.append(str(row[0]))
                if len(self.items) >= 100_000:
                    self._fold()

        def terminate(self):
            self._fold()
            for item, est, err in self.summary.rows():
                yield item, est, err, self.summary.n

    spark.udtf.register("frequent_local", Local)
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tokenize(t STRING) RETURNS ARRAY<STRING> RETURN regexp_extract_all(lower(t), '[a-z]+', 0)")
