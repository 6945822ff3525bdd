"""Connected components of a link table by alternating star steps; links and labels stay distributed."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_written, spread_join, written


def _state(edges: DataFrame) -> tuple[int, int]:
    r = edges.agg(F.count(F.lit(1)).alias("n"), F.sum(F.pmod(F.xxhash64("a", "b"), F.lit(1 << 40))).alias("s")).first()
    return r["n"], r["s"] or 0


def components(links: DataFrame, name: str) -> DataFrame:
    """(node, component) for every node of ``links`` (a, b); the component is its smallest node.

    Each round points every node's larger neighbours at its least one, then every node's smaller neighbours and
    itself; the table is written after each round, and ends as one star per component. The minima are tables of their
    own with the nodes' degrees, by which a star's centre is split among tasks.
    """
    edges = written(links.select(F.least("a", "b").alias("b"), F.greatest("a", "b").alias("a")).filter("a <> b").select("a", "b").distinct(), name)
    was = _state(edges)
    while True:
        both = edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = written(both.groupBy("a").agg(F.min("b").alias("m"), F.count(F.lit(1)).alias("c")).select("a", F.least("a", "m").alias("m"), "c"), name)
        large = written(spread_join(both, least, ["a"], "c", 2 * was[0]).filter("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).filter("a <> b").distinct(), name)
        low = written(large.groupBy("a").agg(F.min("b").alias("m"), F.count(F.lit(1)).alias("c")), name)
        small = spread_join(large, low, ["a"], "c", 2 * was[0]).filter("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(low.select("a", F.col("m").alias("b"))).distinct()
        after = written(small, name)
        now = _state(after)
        drop_written(edges, least, large, low)
        edges = after
        if now == was:
            break
        was = now
    return edges.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(edges.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
