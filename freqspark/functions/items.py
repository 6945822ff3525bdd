"""Item expressions over the given tables and the integer Zipf column."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

UNIVERSE = 1000


def words(df: DataFrame, text: str = "text", item: str = "item", keep: tuple[str, ...] = ()) -> DataFrame:
    """One row per lower-case ASCII word."""
    return df.select(*keep, F.explode(F.regexp_extract_all(F.lower(text), F.lit("[a-z]+"), F.lit(0))).alias(item))


def host(url: str = "url") -> F.Column:
    return F.regexp_extract(url, r"^[a-z]+://([^/:]+)", 1)


def item_type(df: DataFrame, item: str) -> T.DataType:
    """The item's type, refused where equality or order is not portable."""
    kind = df.schema[item].dataType
    if isinstance(kind, (T.MapType, T.ArrayType)) or kind.typeName() == "variant":
        raise TypeError(f"items of type {kind.simpleString()} are not supported; use to_json or xxhash64 of the column")
    return kind


def zipf_bounds(rho: float, universe: int = UNIVERSE) -> list[tuple[int, int, int]]:
    """(rank, low, high) intervals of [0, 2^32): rank r owns its share r^-rho of the range, in integers."""
    weights = [r**-rho for r in range(1, universe + 1)]
    total, at, out = sum(weights), 0.0, []
    edges = [0]
    for w in weights:
        at += w
        edges.append(round(at / total * 2**32))
    edges[-1] = 2**32
    for r in range(universe):
        out.append((r + 1, edges[r], edges[r + 1]))
    return out


def zipf_items(df: DataFrame, key: str, rho: float, universe: int = UNIVERSE, item: str = "item") -> DataFrame:
    """``df`` with a Zipf-distributed rank, a fixed function of the integer column ``key``.

    The rank intervals are cut at 1,024 equal slots of the range, so finding one is an equality join with a table of a
    few thousand rows at most (its size depends on the universe alone) and a comparison.
    """
    spark = df.sparkSession
    step = 2**22
    rows = [(slot, lo, hi, r) for r, lo, hi in zipf_bounds(rho, universe) if hi > lo for slot in range(lo // step, (hi - 1) // step + 1)]
    table = spark.createDataFrame(rows, "slot long, lo long, hi long, rank long")
    u = F.expr(f"({key} * 2654435761 + 12345) % 4294967296")
    drawn = df.withColumn("_u", u).withColumn("_slot", F.shiftright("_u", 22))
    return drawn.join(F.broadcast(table), (F.col("_slot") == F.col("slot")) & (F.col("_u") >= F.col("lo")) & (F.col("_u") < F.col("hi"))).withColumnRenamed("rank", item).drop("_u", "_slot", "slot", "lo", "hi")
