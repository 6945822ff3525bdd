"""Merging long summaries: pairwise, as a tree, and flat.

An item's estimate after a merge is the sum of all floors plus what it has above the floor where it is kept, so one sum per
item does what repeated pairwise merges do, without their intermediate cuts. Heads (kind 'block') are summed in the same
aggregate as the items, so a merge reads its input once and joins nothing.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .local import floor_of


def _sums(local: DataFrame, keys: list[str]) -> DataFrame:
    """Per group its head (n, floors) and per item what it has above the floors."""
    return local.groupBy(*keys, "kind", "item").agg(F.sum("n").alias("n"), F.sum("floor").alias("f"), F.sum(F.col("est") - F.col("floor")).alias("e"), F.sum(F.col("err") - F.col("floor")).alias("r"))


def _order() -> list:
    return [F.col("kind"), F.col("e").desc(), F.col("item")]  # the head, then items by estimate; ties are total


def _cut(sums: DataFrame, keys: list[str], k: int, rule: str) -> DataFrame:
    """The head and the k largest items of each group, with the group's n and the floor that the rule gives."""
    group = Window.partitionBy(*keys)
    ranked = sums.select("*", (F.row_number().over(group.orderBy(*_order())) - 1).alias("_rank")).filter(f"_rank <= {k + 1}")
    item = F.col("kind") == "item"
    known = ranked.select("*", F.max(F.when(~item, F.col("f"))).over(group).alias("floors"), F.max(F.when(~item, F.col("n"))).over(group).alias("total"))
    floored = known.select("*", floor_of(rule, k, group, F.col("floors"), F.col("_rank"), item, F.col("e")).cast("long").alias("floor")).filter(f"_rank <= {k}")
    return floored.select(*keys, "kind", F.col("total").alias("n"), "floor", "item", F.when(item, F.col("floors") + F.col("e")).alias("est"), F.when(item, F.col("floors") + F.col("r")).alias("err"))


def merge_groups(local: DataFrame, k: int, keys: list[str], floor_rule: str = "spare_zero") -> DataFrame:
    """All summaries of each group in one step, for groups of a bounded number of summaries: one exchange, by group."""
    return _cut(_sums(local.repartition(*keys), keys), keys, k, floor_rule)


def merge_flat(local: DataFrame, k: int, floor_rule: str = "spare_zero", by: tuple[str, ...] = ()) -> DataFrame:
    """One summary of all blocks (per group of ``by``): one shuffle of at most blocks times k rows, summed in the map tasks.

    A hot item has one row per block at most. What meets in one task is k + 2 rows of every task (per group).
    """
    sums = _sums(local, list(by))
    if not by:
        sums = sums.orderBy(*_order()).limit(k + 2)
    return _cut(sums.withColumn("block", F.lit(0).cast("long")), [*by, "block"], k, floor_rule)


def merge_tree(local: DataFrame, k: int, blocks: int, fan_in: int = 2, floor_rule: str = "spare_zero", by: tuple[str, ...] = ()) -> DataFrame:
    """Repeated merges of ``fan_in`` neighbours with a cut after each, one exchange a round; the rounds follow from ``blocks``."""
    while blocks > 1:
        local = merge_groups(local.withColumn("block", F.expr(f"block div {fan_in}")), k, [*by, "block"], floor_rule)
        blocks = -(-blocks // fan_in)
    return local


def merge_pair(a: DataFrame, b: DataFrame, k: int, floor_rule: str = "spare_zero") -> DataFrame:
    """Two long summaries of one block each into one: full outer join on the item, then the cut."""
    left, right = (s.filter("kind = 'item'").select(F.col("item").alias(f"item_{t}"), F.col("est").alias(f"est_{t}"), F.col("err").alias(f"err_{t}")) for s, t in ((a, "a"), (b, "b")))
    heads = [s.filter("kind = 'block'").agg(F.coalesce(F.sum("n"), F.lit(0)).alias(f"n_{t}"), F.coalesce(F.sum("floor"), F.lit(0)).alias(f"floor_{t}")) for s, t in ((a, "a"), (b, "b"))]
    both = heads[0].crossJoin(heads[1])  # one row
    met = left.join(right, F.col("item_a").eqNullSafe(F.col("item_b")), "full_outer").select(F.coalesce("item_a", "item_b").alias("item"), "est_a", "err_a", "est_b", "err_b")
    floors = F.col("floor_a") + F.col("floor_b")
    items = met.crossJoin(F.broadcast(both)).select(
        F.lit("item").alias("kind"),
        "item",
        F.lit(None).cast("long").alias("n"),
        F.lit(None).cast("long").alias("f"),
        (F.coalesce("est_a", "floor_a") + F.coalesce("est_b", "floor_b") - floors).alias("e"),
        (F.coalesce("err_a", "floor_a") + F.coalesce("err_b", "floor_b") - floors).alias("r"),
    )
    long = F.lit(None).cast("long")
    head = both.select(F.lit("block").alias("kind"), F.lit(None).cast(met.schema["item"].dataType).alias("item"), (F.col("n_a") + F.col("n_b")).alias("n"), floors.alias("f"), long.alias("e"), long.alias("r"))
    best = head.unionByName(items).orderBy(*_order()).limit(k + 2)
    return _cut(best.withColumn("block", F.lit(0).cast("long")), ["block"], k, floor_rule)
