"""The block-parallel plan: local summaries, one or two levels of merging, threshold, verification."""

from __future__ import annotations

from pyspark import StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.blocks import per_core, splits_of
from ..operators.exact import verify
from ..operators.local import folded_in_task, local_summaries
from ..operators.merge import merge_flat, merge_groups, merge_tree
from ..session import use_library
from ..spec import FrequentSpec, threshold_col


def summarise(df: DataFrame, item: str, spec: FrequentSpec, block: str | None = None, order: str | None = None, blocks: int | None = None) -> DataFrame:
    """The global long summary.

    On two levels, splits merge inside the worker: a task takes a group of them and sends one summary. Explicit blocks, and
    exact counts, which Spark makes in a shuffle, merge by group of neighbouring blocks first. ``blocks`` tells the tree its
    rounds; without it they follow from the heads of the summaries, which are kept for that (see :func:`release`).
    """
    use_library(df.sparkSession)
    if spec.blocks_per_core and block is None:
        df = per_core(df, spec.blocks_per_core)
    local = local_summaries(df, item, spec, block, order)
    by = tuple(spec.by)
    if spec.levels == 2:
        if block is None and not by and spec.kernel != "exact_local":
            local = folded_in_task(local, spec, splits_of(df))
        else:
            local = merge_groups(local.withColumn("block", F.expr(f"block div {spec.group}")), spec.size, [*by, "block"], spec.floor_rule)
        blocks = -(-blocks // spec.group) if blocks else None
    if spec.merge == "tree":
        kept = None
        if not blocks:
            kept = local = local.persist(StorageLevel.MEMORY_AND_DISK_2)
            blocks = (local.filter("kind = 'block'").agg(F.max("block").alias("b")).first()["b"] or 0) + 1
        out = merge_tree(local, spec.size, blocks, spec.fan_in or 2, spec.floor_rule, by)
        out._kept = kept
        return out
    return merge_flat(local, spec.size, spec.floor_rule, by)


def release(summary: DataFrame) -> None:
    """Drop what :func:`summarise` kept; the summary can then still be worked out anew."""
    kept = getattr(summary, "_kept", None)
    if kept is not None:
        kept.unpersist()


def candidates(summary: DataFrame, k: int, by: tuple[str, ...] = ()) -> DataFrame:
    """Items that may exceed n / k: the cut at the root, with what the summary guarantees of each."""
    reach = summary.filter("kind = 'item'").withColumn("threshold", threshold_col("n", k)).filter("est >= threshold")
    return reach.select(*by, "item", "est", "err", (F.col("est") - F.col("err")).alias("lower"), (F.col("est") - F.col("err") >= F.col("threshold")).alias("guaranteed"), "n", "threshold")


def frequent_items(df: DataFrame, item: str, spec: FrequentSpec | int, block: str | None = None, order: str | None = None, blocks: int | None = None, with_meta: bool = False, checked: bool = False, **options) -> DataFrame:
    """Frequent items of ``df``. One-pass: item, est, err, lower, guaranteed. Verified: item, cnt, exactly the true set.

    A verified answer takes n from the candidates' own summary: a group without candidates has no answer either, and all
    candidates carry their group's n, so nothing but the items is read twice. ``checked`` counts the items first and warns
    where k exceeds them.
    """
    spec = spec if isinstance(spec, FrequentSpec) else FrequentSpec(spec, **options)
    summary = summarise(df, item, spec, block, order, blocks)
    by = tuple(spec.by)
    if checked and not by:
        spec.validate(int(summary.filter("kind = 'block'").agg(F.sum("n").alias("n")).first()["n"] or 0))
    found = candidates(summary, spec.k, by)
    if spec.setting == "one_pass":
        return found if with_meta else found.drop("n", "threshold")
    out = verify(df, item, found, spec.k, spec.weight, spec.nulls, by)
    return out if with_meta else out.drop("n")
