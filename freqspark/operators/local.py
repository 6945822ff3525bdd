"""Local summaries: one per block, in the long shape.

Rows are (by..., block, kind, n, floor, item, est, err). Each block has one row of kind 'block' with its n and floor, also
if it has no items, and one row of kind 'item' per counter. The floor travels with every row, so no step sorts a summary.
"""

from __future__ import annotations

import time
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.window import Window

from ..functions.items import item_type
from ..kernels.batched import arrow_kernel, fold
from ..kernels.scalar import Summary, misra_gries_kernel, scalar_kernel
from ..session import use_library
from ..spec import FrequentSpec


def summary_schema(df: DataFrame, item: str, by: tuple[str, ...] = ()) -> T.StructType:
    return T.StructType(
        [
            *[df.schema[c] for c in by],
            T.StructField("block", T.LongType()),
            T.StructField("kind", T.StringType()),
            T.StructField("n", T.LongType()),
            T.StructField("floor", T.LongType()),
            T.StructField("item", item_type(df, item)),
            T.StructField("est", T.LongType()),
            T.StructField("err", T.LongType()),
        ]
    )


def projected(df: DataFrame, item: str, spec: FrequentSpec, *keep: str) -> DataFrame:
    """The item, its weight and what dealing needs, under the null policy. Negative zero and NaN are made equal."""
    kind = item_type(df, item)
    c = F.col(item)
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        c = F.when(F.isnan(c), F.lit(float("nan")).cast(kind)).otherwise(c + F.lit(0.0).cast(kind))
    cols = [*spec.by, *keep]
    out = df.select(*cols, c.alias("item"), *([F.col(spec.weight).cast("long").alias("weight")] if spec.weight else []))
    return out.filter("item IS NOT NULL") if spec.nulls == "skip" else out


def _values(x: Iterable) -> Iterator:
    return (tuple(v.values()) if isinstance(v, dict) else v for v in x)


def _run(spec: FrequentSpec, batches: Iterable[tuple[pa.Array, pa.Array | None]]) -> Summary:
    """A one-at-a-time kernel over batches as they come: no split is held."""
    if spec.kernel == "misra_gries":
        if spec.weight:
            raise ValueError("the misra_gries kernel takes no weights")
        s = misra_gries_kernel((x for values, _ in batches for x in _values(values.to_pylist())), spec.size)
        # an estimate plus what was lost, with a floor of the same, is a summary like the others: one merge serves all
        s.counters = {x: [c + s.floor, s.floor] for x, (c, _) in s.counters.items()}
        return s
    if not spec.weight:
        return scalar_kernel((x for values, _ in batches for x in _values(values.to_pylist())), spec.size, spec.tie)
    pairs = (p for values, ws in batches for p in zip(_values(values.to_pylist()), (w or 0 for w in ws.to_pylist()), strict=True))
    return scalar_kernel(pairs, spec.size, spec.tie, weighted=True)


def _shape(n: int, floor: int, block: int, items: pa.Array, est, err, lead=()) -> pa.Table:
    m = len(items) + 1
    one = lambda v, t: pa.array([v], t).take(pa.array([0] * m))
    none = pa.array([None], pa.int64())
    return pa.table(
        {name: one(value, t) for name, t, value in lead}
        | {
            "block": one(block, pa.int64()),
            "kind": pa.array(["block"] + ["item"] * (m - 1)),
            "n": one(n, pa.int64()),
            "floor": one(floor, pa.int64()),
            "item": pa.concat_arrays([pa.nulls(1, items.type), items]),
            "est": pa.concat_arrays([none, pa.array(est, pa.int64())]),
            "err": pa.concat_arrays([none, pa.array(err, pa.int64())]),
        }
    )


def _items(values: list, kind: pa.DataType) -> pa.Array:
    if pa.types.is_struct(kind):
        return pa.array([dict(zip([f.name for f in kind], v, strict=True)) for v in values], kind)
    return pa.array(values, kind)


def _table(s: Summary, block: int, kind: pa.DataType, lead=()) -> pa.Table:
    rows = s.rows()
    return _shape(s.n, s.floor, block, _items([r[0] for r in rows], kind), [r[1] for r in rows], [r[2] for r in rows], lead)


def _summarised(spec: FrequentSpec, batches: Iterator[tuple[pa.Array, pa.Array | None]], kinds: list[pa.DataType], block: int, lead=()) -> pa.Table | None:
    if spec.kernel == "batched":
        s = arrow_kernel(batches, spec.size)
        if s is None or not s.n:
            return None
        items, est, err = s.columns()
        return _shape(s.n, s.floor, block, items, est, err, lead)
    s = _run(spec, batches)
    return _table(s, block, kinds[0], lead) if s.n else None


def _parts(batches: Iterator[pa.RecordBatch], weighted: bool, kinds: list[pa.DataType]) -> Iterator[tuple[pa.Array, pa.Array | None]]:
    for b in batches:
        if not kinds:
            kinds.append(b.schema.field("item").type)
        yield b.column("item"), b.column("weight") if weighted else None


def local_summaries(df: DataFrame, item: str, spec: FrequentSpec, block: str | None = None, order: str | None = None) -> DataFrame:
    """One summary per block.

    Without ``block`` an input split is a block and no row moves. With it (and ``order``, the key that fixes the order in
    the block) rows are grouped by block. ``by`` columns give one summary per group and block.
    """
    use_library(df.sparkSession)
    if spec.kernel == "exact_local":
        return exact_local(df, item, spec, block)
    keep = [c for c in (block, order) if c]
    rows = projected(df, item, spec, *keep)
    schema = summary_schema(rows, "item", spec.by)
    weighted = bool(spec.weight)

    if block is None and not spec.by:

        def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            kinds: list[pa.DataType] = []
            t = _summarised(spec, _parts(batches, weighted, kinds), kinds, TaskContext.get().partitionId())
            if t is not None:
                yield from t.combine_chunks().to_batches()

        return rows.mapInArrow(split, schema)

    at = rows if block else rows.withColumn("block", F.spark_partition_id().cast("long"))
    at = at.withColumnRenamed(block, "block") if block and block != "block" else at

    def group(t: pa.Table) -> pa.Table:
        if order:
            t = t.sort_by(order)
        lead = [(c, t.schema.field(c).type, t.column(c)[0].as_py()) for c in spec.by]
        number = t.column("block")[0].as_py()
        kinds = [t.schema.field("item").type]
        out = _summarised(spec, _parts(iter(t.to_batches()), weighted, kinds), kinds, number, lead)
        return out if out is not None else _table(Summary(), number, kinds[0], lead)

    return at.groupBy(*spec.by, "block").applyInArrow(group, schema)


def kernel_times(df: DataFrame, item: str, spec: FrequentSpec) -> DataFrame:
    """(block, n, counters, seconds): the kernel's own seconds in every split, without what Spark adds.

    Reading and the Arrow transfer are waited for inside the kernel's loop and are taken out of its time.
    """
    use_library(df.sparkSession)
    rows = projected(df, item, spec)
    weighted = bool(spec.weight)

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        waited = 0.0

        def noted() -> Iterator[pa.RecordBatch]:
            nonlocal waited
            while True:
                start = time.perf_counter()
                b = next(batches, None)
                waited += time.perf_counter() - start
                if b is None:
                    return
                yield b

        start = time.perf_counter()
        kinds: list[pa.DataType] = []
        t = _summarised(spec, _parts(noted(), weighted, kinds), kinds, 0)
        spent = time.perf_counter() - start - waited
        n = t.column("n")[0].as_py() if t is not None else 0
        yield pa.RecordBatch.from_pylist([{"block": TaskContext.get().partitionId(), "n": n, "counters": t.num_rows - 1 if t is not None else 0, "seconds": spent}])

    return rows.mapInArrow(split, "block long, n long, counters long, seconds double")


def folded_in_task(local: DataFrame, spec: FrequentSpec, splits: int) -> DataFrame:
    """Level one inside the worker: every task takes ``spec.group`` splits, one after the other, and sends one summary.

    The kernels and the fold share a stage (a narrow coalesce), so the shuffle sees splits / group * k rows at most. A
    row of kind 'block' begins each split's summary.
    """
    schema = local.schema

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind: list[pa.DataType] = []

        def summaries() -> Iterator[Summary]:
            s: Summary | None = None
            for b in batches:
                kind[:] = [b.schema.field("item").type]
                values = list(_values(b.column("item").to_pylist()))
                for what, n, floor, x, est, err in zip(*(b.column(c).to_pylist() for c in ("kind", "n", "floor")), values, *(b.column(c).to_pylist() for c in ("est", "err")), strict=True):
                    if what == "block":
                        if s is not None:
                            yield s
                        s = Summary(n, floor, {})
                    else:
                        s.counters[x] = [est, err]
            if s is not None:
                yield s

        out = fold(summaries(), spec.size, spec.floor_rule)
        if out.n:
            yield from _table(out, TaskContext.get().partitionId(), kind[0]).combine_chunks().to_batches()

    return local.coalesce(max(1, -(-splits // spec.group))).mapInArrow(run, schema)


def exact_local(df: DataFrame, item: str, spec: FrequentSpec, block: str | None = None) -> DataFrame:
    """Local summaries by exact counts, cut to the counters: built-in operators only, spills where memory ends."""
    rows = projected(df, item, spec, *([block] if block else []))
    rows = rows.withColumnRenamed(block, "block") if block else rows.withColumn("block", F.spark_partition_id().cast("long"))
    keys = [*spec.by, "block"]
    one = F.sum("weight") if spec.weight else F.count(F.lit(1))
    counts = rows.groupBy(*keys, "item").agg(one.alias("e")).filter("e > 0")
    k, group = spec.size, Window.partitionBy(*keys)
    ranked = counts.select(*keys, "item", "e", F.sum("e").over(group).alias("n"), F.row_number().over(group.orderBy(F.col("e").desc(), "item")).alias("_rank")).filter(f"_rank <= {k + 1}")
    floor = floor_of(spec.floor_rule, k, group, F.lit(0), F.col("_rank"), F.lit(True), F.col("e"))
    kept = ranked.select(*keys, "item", "e", "n", "_rank", floor.cast("long").alias("floor")).filter(f"_rank <= {k}")
    # the first counter of a block also brings its head row
    seats = kept.select(*keys, F.explode(F.when(F.col("_rank") == 1, F.array(F.lit("block"), F.lit("item"))).otherwise(F.array(F.lit("item")))).alias("kind"), "n", "floor", "item", "e")
    own = F.col("kind") == "item"
    return seats.select(*keys, "kind", "n", "floor", F.when(own, F.col("item")).alias("item"), F.when(own, F.col("e")).alias("est"), F.when(own, F.lit(0)).cast("long").alias("err"))


def floor_of(rule: str, k: int, group, floors, rank, is_item, above):
    """The floor after a cut to k: ``rank`` numbers a group's items from 1 and k + 1 of them are there; ``above`` is the
    estimate less the inputs' ``floors``. An under-full result keeps the inputs' floors."""
    least = F.min(F.when(is_item & (rank <= k), above)).over(group) + floors
    if rule == "tight":
        return F.greatest(floors, F.coalesce(F.max(F.when(is_item & (rank == k + 1), above)).over(group) + floors, floors))
    if rule == "stored_min":
        return F.coalesce(least, floors)
    return F.when(F.max(F.when(is_item, rank)).over(group) >= k, least).otherwise(floors)
