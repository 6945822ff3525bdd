"""Estimates of single items, accuracy and cost measures, and the rank-frequency check."""

from __future__ import annotations

import math
import time
from collections.abc import Callable, Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..spec import threshold_col


def estimate(summary: DataFrame, items: DataFrame) -> DataFrame:
    """(item, est, lower, upper) of asked items; one without a counter may have anything from 0 to the floor."""
    head = summary.filter("kind = 'block'").agg(F.max("floor").alias("f"))
    kept = summary.filter("kind = 'item'").select("item", "est", "err")
    asked = items.select("item").distinct().join(kept, "item", "left").crossJoin(F.broadcast(head))
    return asked.select("item", F.coalesce("est", "f").alias("est"), F.coalesce(F.col("est") - F.col("err"), F.lit(0)).cast("long").alias("lower"), F.coalesce("est", "f").alias("upper"))


def errors(reported: DataFrame, exact: DataFrame) -> DataFrame:
    """(item, est, cnt, rel_err): what is estimated against what is true; items must have occurred."""
    return reported.select("item", "est").join(exact.select("item", "cnt"), "item").withColumn("rel_err", F.abs(F.col("est") - F.col("cnt")) / F.col("cnt"))


def average_relative_error(reported: DataFrame, exact: DataFrame, over: str | None = None, k: int | None = None, true: DataFrame | None = None) -> DataFrame:
    """One row; 0 where nothing is measured.

    Without ``over`` the rows of ``reported`` are measured. With it ``reported`` is a global summary, and measured are its
    ``reported`` items (at or above the threshold for k), all ``monitored`` ones, or the ``true`` ones of the table ``true``,
    of which one without a counter is estimated by the floor.
    """
    if over not in (None, "reported", "monitored", "true"):
        raise ValueError(f"over is {over!r}; it must be one of reported, monitored, true")
    if over == "reported":
        reported = reported.filter("kind = 'item'").filter(F.col("est") >= threshold_col("n", k))
    elif over == "monitored":
        reported = reported.filter("kind = 'item'")
    elif over == "true":
        reported = estimate(reported, true)
    return errors(reported, exact).agg(F.round(F.coalesce(F.avg("rel_err"), F.lit(0.0)), 6).alias("are"))


def ordered(summary: DataFrame) -> DataFrame:
    """A summary's counters by ascending estimate with their position; the least is first, as a merge reads them.

    A summary has a bounded number of counters, so its order is one task's work.
    """
    w = Window.partitionBy("block").orderBy("est", "item")
    return summary.filter("kind = 'item'").withColumn("position", F.row_number().over(w).cast("long"))


def false_positives(reported: DataFrame, true: DataFrame) -> DataFrame:
    return reported.select("item").join(true.select("item"), "item", "left_anti")


def false_negatives(reported: DataFrame, true: DataFrame) -> DataFrame:
    return true.select("item").join(reported.select("item"), "item", "left_anti")


def precision_recall(reported: DataFrame, true: DataFrame) -> DataFrame:
    """One row: reported, true_items, hits, precision, recall; a ratio over nothing is 1."""
    r = reported.select("item").distinct().withColumn("r", F.lit(1))
    t = true.select("item").distinct().withColumn("t", F.lit(1))
    met = r.join(t, "item", "full_outer").agg(F.count("r").alias("reported"), F.count("t").alias("true_items"), F.coalesce(F.sum(F.col("r") * F.col("t")), F.lit(0)).cast("long").alias("hits"))
    ratio = lambda over: F.round(F.when(F.col(over) == 0, F.lit(1.0)).otherwise(F.col("hits") / F.col(over)), 6)
    return met.withColumn("precision", ratio("reported")).withColumn("recall", ratio("true_items"))


def report(summary: DataFrame, exact: DataFrame, k: int) -> DataFrame:
    """One row of accuracy for a global summary: n, floor, reported, true, precision, recall, ARE over reported items."""
    head = summary.filter("kind = 'block'").select("n", "floor")
    rows = summary.filter("kind = 'item'").withColumn("threshold", threshold_col("n", k))
    said = rows.filter("est >= threshold")
    n = exact.agg(F.sum("cnt").alias("n"))
    true = exact.crossJoin(F.broadcast(n)).filter(F.col("cnt") >= threshold_col("n", k))
    return F.broadcast(head).crossJoin(precision_recall(said, true)).crossJoin(average_relative_error(said, exact))


def audit(summary: DataFrame, exact: DataFrame, k: int, floor_bound: bool = True) -> DataFrame:
    """One row of booleans: the bounds that every summary must keep."""
    head = summary.filter("kind = 'block'").agg(F.sum("n").alias("n"), F.max("floor").alias("floor"))
    met = exact.select("item", "cnt").join(summary.filter("kind = 'item'").select("item", "est", "err"), "item", "full_outer").crossJoin(F.broadcast(head))
    every = lambda c: F.coalesce(F.bool_and(c), F.lit(True))
    return met.agg(
        every(F.when(F.col("est").isNotNull(), F.coalesce("cnt", F.lit(0)) <= F.col("est"))).alias("never_under"),
        every(F.when(F.col("est").isNotNull(), F.col("est") - F.coalesce("cnt", F.lit(0)) <= F.col("err"))).alias("error_bounded"),
        every(F.when(F.col("est").isNotNull(), F.col("err") <= F.col("floor"))).alias("error_within_floor"),
        every(F.when(F.col("est").isNull(), F.col("cnt") <= F.col("floor"))).alias("missing_within_floor"),
        every(F.col("floor") * k <= F.col("n")).alias("floor_within_share"),
        F.coalesce(F.max("n") == F.sum("cnt"), F.lit(True)).alias("n_is_total"),
    )


def rank_frequency(counts: DataFrame, top: int = 2000) -> DataFrame:
    """(rank, item, cnt, share so far) of the most frequent items, ties by item."""
    best = counts.orderBy(F.col("cnt").desc(), "item").limit(top)
    w = Window.orderBy(F.col("cnt").desc(), "item")
    whole = counts.agg(F.sum("cnt").alias("n"))
    ranked = best.withColumn("rank", F.row_number().over(w).cast("long")).withColumn("sofar", F.sum("cnt").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return ranked.crossJoin(F.broadcast(whole)).select("rank", "item", "cnt", F.round(F.col("sofar") / F.col("n"), 6).alias("cumulative_share"))


def zipf_fit(counts: DataFrame, top: int = 2000) -> DataFrame:
    """Slope of log frequency over log rank for the most frequent items."""
    r = rank_frequency(counts, top)
    return r.agg(F.round(F.regr_slope(F.log("cnt"), F.log("rank")), 6).alias("slope"), F.count(F.lit(1)).alias("ranks"))


def timed(action: DataFrame | Callable[[], object]) -> float:
    """Wall seconds of a full evaluation."""
    start = time.perf_counter()
    action() if callable(action) else action.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start


def dealt_times(df: DataFrame, series: str, key: str, cores: Sequence[int]) -> DataFrame:
    """(series, p, wall, compute): seconds of p workers that take the rows by key modulo p, a row taking one second.

    ``wall`` is the fullest worker's time, for which all wait, ``compute`` all work over p. Rows without a key go to worker 0.
    Rows are counted once, by key modulo the least common multiple of ``cores``, which decides every other remainder.
    """
    slot = F.pmod(F.coalesce(F.col(key).cast("long"), F.lit(0).cast("long")), F.lit(math.lcm(*cores)).cast("long"))
    counted = df.groupBy(F.col(series).alias("series"), slot.alias("slot")).agg(F.count(F.lit(1)).alias("rows"))
    dealt = counted.select("*", F.explode(F.array(*[F.lit(p) for p in cores])).alias("p"))
    workers = dealt.groupBy("series", "p", (F.col("slot") % F.col("p")).alias("worker")).agg(F.sum("rows").alias("rows"))
    return workers.groupBy("series", "p").agg(F.max("rows").cast("double").alias("wall"), (F.sum("rows").cast("double") / F.col("p")).alias("compute"))


def scaling(times: DataFrame) -> DataFrame:
    """(series, p, seconds) with speedup and parallel efficiency against the same series at p = 1; a null series is one, too."""
    base = times.filter("p = 1").select(F.col("series").alias("_series"), F.col("seconds").alias("_one"))
    return times.join(base, F.col("series").eqNullSafe(F.col("_series"))).select("series", "p", "seconds", F.round(F.col("_one") / F.col("seconds"), 4).alias("speedup"), F.round(F.col("_one") / F.col("seconds") / F.col("p"), 4).alias("efficiency"))


def scaling_slope(times: DataFrame) -> DataFrame:
    """Slope of log seconds over log p per series; -1 is ideal."""
    return times.groupBy("series").agg(F.round(F.regr_slope(F.log("seconds"), F.log("p")), 6).alias("slope"))


def fractional_overhead(times: DataFrame) -> DataFrame:
    """(series, p, wall, compute): what is not computing, per second of computing."""
    return times.withColumn("overhead", F.round((F.col("wall") - F.col("compute")) / F.col("compute"), 6))


def overhead_run(df: DataFrame, item: str, spec, cores: int) -> dict:
    """Wall seconds of a one-pass answer, the kernels' own seconds over the cores, and their ratio as overhead."""
    from ..operators.local import kernel_times
    from ..plans.engine import frequent_items

    own = kernel_times(df, item, spec).agg(F.sum("seconds").alias("s"), F.sum("n").alias("n"), F.sum("counters").alias("c")).first()
    wall = timed(frequent_items(df, item, spec))
    compute = own["s"] / cores
    return {"wall": wall, "compute": compute, "overhead": (wall - compute) / compute if compute else 0.0, "items": own["n"], "sent": own["c"]}


def cost_report(spark: SparkSession, df: DataFrame) -> dict:
    """Wall seconds, exchanges and, from the stages that ran, bytes shuffled and spilled, and rows sent."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    before = {s.stageId() for s in _stages(spark)}
    seconds = timed(df)
    ran = [s for s in _stages(spark) if s.stageId() not in before]
    return {
        "seconds": seconds,
        "exchanges": plan.count("Exchange hashpartitioning") + plan.count("Exchange SinglePartition"),
        "broadcasts": plan.count("BroadcastExchange"),
        "shuffle_bytes": sum(s.shuffleWriteBytes() for s in ran),
        "summary_rows": sum(s.shuffleWriteRecords() for s in ran),
        "spill_bytes": sum(s.diskBytesSpilled() for s in ran),
    }


def _stages(spark: SparkSession) -> list:
    """What the session's status store holds of its stages."""
    gateway = spark.sparkContext._gateway
    no_quantiles, every = gateway.new_array(gateway.jvm.double, 0), gateway.jvm.java.util.ArrayList()
    found = spark.sparkContext._jsc.sc().statusStore().stageList(every, False, False, no_quantiles, every)
    return [found.apply(i) for i in range(found.size())]
