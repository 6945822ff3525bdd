"""The experiments: one against two levels over block counts, counters and skew; stream sizes; audits of every plan; errors.

Cells of a sweep are dealt as blocks of one plan: block number = cell * SPAN + block within the cell, so a sweep costs
as many exchanges as a single run. What is measured in seconds is in bench.py; here are the columns that data decide.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .functions import items as I
from .functions import sql as S
from .operators import blocks as B
from .operators import exact as E
from .operators import measures as M
from .operators import surround as O
from .operators.local import exact_local, local_summaries
from .operators.merge import merge_groups, merge_tree
from .plans.engine import candidates, frequent_items, summarise
from .session import scratch, use_library
from .spec import FrequentSpec
from .workloads import _ALL_TRUE, _FIRST, _FLAT_SQL, _K, _LINE_TIMES, _VALUE, _WORDS_SQL, _flat, _having, _sql_cut, _sql_merge, _words, _zipf_sql, line_times, query, table

SPAN, GROUP = 4096, 8
BLOCKS, SKEWS = (32, 64, 128, 256, 512), (1.1, 1.8)


# ---- one level against two, over blocks, counters and skew ---------------------------------------------------------------


def _cells(spark, sf_dir) -> tuple[DataFrame, DataFrame]:
    """(block, item) of every cell, and the items of every skew."""
    events = table(spark, sf_dir, "events").select("event_id")
    n = events.count()
    drawn = reduce(DataFrame.unionByName, [I.zipf_items(events, "event_id", rho).withColumn("s", F.lit(i).cast("long")) for i, rho in enumerate(SKEWS)])
    blocks = F.explode(F.array(*[F.struct(F.lit(j).cast("long").alias("j"), F.lit(p).cast("long").alias("p")) for j, p in enumerate(BLOCKS)]))
    cells = drawn.select("*", blocks.alias("c")).select(F.expr(f"(s * {len(BLOCKS)} + c.j) * {SPAN} + ((event_id + 1) * c.p - 1) div {n}").alias("block"), "item")
    return cells, drawn.select("s", "item")


def _graded(merged: DataFrame, sent: DataFrame, items: DataFrame, k: int) -> DataFrame:
    """One row per cell: size, floor, rows sent to the root, and accuracy against exact counts."""
    names = F.create_map(*[x for i, rho in enumerate(SKEWS) for j, p in enumerate(BLOCKS) for x in (F.lit(i * len(BLOCKS) + j).cast("long"), F.struct(F.lit(rho).alias("skew"), F.lit(p).cast("long").alias("blocks")))])
    exact = items.groupBy("s", "item").agg(F.count(F.lit(1)).alias("cnt"))
    total = items.groupBy("s").agg(F.count(F.lit(1)).alias("total"))
    true = exact.join(total, "s").withColumn("is_true", F.col("cnt") >= F.expr(f"total div {k} + 1"))
    heads = merged.filter("kind = 'block'").select(F.col("block").alias("cell"), "n", "floor", F.expr(f"block div {len(BLOCKS)}").alias("s"))
    said = merged.filter(f"kind = 'item' AND est >= n div {k} + 1").select(F.col("block").alias("cell"), "item", "est", F.expr(f"block div {len(BLOCKS)}").alias("s"))
    per = said.join(true, ["s", "item"]).groupBy("cell").agg(F.count(F.lit(1)).alias("reported"), F.sum(F.col("is_true").cast("long")).alias("hits"), F.avg(F.abs(F.col("est") - F.col("cnt")) / F.col("cnt")).alias("are"))
    truths = true.filter("is_true").groupBy("s").agg(F.count(F.lit(1)).alias("true_items"))
    out = heads.join(per, "cell", "left").join(truths, "s", "left").join(sent, "cell").na.fill(0, ["reported", "hits", "true_items"])
    ratio = lambda over: F.round(F.when(F.col(over) == 0, F.lit(1.0)).otherwise(F.col("hits") / F.col(over)), 6)
    name = F.element_at(names, F.col("cell"))
    return out.select(name["skew"].alias("skew"), name["blocks"].alias("blocks"), "n", "floor", "sent", "reported", "true_items", "hits", ratio("reported").alias("precision"), ratio("true_items").alias("recall"), F.round(F.coalesce("are", F.lit(0.0)), 6).alias("are"))


def sweep(spark, sf_dir, k: int, levels: int) -> DataFrame:
    cells, items = _cells(spark, sf_dir)
    local = exact_local(cells, "item", FrequentSpec(k), "block")
    span = SPAN
    if levels == 2:
        local, span = merge_groups(local.withColumn("block", F.expr(f"block div {GROUP}")), k, ["block"]), SPAN // GROUP
    local = local.withColumn("cell", F.expr(f"block div {span}"))
    sent = local.filter("kind = 'item'").groupBy("cell").agg(F.count(F.lit(1)).alias("sent"))
    merged = merge_groups(local.withColumn("block", F.col("cell")).drop("cell"), k, ["block"])
    return _graded(merged, sent, items, k)


def _sweep_sql(k: int, levels: int) -> str:
    drawn = " UNION ALL ".join(f"SELECT {i} AS s, z.r AS item, e.event_id {_zipf_sql(rho).split('SELECT z.r AS item', 1)[1]}" for i, rho in enumerate(SKEWS))
    cells = ", ".join(f"({j}, {p})" for j, p in enumerate(BLOCKS))
    first = f"d AS ({drawn}), b AS (SELECT (s * {len(BLOCKS)} + j) * {SPAN} + ((event_id + 1) * p - 1) // (SELECT count(*) FROM events) AS block, item FROM d, (VALUES {cells}) v(j, p)), c AS (SELECT block, item, count(*) AS est, 0 AS err, 0 AS floors, sum(count(*)) OVER (PARTITION BY block) AS n FROM b GROUP BY block, item), {_sql_cut('l', 'c', k, 'spare_zero')}"
    root, span = "l", SPAN
    if levels == 2:
        first += f", {_sql_merge('g', 'l', f'block // {GROUP}', k)}"
        root, span = "g", SPAN // GROUP
    names = ", ".join(f"({i * len(BLOCKS) + j}, {i}, CAST({rho} AS DOUBLE), {p})" for i, rho in enumerate(SKEWS) for j, p in enumerate(BLOCKS))
    return f"""WITH {first}, {_sql_merge('m', root, f'block // {span}', k)},
names AS (SELECT * FROM (VALUES {names}) v(cell, s, skew, blocks)),
sent AS (SELECT block // {span} AS cell, count(*) AS sent FROM {root} GROUP BY 1),
t AS (SELECT s, item, count(*) AS cnt, count(*) >= (SELECT count(*) FROM events) // {k} + 1 AS is_true FROM d GROUP BY 1, 2),
x AS (SELECT names.cell, count(*) AS reported, count(*) FILTER (t.is_true) AS hits, avg(abs(m.est - t.cnt) / t.cnt) AS are FROM m JOIN names ON m.block = names.cell JOIN t ON t.s = names.s AND t.item = m.item WHERE m.est >= m.n // {k} + 1 GROUP BY 1),
h AS (SELECT block AS cell, max(n) AS n, max(floor) AS floor FROM m GROUP BY 1), tt AS (SELECT s, count(*) FILTER (is_true) AS true_items FROM t GROUP BY 1)
SELECT skew, CAST(blocks AS BIGINT) AS blocks, h.n, h.floor, sent.sent, coalesce(reported, 0) AS reported, true_items, coalesce(hits, 0) AS hits,
 round(CASE WHEN coalesce(reported, 0) = 0 THEN 1.0 ELSE hits / reported END, 6) AS precision, round(CASE WHEN true_items = 0 THEN 1.0 ELSE coalesce(hits, 0) / true_items END, 6) AS recall, round(coalesce(are, 0), 6) AS are
FROM h JOIN names ON names.cell = h.cell JOIN sent ON sent.cell = h.cell JOIN tt ON tt.s = names.s LEFT JOIN x ON x.cell = h.cell"""


for _k in (20, 100, 500):
    for _levels in (1, 2):
        query(f"sweep_blocks_{'single' if _levels == 1 else 'two_level'}_k{_k}", _sweep_sql(_k, _levels))(lambda s, d, k=_k, levels=_levels: sweep(s, d, k, levels))


_TWO = "SELECT 'events' AS stream, CAST(floor(value) AS BIGINT) AS item FROM events UNION ALL SELECT 'lineitem', l_suppkey FROM lineitem"


@query("two_stream_sizes_k50", f"WITH i AS ({_TWO}), c AS (SELECT stream, item, count(*) AS cnt FROM i GROUP BY 1, 2), n AS (SELECT stream, CAST(sum(cnt) AS BIGINT) AS n FROM c GROUP BY 1) SELECT c.stream, item, cnt, n FROM c JOIN n ON c.stream = n.stream WHERE cnt >= n // 50 + 1")
def two_stream_sizes(spark, sf_dir):
    """Streams of two sizes through one plan, each against its own n."""
    rows = table(spark, sf_dir, "events").select(F.lit("events").alias("stream"), F.expr(_VALUE).alias("item")).unionByName(table(spark, sf_dir, "lineitem").select(F.lit("lineitem").alias("stream"), F.col("l_suppkey").alias("item")))
    return frequent_items(rows, "item", FrequentSpec(50, by=("stream",)), with_meta=True)


# ---- every plan keeps its bounds, also where a block's counters all cancel ---------------------------------------------------

_CANCEL = "CASE WHEN event_id < (SELECT count(*) FROM events) // 2 THEN event_id % 3 WHEN event_id % 10 < 8 THEN 0 ELSE 100 + event_id % 7 END"


def cancelled(spark, sf_dir) -> DataFrame:
    """(event_id, item, block): the first half repeats three items in turn, which leaves two decrementing counters nothing."""
    events = table(spark, sf_dir, "events").select("event_id")
    n = events.count()
    rows = events.select("event_id", F.expr(_CANCEL.replace("(SELECT count(*) FROM events) // 2", str(n // 2))).alias("item"))
    return B.by_index(rows, "event_id", 6, n)


def _plans(spark, sf_dir, kernel: str) -> DataFrame:
    rows = cancelled(spark, sf_dir)
    exact = E.exact_counts(rows, "item")
    order = None if kernel == "exact_local" else "event_id"
    out = []
    for rule in ("spare_zero", "tight"):
        for levels, merge in ((1, "flat"), (2, "flat"), (1, "tree"), (2, "tree")):
            spec = FrequentSpec(3, kernel=kernel, floor_rule=rule, levels=levels, merge=merge, group=2)
            summary = summarise(rows, "item", spec, "block", order, blocks=6)
            out.append(M.audit(summary, exact, 3).select(F.lit(f"{rule} {levels} {merge}").alias("plan"), "*"))
    return reduce(DataFrame.unionByName, out)


_PLANS_SQL = " UNION ALL ".join(_ALL_TRUE.replace("SELECT ", f"SELECT '{rule} {levels} {merge}' AS plan, ", 1) for rule in ("spare_zero", "tight") for levels, merge in ((1, "flat"), (2, "flat"), (1, "tree"), (2, "tree")))
for _kernel in ("scalar", "batched", "exact_local", "misra_gries"):
    query(f"audit_plans_{_kernel}", _PLANS_SQL)(lambda s, d, kernel=_kernel: _plans(s, d, kernel))
for _levels in (1, 2):
    query(f"mg_cancelled_levels{_levels}", _having(f"SELECT {_CANCEL} AS item FROM events", 3))(
        lambda s, d, levels=_levels: frequent_items(cancelled(s, d), "item", FrequentSpec(3, kernel="misra_gries", levels=levels, group=1), "block", "event_id")
    )
for _kernel in ("batched", "scalar", "misra_gries"):
    query(f"words_in_task_fold_{_kernel}", _having(_WORDS_SQL.format("documents"), 500))(
        lambda s, d, kernel=_kernel: frequent_items(_words(s, d).repartition(8), "item", FrequentSpec(500, kernel=kernel, levels=2, group=4))
    )
query("words_blocks_per_core", _having(_WORDS_SQL.format("documents"), 500))(lambda s, d: frequent_items(_words(s, d), "item", FrequentSpec(500, blocks_per_core=2)))


@query("mg_isomorphism", "SELECT true AS same_counters, true AS same_lost")
def mg_isomorphism(spark, sf_dir):
    """k counters less their floor are the k - 1 decrementing counters: same items, same counts, same loss."""
    rows = table(spark, sf_dir, "events").select("event_id", F.expr(_VALUE).alias("item")).repartition(1).sortWithinPartitions("event_id")
    spaced, lost = (local_summaries(rows, "item", FrequentSpec(20, kernel=kernel)).filter("kind = 'item'").select("item", F.expr("est - floor").alias("c"), "floor") for kernel in ("scalar", "misra_gries"))
    met = spaced.filter("c > 0").join(lost.withColumnsRenamed({"c": "d", "floor": "lost"}), "item", "full")
    return met.agg(F.coalesce(F.bool_and(F.coalesce(F.col("c") == F.col("d"), F.lit(False))), F.lit(True)).alias("same_counters"), F.coalesce(F.bool_and(F.coalesce(F.col("floor") == F.col("lost"), F.lit(False))), F.lit(True)).alias("same_lost"))


# ---- iceberg queries and groups that went wrong before ------------------------------------------------------------------------

_SHARED = "CASE WHEN event_id % 100 < 40 THEN 'a' WHEN event_id % 100 < 68 THEN 'b' ELSE 'c' END"
query("iceberg_share_030", f"SELECT {_SHARED} AS item, count(*) AS cnt FROM events GROUP BY 1 HAVING count(*) > 0.3 * (SELECT count(*) FROM events)")(
    lambda s, d: E.iceberg(table(s, d, "events").select(F.expr(_SHARED).alias("item")), ["item"], share=0.3, approx=True)
)
_STAMPS = "TIMESTAMP '2024-01-01 00:00:00.000001' AS a, TIMESTAMP '2024-01-01 00:00:00' + INTERVAL 1 MICROSECOND * (event_id % 2) AS b"
query("iceberg_timestamp_pair", f"SELECT a, b, count(*) AS cnt FROM (SELECT {_STAMPS} FROM events) GROUP BY 1, 2 HAVING count(*) > 0.2 * (SELECT count(*) FROM events)")(
    lambda s, d: E.iceberg(
        table(s, d, "events").select(F.expr("TIMESTAMP_NTZ '2024-01-01 00:00:00.000001'").alias("a"), F.expr("TIMESTAMP_NTZ '2024-01-01 00:00:00' + make_dt_interval(0, 0, 0, (event_id % 2) * 0.000001)").alias("b")), ["a", "b"], share=0.2, approx=True
    )
)
_LANG = "CASE WHEN doc_id % 5 = 0 THEN NULL ELSE lang END"
for _kernel in ("batched", "exact_local", "scalar"):
    query(
        f"grouped_null_lang_{_kernel}",
        f"WITH i AS (SELECT {_LANG} AS lang, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS item FROM documents), c AS (SELECT lang, item, count(*) AS cnt FROM i GROUP BY 1, 2), n AS (SELECT lang, CAST(sum(cnt) AS BIGINT) AS n FROM c GROUP BY 1) SELECT c.lang, item, cnt FROM c JOIN n ON c.lang IS NOT DISTINCT FROM n.lang WHERE cnt >= n // 60 + 1",
    )(lambda s, d, kernel=_kernel: frequent_items(I.words(table(s, d, "documents").select("text", F.expr(_LANG).alias("lang")), keep=("lang",)), "item", FrequentSpec(60, by=("lang",), kernel=kernel)))
query("share_threshold", "SELECT event_type AS item, count(*) AS cnt FROM events GROUP BY 1 HAVING count(*) > 0.15 * (SELECT count(*) FROM events)")(lambda s, d: E.iceberg(table(s, d, "events").withColumnRenamed("event_type", "item"), ["item"], share=0.15))
query("majority_vote", _having("SELECT CASE WHEN event_id % 5 < 3 THEN 'yes' ELSE event_type END AS item FROM events", 2))(lambda s, d: E.majority(table(s, d, "events").select(F.expr("CASE WHEN event_id % 5 < 3 THEN 'yes' ELSE event_type END").alias("item")), "item"))


# ---- accuracy over its scopes ---------------------------------------------------------------------------------------------------

_SCOPES = f"t AS (SELECT {_VALUE} AS item, count(*) AS cnt FROM events GROUP BY 1), e AS (SELECT m.item, m.est, m.n, t.cnt, abs(m.est - t.cnt) / t.cnt AS rel FROM m JOIN t ON m.item = t.item)"
query(
    "are_by_scope_k20",
    f"{_FLAT_SQL}, {_SCOPES} SELECT 'reported' AS scope, round(coalesce(avg(rel), 0), 6) AS are FROM e WHERE est >= n // {_K} + 1 UNION ALL SELECT 'monitored', round(coalesce(avg(rel), 0), 6) FROM e UNION ALL SELECT 'true', round(coalesce(avg(abs(coalesce(m.est, (SELECT max(floor) FROM m)) - t.cnt) / t.cnt), 0), 6) FROM t LEFT JOIN m ON t.item = m.item WHERE t.cnt >= (SELECT count(*) FROM events) // 500 + 1",
)(lambda s, d: _scopes(s, d))


def _scopes(spark, sf_dir) -> DataFrame:
    summary = _flat(spark, sf_dir)
    exact = E.exact_counts(table(spark, sf_dir, "events").select(F.expr(_VALUE).alias("item")), "item")
    true = E.exact_frequent(table(spark, sf_dir, "events").select(F.expr(_VALUE).alias("item")), "item", 500)
    return reduce(DataFrame.unionByName, [M.average_relative_error(summary, exact, over, _K, true).select(F.lit(over).alias("scope"), "are") for over in ("reported", "monitored", "true")])


_WORD_CELLS = f"b AS (SELECT doc_id % 8 AS block, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS item FROM documents), c AS (SELECT block, item, count(*) AS est, 0 AS err, 0 AS floors, sum(count(*)) OVER (PARTITION BY block) AS n FROM b GROUP BY block, item), {_sql_cut('l', 'c', 500, 'spare_zero')}, {_sql_merge('m', 'l', '0', 500)}"


@query(
    "accuracy_words",
    f"WITH {_WORD_CELLS}, t AS (SELECT item, count(*) AS cnt FROM b GROUP BY 1), tt AS (SELECT * FROM t WHERE cnt >= (SELECT count(*) FROM b) // 500 + 1), s AS (SELECT * FROM m WHERE est >= n // 500 + 1), x AS (SELECT (SELECT count(*) FROM s) AS reported, (SELECT count(*) FROM tt) AS true_items, (SELECT count(*) FROM s JOIN tt ON s.item = tt.item) AS hits) SELECT (SELECT max(n) FROM m) AS n, (SELECT max(floor) FROM m) AS floor, reported, true_items, hits, round(CASE WHEN reported = 0 THEN 1.0 ELSE hits / reported END, 6) AS precision, round(CASE WHEN true_items = 0 THEN 1.0 ELSE hits / true_items END, 6) AS recall, (SELECT round(coalesce(avg(abs(s.est - t.cnt) / t.cnt), 0), 6) FROM s JOIN t ON s.item = t.item) AS are FROM x",
)
def accuracy_words(spark, sf_dir):
    """Precision, recall and error of the words of eight blocks, 500 counters each."""
    rows = I.words(table(spark, sf_dir, "documents").select("text", F.expr("doc_id % 8").alias("block")), keep=("block",))
    return M.report(summarise(rows, "item", FrequentSpec(500, kernel="exact_local"), "block"), E.exact_counts(rows, "item"), 500)


_USERS = f"b AS (SELECT ((event_id + 1) * 16 - 1) // (SELECT count(*) FROM events) AS block, user_id AS item FROM events), c AS (SELECT block, item, count(*) AS est, 0 AS err, 0 AS floors, sum(count(*)) OVER (PARTITION BY block) AS n FROM b GROUP BY block, item), {_sql_cut('l', 'c', 100, 'stored_min')}, {_sql_merge('m', 'l', '0', 100, 'stored_min')}"


@query("false_positives_users_k100", f"WITH {_USERS} SELECT item FROM m WHERE est >= n // 100 + 1 AND item NOT IN (SELECT user_id FROM events GROUP BY 1 HAVING count(*) >= (SELECT count(*) FROM events) // 100 + 1)")
def false_positives_users(spark, sf_dir):
    """What a single pass reports wrongly of a flat distribution under the literal floor."""
    rows = B.by_index(table(spark, sf_dir, "events").select("event_id", F.col("user_id").alias("item")), "event_id", 16, table(spark, sf_dir, "events").count())
    summary = summarise(rows, "item", FrequentSpec(100, kernel="exact_local", floor_rule="stored_min"), "block")
    return M.false_positives(candidates(summary, 100), E.exact_frequent(rows, "item", 100))


query("efficiency_table", f"WITH {_LINE_TIMES} SELECT t.series, t.p, round(o.wall / t.wall / t.p, 4) AS efficiency FROM t JOIN t o ON t.series IS NOT DISTINCT FROM o.series AND o.p = 1 WHERE t.p > 1")(
    lambda s, d: M.scaling(line_times(s, d).withColumnRenamed("wall", "seconds")).filter("p > 1").select("series", "p", "efficiency")
)


# ---- the block-parallel plan against a replay of its kernel ---------------------------------------------------------------------


@query("blocks_parallel_bounds", "SELECT true AS never_missed, true AS bounded, true AS n_is_total")
def blocks_parallel_bounds(spark, sf_dir):
    """Sequential kernels in four blocks merged as a tree: no true item is missed, and estimates stay in their bounds."""
    rows = B.by_index(table(spark, sf_dir, "events").select("event_id", F.expr(_VALUE).alias("item")), "event_id", 4, table(spark, sf_dir, "events").count())
    local = local_summaries(rows, "item", FrequentSpec(40, kernel="scalar"), "block", "event_id")
    summary = merge_tree(local, 40, 4)
    exact = E.exact_counts(rows, "item")
    audit = M.audit(summary, exact, 40)
    missed = M.false_negatives(candidates(summary, 40), E.exact_frequent(rows, "item", 40)).agg(F.count(F.lit(1)).alias("m"))
    return audit.crossJoin(missed).select((F.col("m") == 0).alias("never_missed"), (F.col("never_under") & F.col("error_bounded") & F.col("missing_within_floor")).alias("bounded"), "n_is_total")


query("ordered_summary", f"{_FLAT_SQL} SELECT item, est, CAST(row_number() OVER (ORDER BY est, item) AS BIGINT) AS position FROM m")(lambda s, d: M.ordered(_flat(s, d)).select("item", "est", "position"))


# ---- surroundings and SQL ---------------------------------------------------------------------------------------------------------

_DAY = "SELECT event_type, CAST(CAST(ts AS DATE) AS VARCHAR) AS day FROM events"


@query("set_except_days", f"WITH d AS ({_DAY}), f AS (SELECT day, event_type AS item FROM d GROUP BY 1, 2 HAVING count(*) * 5 > (SELECT count(*) FROM d x WHERE x.day = d.day)) SELECT item FROM f WHERE day = (SELECT max(day) FROM d) EXCEPT SELECT item FROM f WHERE day = (SELECT min(day) FROM d)")
def set_except_days(spark, sf_dir):
    """Types frequent on the last day and not on the first."""
    rows = table(spark, sf_dir, "events").select(F.to_date("ts").cast("string").alias("day"), "event_type")
    found = E.exact_frequent(rows, "event_type", 5, by=("day",))
    ends = rows.agg(F.min("day").alias("lo"), F.max("day").alias("hi"))
    marked = found.crossJoin(F.broadcast(ends))  # one row
    return O.lost_items(marked.filter("day = hi"), marked.filter("day = lo"))


@query("sql_frequent", "SELECT event_type AS item, count(*) AS est FROM events GROUP BY 1 HAVING count(*) >= (SELECT count(*) FROM events) // 6 + 1")
def sql_frequent(spark, sf_dir):
    """Table function, merge and threshold in SQL text alone."""
    S.register(use_library(spark))
    table(spark, sf_dir, "events").createOrReplaceTempView("freq_events")
    return spark.sql(
        "SELECT item, sum(est) AS est FROM frequent_local(TABLE(SELECT event_type, user_id % 4 AS b FROM freq_events) PARTITION BY (b), 50) GROUP BY item HAVING sum(est) >= (SELECT count(*) FROM freq_events) div 6 + 1"
    )


@query("sql_estimate", f"{_FLAT_SQL} SELECT a.item, coalesce(m.est, (SELECT max(floor) FROM m)) AS est FROM (SELECT DISTINCT {_VALUE} AS item FROM events) a LEFT JOIN m ON a.item = m.item")
def sql_estimate(spark, sf_dir):
    """Estimates of single items from a packed summary by built-in expressions."""
    packed = S.pack(_flat(spark, sf_dir), _K).select("summary")
    asked = table(spark, sf_dir, "events").select(F.expr(_VALUE).alias("item")).distinct()
    return asked.crossJoin(F.broadcast(packed)).select("item", S.freq_estimate("summary", F.col("item")).alias("est"))


query("builtin_freq_items", "SELECT true AS contains_all")(lambda s, d: _superset(O.builtin_freq_items(table(s, d, "events"), "event_type", 0.15), E.iceberg(table(s, d, "events").withColumnRenamed("event_type", "item"), ["item"], share=0.15)))


def _superset(said: DataFrame, true: DataFrame) -> DataFrame:
    return M.false_negatives(said, true).agg((F.count(F.lit(1)) == 0).alias("contains_all"))


@query("sample_estimate", "SELECT true AS within_bound")
def sample_estimate(spark, sf_dir):
    """Counts from a tenth of the words, scaled: within six standard deviations for every word of over 1,000 occurrences."""
    exact = E.exact_counts(_words(spark, sf_dir), "item").filter("cnt > 1000")
    met = exact.join(O.sample_estimate(_words(spark, sf_dir), "item", 0.1, 7), "item", "left")
    return met.agg(F.coalesce(F.bool_and(F.abs(F.coalesce("est", F.lit(0)) - F.col("cnt")) <= 6 * F.sqrt(F.col("cnt") * 9)), F.lit(True)).alias("within_bound"))


@query("builtin_count_min", "SELECT event_type AS item, true AS never_under, true AS within_bound FROM events GROUP BY 1")
def builtin_count_min(spark, sf_dir):
    """Spark's count-min sketch, read back per item: never under the count, over it by at most the share asked."""
    events = table(spark, sf_dir, "events")
    sketch = bytes(O.builtin_count_min(events, "event_type", 0.01).first()["sketch"])
    jvm = spark.sparkContext._jvm
    read = jvm.org.apache.spark.util.sketch.CountMinSketch.readFrom(sketch)
    exact = E.exact_counts(events, "event_type").collect()  # five types
    n = sum(r["cnt"] for r in exact)
    rows = [(r["item"], read.estimateCount(r["item"]) >= r["cnt"], read.estimateCount(r["item"]) <= r["cnt"] + 0.01 * n) for r in exact]
    return spark.createDataFrame(rows, "item string, never_under boolean, within_bound boolean")


# ---- streams: windows, sessions, late rows -----------------------------------------------------------------------------------------


def _stream_parts():
    from . import streaming
    from .workloads import _events_stream

    return streaming, _events_stream


@query("stream_sliding", "SELECT start, event_type AS item, count(*) AS cnt FROM (SELECT event_type, unnest([date_trunc('day', ts), date_trunc('day', ts) - INTERVAL 1 DAY]) AS start FROM events) GROUP BY 1, 2")
def stream_sliding(spark, sf_dir):
    s, stream = _stream_parts()
    out = s.to_files(s.window_counts(stream(spark, sf_dir), "ts", "event_type", "2 days", "1 day"), scratch(spark, "sliding"), "complete")
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


_SESSIONS = "SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 6 HOUR THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)"


@query("stream_session", f"SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 6 HOUR AS \"end\", count(*) AS cnt FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM ({_SESSIONS})) GROUP BY user_id, s")
def stream_session(spark, sf_dir):
    s, stream = _stream_parts()
    out = s.to_files(s.session_counts(stream(spark, sf_dir), "ts", "user_id", "6 hours"), scratch(spark, "sessions"), "complete")
    return out.select("user_id", F.col("start").cast("timestamp_ntz").alias("start"), F.col("end").cast("timestamp_ntz").alias("end"), "cnt")


@query("stream_window_summaries", "SELECT date_trunc('day', ts) AS start, event_type AS item, count(*) AS est FROM events GROUP BY 1, 2")
def stream_window_summaries(spark, sf_dir):
    """Bounded summaries per window; exact here, as every type has a counter."""
    s, stream = _stream_parts()
    store = s.SummaryStore(spark, scratch(spark, "windows"))
    s.window_frequent(stream(spark, sf_dir), "ts", "event_type", FrequentSpec(20), store, "1 day").trigger(availableNow=True).option("checkpointLocation", scratch(spark, "offsets")).start().awaitTermination()
    return store.latest().filter("kind = 'item'").select(F.col("start").cast("timestamp_ntz").alias("start"), "item", "est")


@query("stream_late_rows", "SELECT count(*) FILTER (CAST(ts AS DATE) >= (SELECT CAST(max(ts) AS DATE) FROM events)) AS counted, count(*) FILTER (CAST(ts AS DATE) < (SELECT CAST(max(ts) AS DATE) FROM events)) AS late FROM events")
def stream_late_rows(spark, sf_dir):
    """The last day comes first, in two batches; all older rows come after the watermark has passed them."""
    s, _ = _stream_parts()
    events = table(spark, sf_dir, "events").select("ts", "event_type")
    last = events.agg(F.to_date(F.max("ts")).alias("d")).first()["d"]
    path = scratch(spark, "late")
    newest = F.to_date("ts") >= F.lit(last)
    for part, rows in (("a", events.filter(newest & (F.minute("ts") < 30))), ("b", events.filter(newest & (F.minute("ts") >= 30))), ("c", events.filter(~newest))):
        rows.coalesce(1).write.parquet(f"{path}/day={part}")
    sdf = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).option("latestFirst", "false").parquet(f"{path}/day=*")
    counted, late = s.counted_and_late(s.window_counts(sdf, "ts", "event_type", "1 day"), scratch(spark, "late-out"))
    return spark.createDataFrame([(counted, late)], "counted long, late long")
