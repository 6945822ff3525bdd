"""Registered queries over the given tables and the SQL they must equal.

Verified and exact answers are compared with plain counts. One-pass queries fix blocks by index and order by key; those
built on exact-local summaries have a closed form in SQL, and the sequential kernels are replayed by recursion.
"""

from __future__ import annotations

from collections.abc import Callable
from uuid import uuid4

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import items as I
from .functions import sql as S
from .operators import blocks as B
from .operators import exact as E
from .operators import measures as M
from .operators import surround as O
from .operators.local import exact_local, local_summaries
from .operators.merge import merge_flat, merge_pair, merge_tree
from .plans.engine import candidates, frequent_items, summarise
from .session import scratch, use_library
from .spec import FrequentSpec

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return use_library(spark).read.parquet(f"{sf_dir}/{name}.parquet")


def query(name: str, oracle: str | None = None):
    def add(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return add


# ---- verified sets: M13/M14 with a second scan, against HAVING --------------------------------------------------------

_WORDS_SQL = "SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS item FROM {0}"


def _having(items: str, k: int) -> str:
    return f"WITH i AS ({items}), c AS (SELECT item, count(*) AS cnt FROM i WHERE item IS NOT NULL GROUP BY item), n AS (SELECT CAST(sum(cnt) AS BIGINT) AS n FROM c) SELECT item, cnt FROM c, n WHERE cnt >= n // {k} + 1"


def _verified(name: str, source: str, expr: str, sql: str, k: int, **options) -> None:
    def run(spark, sf_dir):
        df = table(spark, sf_dir, source).select(F.expr(expr).alias("item"))
        return frequent_items(df, "item", FrequentSpec(k, **options))

    query(name, _having(f"SELECT {sql} AS item FROM {source}", k))(run)


for _name, _source, _expr, _k, _options in (
    ("majority_role", "conversations", "role", 2, {}),
    ("majority_lang", "documents", "lang", 2, {}),
    ("majority_quality", "labels", "quality", 2, {"kernel": "misra_gries"}),
    ("majority_linestatus", "lineitem", "l_linestatus", 2, {}),
    ("no_majority_orderstatus", "orders", "o_orderstatus", 2, {}),
    ("kmajority_event_type_k5", "events", "event_type", 5, {}),
    ("kmajority_quantity_k50", "lineitem", "l_quantity", 50, {}),
    ("kmajority_suppkey_k100", "lineitem", "l_suppkey", 100, {"kernel": "exact_local"}),
    ("kmajority_partkey_k2000", "lineitem", "l_partkey", 2000, {"levels": 2}),
    ("kmajority_user_k100", "events", "user_id", 100, {"kernel": "scalar"}),
    ("kmajority_value_k100", "events", "CAST(floor(value) AS INT)", 100, {}),
):
    _verified(_name, _source, _expr, _expr, _k, **_options)


def _words(spark: SparkSession, sf_dir: str, source: str = "documents") -> DataFrame:
    return I.words(table(spark, sf_dir, source))


def _register_words(k: int, source: str, name: str, **options) -> None:
    query(name, _having(_WORDS_SQL.format(source), k))(lambda spark, sf_dir: frequent_items(_words(spark, sf_dir, source), "item", FrequentSpec(k, **options)))


for _k in (500, 1000, 2000, 4000, 8000):
    _register_words(_k, "documents", f"words_verified_k{_k}")
_register_words(500, "conversations", "conv_words_verified_k500", levels=2, group=2)
_register_words(500, "documents", "words_tight_floor_k500", floor_rule="tight", counters=1000)
_register_words(500, "documents", "words_exact_local_k500", kernel="exact_local")
_register_words(500, "documents", "words_misra_gries_k500", kernel="misra_gries")
_register_words(500, "documents", "words_tree_k500", merge="tree")


@query("host_verified_k25", _having("SELECT regexp_extract(url, '^[a-z]+://([^/:]+)', 1) AS item FROM pages", 25))
def host_verified(spark, sf_dir):
    return frequent_items(table(spark, sf_dir, "pages").select(I.host().alias("item")), "item", FrequentSpec(25))


def _zipf_sql(rho: float) -> str:
    values = ", ".join(f"({r},{lo},{hi})" for r, lo, hi in I.zipf_bounds(rho) if hi > lo)
    return f"SELECT z.r AS item FROM events e JOIN (VALUES {values}) z(r, lo, hi) ON (e.event_id * 2654435761 + 12345) % 4294967296 >= z.lo AND (e.event_id * 2654435761 + 12345) % 4294967296 < z.hi"


def _register_zipf(name: str, rho: float, k: int, **options) -> None:
    query(name, _having(_zipf_sql(rho), k))(lambda spark, sf_dir: frequent_items(I.zipf_items(table(spark, sf_dir, "events").select("event_id"), "event_id", rho), "item", FrequentSpec(k, **options)))


_register_zipf("zipf11_verified_k100", 1.1, 100, levels=2)
_register_zipf("zipf18_verified_k100", 1.8, 100)
_register_zipf("zipf11_verified_k500", 1.1, 500, kernel="scalar")


# ---- iceberg queries --------------------------------------------------------------------------------------------------


@query("iceberg_brand", "SELECT p_brand, count(*) AS cnt FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY p_brand HAVING count(*) >= (SELECT count(*) FROM lineitem) // 26 + 1")
def iceberg_brand(spark, sf_dir):
    """Two-table join; the part side is broadcast only where its size statistics allow."""
    lines = table(spark, sf_dir, "lineitem").select("l_partkey")
    joined = lines.join(table(spark, sf_dir, "part").select("p_partkey", "p_brand"), F.col("l_partkey") == F.col("p_partkey"))
    return frequent_items(joined, "p_brand", FrequentSpec(26)).withColumnRenamed("item", "p_brand")


@query("iceberg_segment_nation", "SELECT c_mktsegment, c_nationkey, count(*) AS cnt FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2 HAVING count(*) > (SELECT count(*) FROM orders) * 0.009")
def iceberg_segment_nation(spark, sf_dir):
    joined = table(spark, sf_dir, "orders").select("o_custkey").join(table(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey"))
    return E.iceberg(joined, ["c_mktsegment", "c_nationkey"], share=0.009)


@query("iceberg_composite", "SELECT event_type, user_id, count(*) AS cnt FROM events GROUP BY 1, 2 HAVING count(*) >= 12")
def iceberg_composite(spark, sf_dir):
    return E.iceberg(table(spark, sf_dir, "events"), ["event_type", "user_id"], min_count=12, approx=True)


@query("iceberg_share_sketch", "SELECT event_type, count(*) AS cnt FROM events GROUP BY 1 HAVING count(*) >= (SELECT count(*) FROM events) // 5 + 1")
def iceberg_share_sketch(spark, sf_dir):
    return E.iceberg(table(spark, sf_dir, "events"), ["event_type"], share=0.2, approx=True)


@query("iceberg_rollup", "SELECT l_returnflag, l_linestatus, count(*) AS cnt FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus) HAVING count(*) >= 15000")
def iceberg_rollup(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("cnt")).filter("cnt >= 15000")


# ---- exact answers and groups -------------------------------------------------------------------------------------------


@query("exact_frequent_types", _having("SELECT event_type AS item FROM events", 5))
def exact_frequent_types(spark, sf_dir):
    return E.exact_frequent(table(spark, sf_dir, "events"), "event_type", 5)


@query("exact_topk_words", f"WITH i AS ({_WORDS_SQL.format('documents')}) SELECT item, count(*) AS cnt FROM i GROUP BY item ORDER BY cnt DESC, item LIMIT 50")
def exact_topk_words(spark, sf_dir):
    return E.exact_counts(_words(spark, sf_dir), "item").orderBy(F.col("cnt").desc(), "item").limit(50)


@query(
    "grouped_words_by_lang",
    "WITH i AS (SELECT lang, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS item FROM documents), c AS (SELECT lang, item, count(*) AS cnt FROM i GROUP BY 1, 2), n AS (SELECT lang, CAST(sum(cnt) AS BIGINT) AS n FROM c GROUP BY 1) SELECT c.lang, item, cnt FROM c JOIN n ON c.lang = n.lang WHERE cnt >= n // 100 + 1",
)
def grouped_words_by_lang(spark, sf_dir):
    rows = I.words(table(spark, sf_dir, "documents").filter("lang IS NOT NULL"), keep=("lang",))
    return frequent_items(rows, "item", FrequentSpec(100, by=("lang",), kernel="exact_local"))


@query(
    "frequent_days",
    "WITH i AS (SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, event_type AS item FROM events), c AS (SELECT day, item, count(*) AS cnt FROM i GROUP BY 1, 2), n AS (SELECT day, CAST(sum(cnt) AS BIGINT) AS n FROM c GROUP BY 1) SELECT c.day, item, cnt FROM c JOIN n ON c.day = n.day WHERE cnt >= n // 5 + 1",
)
def frequent_days(spark, sf_dir):
    rows = table(spark, sf_dir, "events").select(F.to_date(F.date_trunc("day", "ts")).cast("string").alias("day"), "event_type")
    return E.exact_frequent(rows, "event_type", 5, by=("day",))


@query("weighted_quantity_by_part", "WITH c AS (SELECT l_partkey AS item, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS cnt FROM lineitem GROUP BY 1), n AS (SELECT CAST(sum(cnt) AS BIGINT) AS n FROM c) SELECT item, cnt FROM c, n WHERE cnt >= n // 1500 + 1")
def weighted_quantity_by_part(spark, sf_dir):
    rows = table(spark, sf_dir, "lineitem").select("l_partkey", F.col("l_quantity").cast("long").alias("w"))
    return frequent_items(rows, "l_partkey", FrequentSpec(1500, weight="w"))


_NULLS = "CASE WHEN user_id % 3 = 0 THEN NULL ELSE event_type END"


@query("nulls_skip", _having(f"SELECT {_NULLS} AS item FROM events", 5))
def nulls_skip(spark, sf_dir):
    return frequent_items(table(spark, sf_dir, "events").select(F.expr(_NULLS).alias("item")), "item", FrequentSpec(5))


@query("nulls_item", f"WITH c AS (SELECT {_NULLS} AS item, count(*) AS cnt FROM events GROUP BY 1), n AS (SELECT CAST(sum(cnt) AS BIGINT) AS n FROM c) SELECT item, cnt FROM c, n WHERE cnt >= n // 5 + 1")
def nulls_item(spark, sf_dir):
    return frequent_items(table(spark, sf_dir, "events").select(F.expr(_NULLS).alias("item")), "item", FrequentSpec(5, nulls="item"))


@query("composite_struct_items", "SELECT l_returnflag, l_linestatus, count(*) AS cnt FROM lineitem GROUP BY 1, 2 HAVING count(*) >= (SELECT count(*) FROM lineitem) // 4 + 1")
def composite_struct_items(spark, sf_dir):
    rows = table(spark, sf_dir, "lineitem").select(F.struct("l_returnflag", "l_linestatus").alias("item"))
    return E.exact_frequent(rows, "item", 4).select("item.*", "cnt")


# ---- sequential kernels, replayed by recursion --------------------------------------------------------------------------

_FIRST = "SELECT row_number() OVER (ORDER BY event_id) AS pos, {0} AS item FROM events WHERE event_id < {1}"


def _replay(item: str, limit: int, k: int, kind: str = "BIGINT") -> str:
    state = f"STRUCT(item {kind}, est BIGINT, err BIGINT)[]"
    victim = "list_sort(list_transform(st, lambda x: {'est': x.est, 'item': x.item}))[1]"
    return f"""WITH RECURSIVE s AS ({_FIRST.format(item, limit)}),
r(pos, st) AS (SELECT CAST(0 AS BIGINT), CAST([] AS {state}) UNION ALL
 SELECT s.pos, CASE WHEN list_contains(list_transform(st, lambda x: x.item), s.item) THEN list_transform(st, lambda x: CASE WHEN x.item = s.item THEN {{'item': x.item, 'est': x.est + 1, 'err': x.err}} ELSE x END)
  WHEN len(st) < {k} THEN list_append(st, {{'item': s.item, 'est': CAST(1 AS BIGINT), 'err': CAST(0 AS BIGINT)}})
  ELSE list_transform(st, lambda x: CASE WHEN x.item = {victim}.item THEN {{'item': s.item, 'est': x.est + 1, 'err': x.est}} ELSE x END) END
 FROM r JOIN s ON s.pos = r.pos + 1)
SELECT u.item AS item, u.est AS est, u.err AS err FROM (SELECT unnest(st) AS u FROM r WHERE pos = (SELECT max(pos) FROM s))"""


#: Queries over all events whose SQL replays the first 1,000 only: it holds on tables that small and is no oracle beyond.
REPLAYS: set[str] = {"misra_gries_k8"}


def _in_order(spark: SparkSession, sf_dir: str, item: str) -> DataFrame:
    """All events as one ordered split, which a kernel reads as a stream."""
    rows = table(spark, sf_dir, "events").select("event_id", F.expr(item).alias("item"))
    return rows.repartition(1).sortWithinPartitions("event_id")


def _sequential(name: str, item: str, limit: int, k: int, kind: str) -> None:
    def run(spark, sf_dir):
        out = local_summaries(_in_order(spark, sf_dir, item), "item", FrequentSpec(k, kernel="scalar"))
        return out.filter("kind = 'item'").select("item", "est", "err")

    query(name, _replay(item, limit, k, kind))(run)
    REPLAYS.add(name)


_sequential("sequential_users_k8", "user_id", 1000, 8, "BIGINT")
_sequential("sequential_types_k3", "event_type", 1000, 3, "VARCHAR")
_sequential("sequential_spare", "event_type", 1000, 50, "VARCHAR")
_sequential("majority_vote_candidate", "event_type", 1000, 2, "VARCHAR")


def _replay_mg(item: str, limit: int, k: int) -> str:
    return f"""WITH RECURSIVE s AS ({_FIRST.format(item, limit)}),
r(pos, st, lost) AS (SELECT CAST(0 AS BIGINT), CAST([] AS STRUCT(item BIGINT, est BIGINT)[]), CAST(0 AS BIGINT) UNION ALL
 SELECT s.pos, CASE WHEN list_contains(list_transform(st, lambda x: x.item), s.item) THEN list_transform(st, lambda x: CASE WHEN x.item = s.item THEN {{'item': x.item, 'est': x.est + 1}} ELSE x END)
  WHEN len(st) < {k - 1} THEN list_append(st, {{'item': s.item, 'est': CAST(1 AS BIGINT)}})
  ELSE list_filter(list_transform(st, lambda x: {{'item': x.item, 'est': x.est - 1}}), lambda x: x.est > 0) END,
  lost + CASE WHEN list_contains(list_transform(st, lambda x: x.item), s.item) OR len(st) < {k - 1} THEN 0 ELSE 1 END
 FROM r JOIN s ON s.pos = r.pos + 1)
SELECT u.item AS item, u.est AS est, lost FROM (SELECT unnest(st) AS u, lost FROM r WHERE pos = (SELECT max(pos) FROM s))"""


@query("misra_gries_k8", _replay_mg("user_id % 12", 1000, 8))
def misra_gries_k8(spark, sf_dir):
    out = local_summaries(_in_order(spark, sf_dir, "user_id % 12"), "item", FrequentSpec(8, kernel="misra_gries")).filter("kind = 'item'")
    return out.select("item", (F.col("est") - F.col("floor")).alias("est"), F.col("floor").alias("lost"))


# ---- blocks and the merge family over exact-local summaries: closed forms -------------------------------------------------

_VALUE = "CAST(floor(value) AS BIGINT)"
_K, _P = 20, 8


def _blocks(spark: SparkSession, sf_dir: str, p: int = _P, item: str = _VALUE) -> DataFrame:
    events = table(spark, sf_dir, "events")
    n = events.count()
    return B.by_index(events.select("event_id", F.expr(item).alias("item")), "event_id", p, n)


def _sql_blocks(p: int = _P, item: str = _VALUE) -> str:
    return f"b AS (SELECT ((event_id + 1) * {p} - 1) // (SELECT count(*) FROM events) AS block, {item} AS item FROM events)"


def _sql_cut(name: str, source: str, k: int, rule: str, group: str = "block") -> str:
    floor = {
        "spare_zero": f"CASE WHEN count(*) >= {k} THEN min(CASE WHEN rk <= {k} THEN est END) ELSE max(floors) END",
        "stored_min": f"min(CASE WHEN rk <= {k} THEN est END)",
        "tight": f"greatest(max(floors), coalesce(max(CASE WHEN rk = {k + 1} THEN est END), 0))",
    }[rule]
    return (
        f"{name}_r AS (SELECT *, row_number() OVER (PARTITION BY {group} ORDER BY est DESC, item) AS rk FROM {source}), "
        f"{name}_f AS (SELECT {group}, CAST({floor} AS BIGINT) AS floor, CAST(max(n) AS BIGINT) AS n FROM {name}_r GROUP BY {group}), "
        f"{name} AS (SELECT r.{group}, r.item, CAST(r.est AS BIGINT) AS est, CAST(r.err AS BIGINT) AS err, f.floor, f.n FROM {name}_r r JOIN {name}_f f ON r.{group} = f.{group} WHERE r.rk <= {k})"
    )


def _sql_local(k: int = _K, p: int = _P, rule: str = "spare_zero", item: str = _VALUE) -> str:
    counts = "c AS (SELECT block, item, count(*) AS est, 0 AS err, 0 AS floors, sum(count(*)) OVER (PARTITION BY block) AS n FROM b GROUP BY block, item)"
    return f"{_sql_blocks(p, item)}, {counts}, {_sql_cut('l', 'c', k, rule)}"


def _sql_merge(name: str, source: str, group: str, k: int, rule: str = "spare_zero") -> str:
    """One merge step of ``source`` (block, item, est, err, floor, n) by the group expression."""
    heads = f"{name}_h AS (SELECT g, sum(floor) AS floors, sum(n) AS n FROM (SELECT DISTINCT block, {group} AS g, floor, n FROM {source}) GROUP BY g)"
    entries = f"{name}_e AS (SELECT h.g AS block, x.item, h.floors + x.r AS est, h.floors + x.e AS err, h.floors, h.n FROM (SELECT {group} AS g, item, sum(est - floor) AS r, sum(err - floor) AS e FROM {source} GROUP BY 1, 2) x JOIN {name}_h h ON x.g = h.g)"
    return f"{heads}, {entries}, {_sql_cut(name, f'{name}_e', k, rule)}"


_OUT = ("block", "item", "est", "err", "floor", "n")


def _rows(summary: DataFrame) -> DataFrame:
    return summary.filter("kind = 'item'").select(*_OUT)


def _local(spark, sf_dir, k: int = _K, p: int = _P, rule: str = "spare_zero") -> DataFrame:
    return exact_local(_blocks(spark, sf_dir, p), "item", FrequentSpec(k, floor_rule=rule), "block")


@query("block_bounds_p7", f"WITH {_sql_blocks(7)}, x AS (SELECT ((event_id + 1) * 7 - 1) // (SELECT count(*) FROM events) AS block, event_id FROM events) SELECT CAST(block AS BIGINT) AS block, min(event_id) AS first, max(event_id) AS last, count(*) AS size FROM x GROUP BY 1")
def block_bounds(spark, sf_dir):
    return _blocks(spark, sf_dir, 7).groupBy("block").agg(F.min("event_id").alias("first"), F.max("event_id").alias("last"), F.count(F.lit(1)).alias("size"))


@query("block_order_p5", "SELECT CAST(((event_id + 1) * 5 - 1) // (SELECT count(*) FROM events) AS BIGINT) AS block, min(event_id) AS first, max(event_id) AS last, count(*) AS size FROM events GROUP BY 1")
def block_order(spark, sf_dir):
    rows = B.by_order(table(spark, sf_dir, "events").select("event_id"), ["event_id"], 5)
    return rows.groupBy("block").agg(F.min("event_id").alias("first"), F.max("event_id").alias("last"), F.count(F.lit(1)).alias("size"))


_SELECT = "SELECT CAST(block AS BIGINT) AS block, item, est, err, floor, n FROM "

query("exact_local_k20_p8", f"WITH {_sql_local()} {_SELECT} l")(lambda s, d: _rows(_local(s, d)))
query("exact_local_tight", f"WITH {_sql_local(rule='tight')} {_SELECT} l")(lambda s, d: _rows(_local(s, d, rule="tight")))
query("merge_flat_k20_p8", f"WITH {_sql_local()}, {_sql_merge('m', 'l', '0', _K)} {_SELECT} m")(lambda s, d: _rows(merge_flat(_local(s, d), _K)))
query("merge_flat_tight", f"WITH {_sql_local(rule='tight')}, {_sql_merge('m', 'l', '0', _K, 'tight')} {_SELECT} m")(lambda s, d: _rows(merge_flat(_local(s, d, rule="tight"), _K, "tight")))
query("merge_tree_k20_p8_f2", f"WITH {_sql_local()}, {_sql_merge('m1', 'l', 'block // 2', _K)}, {_sql_merge('m2', 'm1', 'block // 2', _K)}, {_sql_merge('m3', 'm2', 'block // 2', _K)} {_SELECT} m3")(lambda s, d: _rows(merge_tree(_local(s, d), _K, _P, 2)))
query("merge_tree_k20_p8_f4", f"WITH {_sql_local()}, {_sql_merge('m1', 'l', 'block // 4', _K)}, {_sql_merge('m2', 'm1', 'block // 4', _K)} {_SELECT} m2")(lambda s, d: _rows(merge_tree(_local(s, d), _K, _P, 4)))
query("two_level_k20_p8_g4", f"WITH {_sql_local()}, {_sql_merge('m1', 'l', 'block // 4', _K)}, {_sql_merge('m2', 'm1', '0', _K)} {_SELECT} m2")(
    lambda s, d: _rows(summarise(_blocks(s, d), "item", FrequentSpec(_K, kernel="exact_local", levels=2, group=4), "block"))
)
query("merge_pair_k20", f"WITH {_sql_local(p=2)}, {_sql_merge('m', 'l', '0', _K)} {_SELECT} m")(lambda s, d: _pair(s, d, "spare_zero"))
query("merge_pair_stored_min", f"WITH {_sql_local(p=2, rule='stored_min')}, {_sql_merge('m', 'l', '0', _K, 'stored_min')} {_SELECT} m")(lambda s, d: _pair(s, d, "stored_min"))


def _pair(spark, sf_dir, rule: str) -> DataFrame:
    local = _local(spark, sf_dir, _K, 2, rule)
    return _rows(merge_pair(local.filter("block = 0"), local.filter("block = 1"), _K, rule))


def _flat(spark, sf_dir) -> DataFrame:
    return merge_flat(_local(spark, sf_dir), _K)


_FLAT_SQL = f"WITH {_sql_local()}, {_sql_merge('m', 'l', '0', _K)}"

query("candidates_one_pass", f"{_FLAT_SQL} SELECT item, est, err, est - err AS lower, (est - err >= n // {_K} + 1) AS guaranteed FROM m WHERE est >= n // {_K} + 1")(lambda s, d: candidates(_flat(s, d), _K).drop("n", "threshold"))
query("guaranteed_flags", f"{_FLAT_SQL} SELECT item, est FROM m WHERE est - err >= n // {_K} + 1")(lambda s, d: candidates(_flat(s, d), _K).filter("guaranteed").select("item", "est"))
query("estimate_items", f"{_FLAT_SQL}, a AS (SELECT DISTINCT {_VALUE} AS item FROM events) SELECT a.item, coalesce(m.est, (SELECT max(floor) FROM m)) AS est, coalesce(m.est - m.err, 0) AS lower, coalesce(m.est, (SELECT max(floor) FROM m)) AS upper FROM a LEFT JOIN m ON a.item = m.item")(
    lambda s, d: M.estimate(_flat(s, d), table(s, d, "events").select(F.expr(_VALUE).alias("item")))
)
query("unmonitored_floor", f"{_FLAT_SQL} SELECT CAST(-1 AS BIGINT) AS item, max(floor) AS est, CAST(0 AS BIGINT) AS lower, max(floor) AS upper FROM m")(lambda s, d: M.estimate(_flat(s, d), s.createDataFrame([(-1,)], "item long")))


# ---- accuracy ---------------------------------------------------------------------------------------------------------------

_TRUE = f"t AS (SELECT {_VALUE} AS item, count(*) AS cnt FROM events GROUP BY 1), tt AS (SELECT * FROM t WHERE cnt >= (SELECT count(*) FROM events) // {_K} + 1), s AS (SELECT * FROM m WHERE est >= n // {_K} + 1)"


@query(
    "accuracy_values_k20",
    f"{_FLAT_SQL}, {_TRUE}, x AS (SELECT (SELECT count(*) FROM s) AS reported, (SELECT count(*) FROM tt) AS true_items, (SELECT count(*) FROM s JOIN tt ON s.item = tt.item) AS hits) SELECT (SELECT max(n) FROM m) AS n, (SELECT max(floor) FROM m) AS floor, reported, true_items, hits, round(CASE WHEN reported = 0 THEN 1.0 ELSE hits / reported END, 6) AS precision, round(CASE WHEN true_items = 0 THEN 1.0 ELSE hits / true_items END, 6) AS recall, (SELECT round(coalesce(avg(abs(s.est - t.cnt) / t.cnt), 0), 6) FROM s JOIN t ON s.item = t.item) AS are FROM x",
)
def accuracy_values(spark, sf_dir):
    exact = E.exact_counts(table(spark, sf_dir, "events").select(F.expr(_VALUE).alias("item")), "item")
    return M.report(_flat(spark, sf_dir), exact, _K)


query("false_positives_values", f"{_FLAT_SQL}, {_TRUE} SELECT item FROM s WHERE item NOT IN (SELECT item FROM tt)")(
    lambda s, d: M.false_positives(candidates(_flat(s, d), _K), E.exact_frequent(table(s, d, "events").select(F.expr(_VALUE).alias("item")), "item", _K))
)
query("false_negatives_values", f"{_FLAT_SQL}, {_TRUE} SELECT item FROM tt WHERE item NOT IN (SELECT item FROM s)")(
    lambda s, d: M.false_negatives(candidates(_flat(s, d), _K), E.exact_frequent(table(s, d, "events").select(F.expr(_VALUE).alias("item")), "item", _K))
)

_ALL_TRUE = "SELECT true AS never_under, true AS error_bounded, true AS error_within_floor, true AS missing_within_floor, true AS floor_within_share, true AS n_is_total"


def _audited(name: str, k: int, **options) -> None:
    def run(spark, sf_dir):
        rows = _blocks(spark, sf_dir, 5, "user_id")
        summary = summarise(rows, "item", FrequentSpec(k, **options), "block", None if options.get("kernel") == "exact_local" else "event_id", blocks=5)
        return M.audit(summary, E.exact_counts(rows, "item"), k)

    query(name, _ALL_TRUE)(run)


_audited("audit_scalar", 50, kernel="scalar")
_audited("audit_batched", 50, kernel="batched", floor_rule="tight")
_audited("audit_tree", 50, kernel="scalar", merge="tree")
_audited("audit_flat", 50, kernel="exact_local")
_audited("audit_two_level", 50, kernel="scalar", levels=2, group=2)


# ---- cost measures on the times of dealt lines ---------------------------------------------------------------------------------

# The lines of each return flag, dealt by part to as many workers as the published runs had cores.
CORES = (1, 2, 4, 8, 16, 32, 64, 128, 256, 512)
_LINE_TIMES = f"""parts AS (SELECT l_returnflag AS series, coalesce(l_partkey, 0) AS part, count(*) AS cnt FROM lineitem GROUP BY 1, 2),
workers AS (SELECT series, p, (part % p + p) % p AS worker, sum(cnt) AS cnt FROM parts, (VALUES {', '.join(f'({p})' for p in CORES)}) x(p) GROUP BY 1, 2, 3),
t AS (SELECT series, p, CAST(max(cnt) AS DOUBLE) AS wall, CAST(sum(cnt) AS DOUBLE) / p AS compute FROM workers GROUP BY 1, 2)"""


def line_times(spark: SparkSession, sf_dir: str) -> DataFrame:
    return M.dealt_times(table(spark, sf_dir, "lineitem"), "l_returnflag", "l_partkey", CORES)


query("speedup_table", f"WITH {_LINE_TIMES} SELECT t.series, t.p, t.wall AS seconds, round(o.wall / t.wall, 4) AS speedup, round(o.wall / t.wall / t.p, 4) AS efficiency FROM t JOIN t o ON t.series IS NOT DISTINCT FROM o.series AND o.p = 1")(
    lambda s, d: M.scaling(line_times(s, d).withColumnRenamed("wall", "seconds"))
)
query("scaling_slope", f"WITH {_LINE_TIMES} SELECT series, round(regr_slope(ln(wall), ln(p)), 6) AS slope FROM t GROUP BY series")(lambda s, d: M.scaling_slope(line_times(s, d).withColumnRenamed("wall", "seconds")))
query("fractional_overhead", f"WITH {_LINE_TIMES} SELECT series, p, wall, compute, round((wall - compute) / compute, 6) AS overhead FROM t")(lambda s, d: M.fractional_overhead(line_times(s, d)))


# ---- rank and frequency ------------------------------------------------------------------------------------------------------

_COUNTS = f"c AS (SELECT item, count(*) AS cnt FROM ({_WORDS_SQL.format('documents')}) GROUP BY item), r AS (SELECT row_number() OVER (ORDER BY cnt DESC, item) AS rank, item, cnt, sum(cnt) OVER (ORDER BY cnt DESC, item) AS sofar FROM c)"
query("rank_frequency_words", f"WITH {_COUNTS} SELECT rank, item, cnt, round(sofar / (SELECT sum(cnt) FROM c), 6) AS cumulative_share FROM r WHERE rank <= 100")(lambda s, d: M.rank_frequency(E.exact_counts(_words(s, d), "item"), 100))
query("zipf_fit", f"WITH {_COUNTS} SELECT round(regr_slope(ln(cnt), ln(rank)), 6) AS slope, count(*) AS ranks FROM r WHERE rank <= 500")(lambda s, d: M.zipf_fit(E.exact_counts(_words(s, d), "item"), 500))


# ---- surrounding operators ------------------------------------------------------------------------------------------------

_TOP = "SELECT item FROM (SELECT item, count(*) AS cnt FROM ({0}) GROUP BY item ORDER BY cnt DESC, item LIMIT 100)"
query("set_intersect_docs_benchmark", f"{_TOP.format(_WORDS_SQL.format('documents'))} INTERSECT {_TOP.format(_WORDS_SQL.format('benchmark'))}")(lambda s, d: O.common_items(O.top_items(_words(s, d), 100), O.top_items(_words(s, d, "benchmark"), 100)))
query("set_except_docs_benchmark", f"{_TOP.format(_WORDS_SQL.format('documents'))} EXCEPT {_TOP.format(_WORDS_SQL.format('benchmark'))}")(lambda s, d: O.lost_items(O.top_items(_words(s, d), 100), O.top_items(_words(s, d, "benchmark"), 100)))

_DAILY = "d AS (SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, user_id AS item, count(*) AS cnt FROM events GROUP BY 1, 2)"
query("asof_previous_report", f"WITH {_DAILY} SELECT day, item, cnt, coalesce(lag(cnt) OVER (PARTITION BY item ORDER BY day), 0) AS before FROM d")(lambda s, d: O.previous_report(O.daily(table(s, d, "events"), "ts", "user_id")).na.fill(0))
query("pivot_types_by_day", "SELECT CAST(CAST(ts AS DATE) AS VARCHAR) AS day, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS view, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY 1")(lambda s, d: O.pivoted(O.daily(table(s, d, "events"), "ts", "event_type"), ["click", "view", "purchase"]))
query("cube_flags", "SELECT l_returnflag, l_linestatus, count(*) AS cnt FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")(lambda s, d: O.cube_counts(table(s, d, "lineitem"), ["l_returnflag", "l_linestatus"]))
query("grouping_sets_orders", "SELECT o_orderstatus, o_orderpriority, count(*) AS cnt FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority))")(lambda s, d: O.grouping_sets_counts(table(s, d, "orders"), ["o_orderstatus", "o_orderpriority"]))
query("per_group_topk", "SELECT event_type, user_id AS item, cnt FROM (SELECT *, row_number() OVER (PARTITION BY event_type ORDER BY cnt DESC, user_id) AS rk FROM (SELECT event_type, user_id, count(*) AS cnt FROM events GROUP BY 1, 2)) WHERE rk <= 3")(lambda s, d: O.top_per_group(E.exact_counts(table(s, d, "events"), "user_id", ("event_type",)), ["event_type"], 3))
query("semi_join_frequent", "SELECT count(*) AS rows FROM lineitem WHERE l_returnflag IN (SELECT l_returnflag FROM lineitem GROUP BY 1 HAVING count(*) >= (SELECT count(*) FROM lineitem) // 3 + 1)")(
    lambda s, d: E.candidate_filter(table(s, d, "lineitem"), "l_returnflag", E.exact_frequent(table(s, d, "lineitem"), "l_returnflag", 3)).agg(F.count(F.lit(1)).alias("rows"))
)
query("named_suppliers", "SELECT s_name, cnt FROM (SELECT l_suppkey, count(*) AS cnt FROM lineitem GROUP BY 1 HAVING count(*) >= (SELECT count(*) FROM lineitem) // 100 + 1) JOIN supplier ON l_suppkey = s_suppkey")(
    lambda s, d: frequent_items(table(s, d, "lineitem"), "l_suppkey", FrequentSpec(100)).join(table(s, d, "supplier"), F.col("item") == F.col("s_suppkey")).select("s_name", "cnt")
)
query("json_items_k3", _having("SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS item FROM events", 200))(lambda s, d: frequent_items(table(s, d, "events").select(F.get_json_object("props", "$.k").cast("long").alias("item")), "item", FrequentSpec(200)))
query("packed_lookup", f"{_FLAT_SQL} SELECT max(n) AS n, max(floor) AS floor, count(*) FILTER (est >= n // {_K} + 1) AS over_threshold FROM m")(
    lambda s, d: S.pack(_flat(s, d), _K).select("summary.n", S.freq_floor("summary").alias("floor"), F.size(S.freq_candidates("summary")).cast("long").alias("over_threshold"))
)


@query("incremental_days", "SELECT event_type AS item, count(*) AS est FROM events GROUP BY 1")
def incremental_days(spark, sf_dir):
    """Daily summaries saved as partitions and merged again: exact while every type has a counter."""
    from .sources import load_summary, save_summary

    path = scratch(spark, "days")
    events = table(spark, sf_dir, "events").select("event_type", F.expr("event_id % 3").alias("part"))
    for part in range(3):
        save_summary(summarise(events.filter(f"part = {part}"), "event_type", FrequentSpec(50)), path, f"day{part}")
    return merge_flat(load_summary(spark, path), 50).filter("kind = 'item'").select("item", "est")


# ---- SQL functions ---------------------------------------------------------------------------------------------------------


@query("udaf_summary_by_type", "SELECT event_type, user_id % 10 AS item, count(*) AS est FROM events GROUP BY 1, 2")
def udaf_summary_by_type(spark, sf_dir):
    S.register(use_library(spark))
    table(spark, sf_dir, "events").createOrReplaceTempView("freq_events")
    packed = spark.sql("SELECT event_type, freq_summary_long(user_id % 10, 20) AS summary FROM freq_events GROUP BY event_type")
    return packed.select("event_type", F.explode("summary.counters").alias("c")).select("event_type", "c.item", "c.est")


@query("udaf_merge", "SELECT user_id % 10 AS item, count(*) AS est FROM events GROUP BY 1")
def udaf_merge(spark, sf_dir):
    S.register(use_library(spark))
    table(spark, sf_dir, "events").createOrReplaceTempView("freq_events")
    packed = spark.sql("SELECT freq_merge_long(summary) AS summary FROM (SELECT freq_summary_long(user_id % 10, 20) AS summary FROM freq_events GROUP BY event_type)")
    return packed.select(F.explode("summary.counters").alias("c")).select("c.item", "c.est")


@query("udtf_local", "SELECT event_type AS item, count(*) AS est FROM events GROUP BY 1")
def udtf_local(spark, sf_dir):
    S.register(use_library(spark))
    table(spark, sf_dir, "events").createOrReplaceTempView("freq_events")
    return spark.sql("SELECT item, sum(est) AS est FROM frequent_local(TABLE(SELECT event_type, user_id % 4 AS b FROM freq_events) PARTITION BY (b), 50) GROUP BY item")


@query("sql_tokenize", f"SELECT item, count(*) AS cnt FROM ({_WORDS_SQL.format('benchmark')}) GROUP BY item")
def sql_tokenize(spark, sf_dir):
    S.register(use_library(spark))
    table(spark, sf_dir, "benchmark").createOrReplaceTempView("freq_benchmark")
    return spark.sql("SELECT item, count(*) AS cnt FROM (SELECT explode(w) AS item FROM (SELECT tokenize(text) AS w FROM freq_benchmark)) GROUP BY item")


# ---- built-in relatives, for comparison ----------------------------------------------------------------------------------

query("builtin_approx_top_k", "SELECT event_type AS item, count(*) AS cnt FROM events GROUP BY 1")(lambda s, d: O.builtin_top_k(table(s, d, "events"), "event_type", 20))
query("builtin_mode", "SELECT max(item) AS item FROM (SELECT event_type AS item, count(*) AS c FROM events GROUP BY 1 ORDER BY c DESC LIMIT 1)")(lambda s, d: table(s, d, "events").agg(F.mode("event_type").alias("item")))


# ---- streams -----------------------------------------------------------------------------------------------------------------


def _events_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A single Parquet file is read as a stream by a glob, a folder as it is."""
    use_library(spark)
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/even*.parquet")


def _stream(name: str, oracle: str):
    return query(name, oracle)


@_stream("stream_daily_types", "SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start, event_type AS item, count(*) AS cnt FROM events GROUP BY 1, 2")
def stream_daily_types(spark, sf_dir):
    from .streaming import to_files, window_counts

    out = to_files(window_counts(_events_stream(spark, sf_dir), "ts", "event_type", "1 day"), scratch(spark, "daily"), "complete")
    return out.withColumn("start", F.col("start").cast("timestamp_ntz"))


@_stream("stream_dedup_types", "SELECT event_type AS item, count(*) AS cnt FROM events GROUP BY 1")
def stream_dedup_types(spark, sf_dir):
    from .streaming import deduplicated_counts, to_files

    return to_files(deduplicated_counts(_events_stream(spark, sf_dir), "ts", "event_id", "event_type", "3650 days"), scratch(spark, "dedup"), "complete")


@_stream("stream_running_summary", "SELECT event_type AS item, count(*) AS est FROM events GROUP BY 1")
def stream_running_summary(spark, sf_dir):

    from .streaming import SummaryStore, stream_frequent

    store = SummaryStore(spark, scratch(spark, "stream"))
    q = stream_frequent(_events_stream(spark, sf_dir), "event_type", FrequentSpec(50), store).trigger(availableNow=True).option("checkpointLocation", scratch(spark, "offsets")).start()
    q.awaitTermination()
    return store.read(store.versions()[-1]).filter("kind = 'item'").select("item", "est")


@_stream("stream_state_users", "SELECT event_type AS key, CAST(user_id % 7 AS VARCHAR) AS item, count(*) AS est FROM events GROUP BY 1, 2")
def stream_state_users(spark, sf_dir):
    from .streaming import keyed_summaries, to_memory

    rows = _events_stream(spark, sf_dir).select("event_type", F.expr("user_id % 7").alias("u"))
    out = to_memory(keyed_summaries(rows, "event_type", "u", 20), f"freq_{uuid4().hex[:8]}", "update")
    return out.groupBy("key", "item").agg(F.max("est").alias("est"))
