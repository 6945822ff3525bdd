from __future__ import annotations

import duckdb
import pytest
from pyspark.sql import functions as F

from freqspark import experiments  # noqa: F401  registers its queries
from freqspark import workloads as W
from freqspark.operators import blocks, exact, measures, surround
from freqspark.operators.local import local_summaries
from freqspark.operators.merge import merge_flat
from freqspark.plans.engine import candidates, frequent_items, summarise
from freqspark.sources import read_items, zipf_source
from freqspark.spec import FrequentSpec

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
#: Queries whose oracle is run here at the smallest scale; all of them are run by the driver.
SOME = (
    "majority_role", "no_majority_orderstatus", "kmajority_event_type_k5", "words_verified_k500", "words_misra_gries_k500", "zipf11_verified_k100", "iceberg_composite",
    "grouped_words_by_lang", "weighted_quantity_by_part", "nulls_item", "sequential_users_k8", "misra_gries_k8", "block_bounds_p7", "block_order_p5", "exact_local_k20_p8", "merge_flat_tight",
    "merge_tree_k20_p8_f2", "two_level_k20_p8_g4", "merge_pair_k20", "merge_pair_stored_min", "candidates_one_pass", "estimate_items", "audit_scalar", "audit_tree", "mg_isomorphism",
    "speedup_table", "scaling_slope", "rank_frequency_words", "asof_previous_report", "packed_lookup", "incremental_days", "udaf_summary_by_type", "udtf_local", "stream_running_summary", "stream_state_users",
    "sweep_blocks_two_level_k100", "audit_plans_misra_gries", "audit_plans_batched", "mg_cancelled_levels2", "iceberg_share_030", "iceberg_timestamp_pair", "grouped_null_lang_batched", "are_by_scope_k20",
    "stream_session", "stream_window_summaries", "stream_late_rows", "sql_frequent",
)


def rows(pdf) -> list[tuple]:
    pdf = pdf[sorted(pdf.columns)]
    return sorted(tuple(str(float(x)) if isinstance(x, float) else str(x) for x in r) for r in pdf.itertuples(index=False))


@pytest.mark.parametrize("name", SOME)
def test_query_equals_its_oracle(spark, sf_small, name):
    db = duckdb.connect()
    for t in TABLES:
        db.execute(f"create view {t} as select * from '{sf_small}/{t}.parquet'")
    assert rows(W.QUERIES[name](spark, sf_small).toPandas()) == rows(db.execute(W.ORACLES[name]).df())


def test_sequential_queries_read_all_events(spark):
    """10,000 events against a plain loop in the order of the ids."""
    sf = "/root/testdata/sf0.01"
    events = spark.read.parquet(f"{sf}/events.parquet").select("event_id", "user_id", "event_type").toPandas().sort_values("event_id")
    assert len(events) > 1000
    for name, column, k in (("sequential_users_k8", "user_id", 8), ("sequential_types_k3", "event_type", 3), ("sequential_spare", "event_type", 50), ("majority_vote_candidate", "event_type", 2)):
        held: dict = {}
        for x in events[column]:
            if x in held:
                held[x][0] += 1
            elif len(held) < k:
                held[x] = [1, 0]
            else:
                least = min(held, key=lambda y: (held[y][0], y))
                est = held.pop(least)[0]
                held[x] = [est + 1, est]
        assert {tuple(r) for r in W.QUERIES[name](spark, sf).collect()} == {(x, e, d) for x, (e, d) in held.items()}, name
    held, lost = {}, 0
    for x in events["user_id"] % 12:
        if x in held or len(held) < 7:
            held[x] = held.get(x, 0) + 1
        else:
            held, lost = {y: c - 1 for y, c in held.items() if c > 1}, lost + 1
    assert {tuple(r) for r in W.QUERIES["misra_gries_k8"](spark, sf).collect()} == {(x, c, lost) for x, c in held.items()}


@pytest.mark.parametrize("kernel", ["scalar", "batched", "exact_local", "misra_gries"])
@pytest.mark.parametrize("levels", [1, 2])
def test_all_plans_give_the_true_set(spark, sf_small, kernel, levels):
    events = blocks.by_hash(spark.read.parquet(f"{sf_small}/events.parquet"), 5, "event_id")
    got = frequent_items(events, "user_id", FrequentSpec(60, kernel=kernel, levels=levels, group=2), "block", None if kernel == "exact_local" else "event_id")
    want = exact.exact_frequent(events, "user_id", 60)
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_one_pass_contains_the_truth_and_guarantees_are_true(spark, sf_small):
    words = W._words(spark, sf_small)
    summary = summarise(words, "item", FrequentSpec(300))
    said = candidates(summary, 300)
    true = {r["item"] for r in exact.exact_frequent(words, "item", 300).collect()}
    assert true <= {r["item"] for r in said.collect()}
    assert {r["item"] for r in said.filter("guaranteed").collect()} <= true


def test_empty_and_single_tables(spark):
    empty = spark.createDataFrame([], "item string")
    assert frequent_items(empty, "item", 5).count() == 0
    assert [tuple(r) for r in frequent_items(spark.createDataFrame([("a",), ("a",), (None,)], "item string"), "item", 2).collect()] == [("a", 2)]


def test_a_count_of_exactly_the_share_is_not_frequent(spark):
    df = spark.createDataFrame([(x,) for x in "aabbccddee"], "item string")
    assert frequent_items(df, "item", 5).count() == 0


def test_unsupported_item_types_are_refused(spark):
    df = spark.sql("SELECT map('a', 1) AS item")
    with pytest.raises(TypeError, match="map"):
        frequent_items(df, "item", 5)


def test_float_items_make_zeros_and_nans_equal(spark):
    df = spark.createDataFrame([(0.0,), (-0.0,), (float("nan"),), (float("nan"),), (1.0,)], "item double")
    got = {str(r["item"]): r["cnt"] for r in frequent_items(df, "item", 3).collect()}
    assert got == {"0.0": 2, "nan": 2}


def test_plans(spark, sf_small):
    lines = spark.read.parquet(f"{sf_small}/lineitem.parquet")
    local = local_summaries(lines, "l_suppkey", FrequentSpec(10))
    plan = local._jdf.queryExecution().executedPlan().toString()
    assert "ReadSchema: struct<l_suppkey:bigint>" in plan and "Exchange" not in plan
    flat = merge_flat(local.persist(), 10)._jdf.queryExecution().executedPlan().toString()
    assert "TakeOrderedAndProject" in flat


def test_sources(spark, tmp_path):
    spark.createDataFrame([("a", 1), ("b", 2)], "x string, y int").write.csv(str(tmp_path / "c"))
    assert sorted(r["item"] for r in read_items(spark, str(tmp_path / "c"), "x", "csv", "x string, y int").collect()) == ["a", "b"]
    with pytest.raises(ValueError, match="schema"):
        read_items(spark, str(tmp_path / "c"), "x", "csv")
    z = zipf_source(spark, 20_000, 1.5, universe=100, partitions=2).groupBy("item").count().orderBy(F.desc("count")).first()
    assert z["item"] == 1


def test_as_of_join_and_report(spark):
    a = spark.createDataFrame([("u", 5), ("u", 1)], "k string, t int")
    b = spark.createDataFrame([("u", 2, 9), ("u", 4, 7)], "k string, t int, v int")
    assert {(r["t"], r["v"]) for r in surround.as_of(a, b, "k", "t", "v").collect()} == {(5, 7), (1, None)}
    cost = measures.cost_report(spark, a.groupBy("k").count())
    assert measures.timed(a) > 0 and cost["exchanges"] >= 1 and cost["shuffle_bytes"] > 0 and cost["spill_bytes"] == 0
    run = measures.overhead_run(spark.range(10_000).selectExpr("id % 7 AS item"), "item", FrequentSpec(5, setting="one_pass"), 4)
    assert run["items"] == 10_000 and run["wall"] > 0 and run["compute"] > 0


def test_iceberg_needs_one_bound(spark):
    with pytest.raises(ValueError, match="min_count"):
        exact.iceberg(spark.range(3), ["id"])


def test_tree_of_many_blocks_plans_fast_and_exchanges_once_a_round(spark):
    import time

    from freqspark.operators.merge import merge_tree

    local = local_summaries(blocks.by_hash(spark.range(1000).withColumnRenamed("id", "item"), 512, "item"), "item", FrequentSpec(5, kernel="exact_local"), "block")
    start = time.perf_counter()
    plan = merge_tree(local, 5, 512)._jdf.queryExecution().executedPlan().toString()
    assert time.perf_counter() - start < 20
    assert plan.split("Initial Plan")[0].count("Exchange hashpartitioning") <= 9 + 2 and "Join" not in plan


def test_two_levels_merge_inside_the_task(spark):
    df = spark.range(0, 4000, 1, 16).selectExpr("id % 50 AS item")
    spec = FrequentSpec(10, levels=2, group=4, setting="one_pass")
    from freqspark.operators.blocks import splits_of
    from freqspark.operators.local import folded_in_task

    local = folded_in_task(local_summaries(df, "item", spec), spec, splits_of(df))
    assert "Exchange" not in local._jdf.queryExecution().executedPlan().toString()
    heads = local.filter("kind = 'block'").collect()
    assert len(heads) == 4 and sum(r["n"] for r in heads) == 4000


def test_cancelled_blocks_keep_their_floor(spark):
    rows = [(i, x, b) for b, xs in enumerate(("xyz" * 100, "xxq")) for i, x in enumerate(xs)]
    df = spark.createDataFrame(rows, "at int, item string, block long")
    for rule in ("spare_zero", "tight"):
        for levels in (1, 2):
            for merge in ("flat", "tree"):
                spec = FrequentSpec(3, kernel="misra_gries", levels=levels, group=1, merge=merge, floor_rule=rule)
                assert [tuple(r) for r in frequent_items(df, "item", spec, "block", "at").collect()] == [("x", 102)]


def test_iceberg_of_shares_and_typed_keys(spark):
    df = spark.createDataFrame([("a",)] * 40 + [("b",)] * 28 + [("c",)] * 32, "k string")
    assert {r["k"] for r in exact.iceberg(df, ["k"], share=0.3, approx=True).collect()} == {"a", "c"}
    stamps = spark.sql("SELECT TIMESTAMP '2024-01-01 00:00:00.000001' + make_dt_interval(0, 0, 0, (id % 2) * 0.000001) AS t, 1 AS one FROM range(100)")
    assert sorted(r["cnt"] for r in exact.iceberg(stamps, ["t", "one"], share=0.2, approx=True).collect()) == [50, 50]


@pytest.mark.parametrize("kernel", ["batched", "scalar", "exact_local", "misra_gries"])
def test_null_groups_are_groups(spark, kernel):
    df = spark.createDataFrame([("a", "x")] * 6 + [("a", "y")] * 2 + [(None, "z")] * 5 + [(None, "x")] * 1, "g string, item string")
    got = {tuple(r) for r in frequent_items(df, "item", FrequentSpec(2, by=("g",), kernel=kernel)).collect()}
    assert got == {("a", "x", 6), (None, "z", 5)}


def test_k_above_n_warns_if_checked(spark):
    with pytest.warns(UserWarning, match="exceeds"):
        assert frequent_items(spark.createDataFrame([("a",)], "item string"), "item", 5, checked=True).count() == 1
