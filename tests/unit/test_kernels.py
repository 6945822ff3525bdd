from __future__ import annotations

from collections import Counter

import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from freqspark.kernels.batched import batched_kernel, cut, fold, merge_pair
from freqspark.kernels.scalar import Summary, misra_gries_kernel, scalar_kernel
from freqspark.spec import FrequentSpec, threshold_count

settings.register_profile("plain", deadline=None)
settings.load_profile("plain")
ITEMS = st.lists(st.integers(0, 9), max_size=60)


def holds(s: Summary, items: list, k: int) -> None:
    true = Counter(items)
    assert s.n == len(items)
    assert s.floor * k <= s.n
    for x, (est, err) in s.counters.items():
        assert true[x] <= est <= true[x] + err and err <= s.floor
    for x, c in true.items():
        assert x in s.counters or c <= s.floor
        if c >= threshold_count(len(items), k):
            assert x in s.counters


@given(ITEMS, st.integers(2, 8), st.sampled_from(["item", "oldest"]))
def test_scalar_keeps_its_bounds_and_sums_to_n(items, k, tie):
    s = scalar_kernel(items, k, tie)
    holds(s, items, k)
    assert sum(e for e, _ in s.counters.values()) == len(items)


@given(ITEMS, st.integers(2, 8), st.integers(1, 9))
def test_batched_keeps_its_bounds(items, k, size):
    batches = [(pa.array(items[i : i + size], pa.int64()), None) for i in range(0, len(items), size)]
    holds(batched_kernel(batches, k), items, k)


@settings(max_examples=200, deadline=None)
@given(ITEMS, st.integers(2, 8), st.integers(1, 9), st.sampled_from(["spare_zero", "tight"]))
def test_merged_blocks_keep_their_bounds(items, k, p, rule):
    n = len(items)
    blocks = [items[i * n // p : (i + 1) * n // p] for i in range(p)]
    holds(fold((scalar_kernel(b, k) for b in blocks), k, rule), items, k)


@given(ITEMS, st.integers(2, 8))
def test_misra_gries_is_the_counter_summary_without_its_floor(items, k):
    s, m = scalar_kernel(items, k), misra_gries_kernel(items, k)
    assert m.floor * k <= len(items)
    true = Counter(items)
    for x, (est, _) in m.counters.items():
        assert true[x] - m.floor <= est <= true[x]
    assert {x: e - s.floor for x, (e, _) in s.counters.items() if e > s.floor} == {x: e for x, (e, _) in m.counters.items()}


def test_worked_trace_and_merge():
    s = scalar_kernel(list("abacabda"), 2)
    assert s.counters == {"d": [4, 3], "a": [4, 3]} and s.floor == 4
    a, b = Summary(7, 2, {"x": [5, 0], "y": [2, 0]}), Summary(5, 1, {"y": [4, 0], "z": [1, 0]})
    assert {x: c[0] for x, c in merge_pair(a, b, 2).counters.items()} == {"x": 6, "y": 6}
    assert merge_pair(a, b, 2).floor == 6 and merge_pair(a, b, 2, "tight").floor == 3


def test_stored_minimum_can_break_the_bound():
    a, b = Summary(100, 0, {"a": [100, 0]}), Summary(1, 0, {"b": [1, 0]})
    assert merge_pair(a, b, 5).counters["b"][0] == 1
    assert cut({"a": [100, 0]}, 5, 0, "stored_min")[1] == 100 and cut({"a": [100, 0]}, 5, 0, "spare_zero")[1] == 0


def test_weights_count_as_repeats():
    s = scalar_kernel(["a", "b", "a", "c"], 3, weights=[2, 1, 3, 0])
    assert s.n == 6 and s.counters == {"a": [5, 0], "b": [1, 0]}


@pytest.mark.parametrize(("option", "value"), [("k", 1), ("levels", 3), ("merge", "heap"), ("counters", 3), ("fan_in", 1)])
def test_spec_names_what_is_wrong(option, value):
    with pytest.raises(ValueError, match=option):
        FrequentSpec(**({"k": 5} | {option: value}))


def test_threshold_is_strict():
    assert threshold_count(10, 5) == 3 and threshold_count(11, 5) == 3 and threshold_count(4, 10) == 1
    with pytest.warns(UserWarning, match="exceeds"):
        assert FrequentSpec(10).validate(4) == 1
