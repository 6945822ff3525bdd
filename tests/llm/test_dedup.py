from __future__ import annotations

import hashlib
import re
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from freqspark.llm import near_dedup, suffix_dedup
from freqspark.llm.common import spread_join
from freqspark.llm.components import components
from freqspark.llm.suffix_sort import common_prefixes, suffix_array

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def lower(t: str) -> str:
    return re.sub("[A-Z]", lambda m: m[0].lower(), t)


def shingle_set(t: str | None, k: int) -> frozenset:
    w = WORD.findall(lower(t or ""))
    return frozenset(tuple(w[i : i + k]) for i in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else [])


def brute_components(ids, texts, k: int, percent: int) -> tuple[dict, dict]:
    sets = {i: shingle_set(t, k) for i, t in zip(ids, texts, strict=True)}
    parent = {i: i for i in sets}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    where = defaultdict(list)
    for i in sorted(sets):
        met = Counter(j for s in sets[i] for j in where[s])
        for j, n in met.items():
            if 100 * n >= percent * (len(sets[i]) + len(sets[j]) - n):
                a, b = root(i), root(j)
                parent[max(a, b)] = min(a, b)
        for s in sets[i]:
            where[s].append(i)
    return sets, {i: root(i) for i in sets}


@pytest.mark.parametrize("k", [2, 5])
def test_near_duplicates_equal_brute_force(spark, texts, sf_small, k):
    docs = spark.read.parquet(f"{sf_small}/documents.parquet")
    got = near_dedup.op4_near_dedup(spark, sf_small) if k == 2 else near_dedup.near_duplicates(docs, words=k)
    sets, comp = brute_components(texts["doc_id"], texts["text"], k, 80)
    assert {tuple(r) for r in got.collect()} == {(i, len(sets[i]), comp[i], comp[i] == i) for i in sets}


def test_members_beyond_the_hub_are_found(spark):
    """x and y are near each other but neither is near the bucket's hub in some bands; chains still join."""
    rng = np.random.default_rng(3)
    base = [f"w{i}" for i in range(120)]
    docs, chain = [], base
    for i in range(12):
        docs.append((i, " ".join(chain)))
        chain = list(chain)
        for j in rng.integers(0, 120, 6):
            chain[j] = f"v{i}x{j}"
    df = spark.createDataFrame(docs, "doc_id long, text string")
    _, comp = brute_components([d[0] for d in docs], [d[1] for d in docs], 2, 80)
    assert {(r["doc_id"], r["component_id"]) for r in near_dedup.near_duplicates(df, words=2).collect()} == set(comp.items())


def test_members_far_from_every_hub_meet_the_near_ones(spark):
    """Long variants with small ids lead every bucket; truncated copies are too short for them and near one text only."""
    rng = np.random.default_rng(11)
    core = [f"c{i}" for i in range(200)]
    texts = [core + [f"x{i}y{j}" for j in range(int(rng.integers(36, 44)))] for i in range(1000)]
    texts += [core] + [core[: 200 - cut] for cut in (30, 34, 36)] + [core[cut:] for cut in (30, 34, 36)]
    docs = [(i, " ".join(t)) for i, t in enumerate(texts)]
    _, comp = brute_components([d[0] for d in docs], [d[1] for d in docs], 2, 80)
    assert set(comp.values()) == {0}
    got = near_dedup.near_duplicates(spark.createDataFrame(docs, "doc_id long, text string"), words=2)
    assert {(r["doc_id"], r["component_id"]) for r in got.collect()} == set(comp.items())


def test_clusters_beyond_one_group_equal_brute_force(spark, monkeypatch):
    """With tiny limits, clusters are confirmed in blocks and crowds are led in parts; the result stays."""
    for name, value in (("SMALL", 3), ("BLOCK", 2), ("LED", 2)):
        monkeypatch.setattr(near_dedup, name, value)
    rng = np.random.default_rng(5)
    docs = []
    for family in range(3):
        chain = [f"f{family}w{i}" for i in range(100)]
        for step in range(10):
            docs.append((len(docs), " ".join(chain)))
            chain = list(chain)
            for j in rng.integers(0, 100, 5):
                chain[j] = f"f{family}v{step}x{j}"
            docs.append((len(docs), " ".join(chain[: int(rng.integers(70, 100))])))
    df = spark.createDataFrame(docs, "doc_id long, text string")
    _, comp = brute_components([d[0] for d in docs], [d[1] for d in docs], 2, 80)
    assert max(Counter(comp.values()).values()) > 3
    assert {(r["doc_id"], r["component_id"]) for r in near_dedup.near_duplicates(df, words=2).collect()} == set(comp.items())


def test_odd_sketch_estimates_high_similarity():
    rng = np.random.default_rng(5)
    a = rng.integers(0, 2**62, (1, 312)).astype(np.uint64)
    b = a.copy()
    b[0, :31] = rng.integers(0, 2**62, 31).astype(np.uint64)
    x, y = near_dedup.odd_sketches(a), near_dedup.odd_sketches(b)
    distance = int(np.bitwise_count(x ^ y).sum())
    assert abs(near_dedup.sketch_similarity(distance, 312) - 0.9) < 0.05
    assert distance <= near_dedup.sketch_cut(0.8, 312) < 256


def test_near_duplicate_cases(odd, empty):
    got = Counter(tuple(r) for r in near_dedup.near_duplicates(odd).collect())
    assert got[(1, 2, 1, True)] == 2 and got[(None, 2, 1, False)] == 1
    for i in (2, 3, 4):
        assert got[(i, 0, i, True)] == 1
    assert near_dedup.near_duplicates(empty).count() == 0
    kept = near_dedup.deduplicated(odd)
    assert kept.columns == odd.columns
    assert Counter(r["doc_id"] for r in kept.collect()) == {1: 1, 2: 1, 3: 1, 4: 1, 5: 1, 6: 1, None: 1}
    assert near_dedup.deduplicated(empty).count() == 0


def test_joins_spread_hot_keys(spark):
    many = spark.range(6000).select((F.col("id") % 3).alias("k"), F.col("id").alias("v")).unionByName(spark.range(4000).select(F.lit(0).alias("k"), (F.col("id") + 6000).alias("v")))
    one = spark.createDataFrame([(0, 6000, "a"), (1, 2000, "b")], "k long, c long, name string")
    want = {(v, "ab"[v % 3] if v % 3 < 2 else None) for v in range(6000)} | {(v, "a") for v in range(6000, 10_000)}
    rows = spread_join(many, one, ["k"], "c", 10_000, "left").select("v", "name").collect()
    assert len(rows) == 10_000 and {tuple(r) for r in rows} == want
    assert spread_join(many, one, ["k"], "c", 10_000).count() == 8000


def test_components_of_chains_and_stars(spark):
    links = [(300, j) for j in range(301, 3000)] + [(i, i + 1) for i in range(40)] + [(100, j) for j in range(101, 160)] + [(200, 201), (201, 200)]
    got = {r["node"]: r["component"] for r in components(spark.createDataFrame(links, "a long, b long"), "test").collect()}
    assert all(got[i] == 0 for i in range(41)) and all(got[i] == 100 for i in range(100, 160)) and got[201] == 200 and all(got[i] == 300 for i in range(300, 3000))


def test_suffix_array_and_prefixes():
    rng = np.random.default_rng(1)
    for _ in range(400):
        d = rng.integers(97, 97 + int(rng.integers(1, 4)), int(rng.integers(0, 40))).astype(np.uint8)
        s = bytes(d)
        want = sorted(range(len(s)), key=lambda i: s[i:])
        assert suffix_array(d, 64).tolist() == want
        common = common_prefixes(d, np.array(want, dtype=int), 64)
        for i in range(1, len(s)):
            a, b = s[want[i] :], s[want[i - 1] :]
            assert common[i] == next((k for k in range(min(len(a), len(b))) if a[k] != b[k]), min(len(a), len(b)))


def brute_removed(rows: list[tuple[int, bytes]], length: int) -> dict:
    seen, out = set(), {}
    for i, b in sorted(rows):
        gone = np.zeros(len(b), bool)
        for k in range(len(b) - length + 1):
            w = b[k : k + length]
            if w in seen:
                gone[k : k + length] = True
            seen.add(w)
        spans = int((np.diff(np.concatenate(([0], gone.astype(int)))) == 1).sum())
        out[i] = (len(b), int(gone.sum()), spans, hashlib.sha256(bytes(np.frombuffer(b, np.uint8)[~gone])).hexdigest())
    return out


def test_suffix_dedup_equals_brute_force(spark, texts, sf_small):
    want = brute_removed([(i, t.encode()) for i, t in zip(texts["doc_id"], texts["text"], strict=True)], 100)
    got = {r["doc_id"]: tuple(r)[1:] for r in suffix_dedup.op6_suffix_dedup(spark, sf_small).collect()}
    assert got == want


def test_suffix_dedup_with_hot_anchors_and_periods(spark, monkeypatch):
    rng = np.random.default_rng(2)
    line = "a common line of forty bytes or so, here."
    docs = [(i, "".join(rng.choice(list("abcdef "), 150)) + line + "".join(rng.choice(list("abcdef "), 150))) for i in range(60)]
    docs += [(60, "x" * 500), (61, "xy" * 300), (62, docs[3][1] + docs[4][1]), (63, "é" * 200 + docs[5][1][100:300])]
    want = brute_removed([(i, t.encode()) for i, t in docs], 100)
    df = spark.createDataFrame(docs, "doc_id long, text string")
    for hot, share, least in ((50_000, 64, 50), (3, 64, 50), (50_000, 1, 1)):
        monkeypatch.setattr(suffix_dedup, "HOT_SEGMENTS", hot)
        monkeypatch.setattr(suffix_dedup, "HEAT_SHARE", share)
        monkeypatch.setattr(suffix_dedup, "HEAT_LEAST", least)
        out = suffix_dedup.remove_repeats(df).collect()
        assert {r["doc_id"]: (r["n_bytes"], r["n_removed"], len(r["spans"]), hashlib.sha256(r["kept"]).hexdigest()) for r in out} == want


def test_numbers_of_repeated_and_null_ids(spark):
    rows = [(None, "b"), (None, "a"), (3, "x"), (1, "y"), (1, "z"), (1, "y"), (2, None)]
    out = suffix_dedup._numbered(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert len(out) == len(rows)
    number = {(r["doc_id"], r["text"]): r["doc"] for r in out}
    assert sorted(number.values()) == [1, 2, 3, 4, 5, 6]
    assert {number[None, "a"], number[None, "b"]} == {1, 2} and {number[1, "y"], number[1, "z"]} == {3, 4} and number[2, None] == 5 and number[3, "x"] == 6


def test_resolve_holds_over_batches():
    """Any cut into batches gives the same rows as one batch."""
    rng = np.random.default_rng(4)
    cols = [rng.integers(0, 12, 300), rng.integers(0, 3, 300), rng.integers(0, 50, 300), rng.integers(0, 50, 300), np.full(300, 5), np.where(rng.random(300) < 0.1, -1, 7)]
    cols = [c[np.lexsort((cols[3], cols[2], cols[1], cols[0]))] for c in cols]
    for hot in ([], [2, 5]):
        seen = []
        for size in (300, 64, 7, 1):
            batches = [suffix_dedup._batch([c[i : i + size] for c in cols], suffix_dedup._SEGMENT) for i in range(0, 300, size)]
            seen.append(Counter(tuple(r.values()) for b in suffix_dedup._resolve(100, np.array(hot, dtype=np.int64))(iter(batches)) for r in b.to_pylist()))
        assert all(s == seen[0] for s in seen)


def test_suffix_dedup_cases(odd, empty):
    out = suffix_dedup.remove_repeats(odd).collect()
    assert len(out) == odd.count()
    long = next(r for r in out if r["doc_id"] == 6)
    assert long["n_bytes"] == 150_000 and long["n_removed"] == 150_000 - 5
    assert suffix_dedup.remove_repeats(empty).count() == 0
    assert suffix_dedup.without_repeats(odd).columns == odd.columns
