from __future__ import annotations

import hashlib
import zlib
from collections import Counter
from itertools import product

import duckdb
import numpy as np
import pytest

import corpus_pipeline
from freqspark.llm import mixing, packing, quality_rules, syncmers
from freqspark.llm import textops as X


def test_rules_equal_their_sql(spark, sf_small):
    db = duckdb.connect()
    db.execute(f"create view documents as select * from '{sf_small}/documents.parquet'")
    want = db.execute(quality_rules.ORACLES["op8_quality_rules"]).df()
    got = quality_rules.op8_quality_rules(spark, sf_small).toPandas()
    cols = sorted(want.columns)
    assert sorted(map(tuple, got[cols].astype(str).to_numpy())) == sorted(map(tuple, want[cols].astype(str).to_numpy()))


def test_rules_run_without_user_functions_and_cases(odd, empty):
    out = quality_rules.quality_rules(odd)
    assert "Python" not in out._jdf.queryExecution().executedPlan().toString()
    rows = out.collect()
    assert len(rows) == odd.count() and all(r["base_failed"] and not r["kept"] for r in rows if not (r["text"] or "").strip())
    long = next(r for r in rows if r["doc_id"] == 6)
    assert long["n_words"] == 30_000 and long["n_repeat_words"] == 30_000
    assert quality_rules.quality_rules(empty).count() == 0


def test_token_cache_equals_the_tokeniser(texts):
    tok = packing.tokens_of(packing.default_tokenizer())
    odd = ["", "  ", "don't STOP'S it's", "<|endoftext|> hi", "ß É x ÿ,", "\x1c\x1d x", "日本語 テスト", "a" * 300, "a_b (y) http://a.b/c?d=1", "ªº µ", "foo\x0bbar", "x \x01 y\x01z", "é ́x"]
    for t in [*odd, *texts["text"]]:
        assert np.frombuffer(tok.encode(t), tok.kind).tolist() == tok.tokenizer.encode(t, add_special_tokens=False).ids


def test_hilbert_curve_is_a_path():
    points = np.array(list(product(range(8), repeat=3)))
    order = points[np.argsort(packing.hilbert(points, 3))]
    assert len(set(packing.hilbert(points, 3).tolist())) == 512
    assert (np.abs(np.diff(order, axis=0)).sum(axis=1) == 1).all()


def check_pieces(pieces, texts: list[tuple[int | None, str | None]], length: int = 2048) -> None:
    tok = packing.tokens_of(packing.default_tokenizer())
    ids = {i: np.array(tok.tokenizer.encode(t or "", add_special_tokens=False).ids + [1], dtype="<u4") for i, t in texts}
    cover, fill = Counter(), {}
    for r in pieces:
        own = ids[r["doc_id"]][r["start"] : r["start"] + r["length"]]
        assert len(own) == r["length"] and zlib.crc32(own.tobytes()) == r["ids_crc32"] and r["doc_tokens"] == len(ids[r["doc_id"]])
        cover[r["doc_id"]] += r["length"]
        fill.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    assert cover == {i: len(v) for i, v in ids.items()}
    for parts in fill.values():
        at = 0
        for offset, n in sorted(parts):
            assert offset == at
            at += n
        assert at <= length


def test_packing_covers_every_id_once(spark, texts, sf_small):
    rows = packing.op1_packing(spark, sf_small).collect()
    check_pieces(rows, list(zip(texts["doc_id"], texts["text"], strict=True)))
    full = Counter()
    for r in rows:
        full[r["sequence_id"]] += r["length"]
    assert sum(2048 - n for n in full.values()) < 0.05 * sum(full.values())


def test_packing_cases(odd, empty):
    unique = odd.dropDuplicates(["doc_id"])
    check_pieces(packing.pack(unique).collect(), [(r["doc_id"], r["text"]) for r in unique.collect()])
    assert packing.pack(empty).count() == 0


@pytest.mark.parametrize("seed", range(30))
def test_subset_sums_are_best(seed):
    rng = np.random.default_rng(seed)
    lengths = sorted(set(rng.integers(1, 30, 5).tolist()))
    counts = rng.integers(1, 4, len(lengths)).tolist()
    reach = {sum(a * b for a, b in zip(lengths, take, strict=True)) for take in product(*(range(c + 1) for c in counts))}
    for goal in rng.integers(0, max(reach) + 5, 6).tolist():
        take = mixing.choose_counts(lengths, counts, goal)
        got = sum(a * b for a, b in zip(lengths, take, strict=True))
        assert all(0 <= t <= c for t, c in zip(take, counts, strict=True))
        assert abs(got - goal) == min(abs(s - goal) for s in reach)


def test_large_goals_are_met_too():
    rng = np.random.default_rng(4)
    lengths = sorted(set(rng.integers(3, 3000, 900).tolist()))
    counts = rng.integers(1, 200, len(lengths)).tolist()
    total = sum(a * b for a, b in zip(lengths, counts, strict=True))
    for share in (0.1, 0.5, 0.93):
        goal = int(total * share)
        take = mixing.choose_counts(lengths, counts, goal)
        assert all(0 <= t <= c for t, c in zip(take, counts, strict=True))
        assert sum(a * b for a, b in zip(lengths, take, strict=True)) == goal


def brute_targets(size: dict, weights=(1, 2, 3), cap=3) -> dict:
    names = sorted(size, key=lambda s: (s is None, (s or "").encode()))
    weight = {s: weights[i % 3] for i, s in enumerate(names)}
    total, capped = sum(size.values()), set()
    while True:
        free = [s for s in names if s not in capped]
        rest = total - sum(cap * size[s] for s in capped)
        target = {s: cap * size[s] if s in capped else rest * weight[s] / sum(weight[x] for x in free) for s in names}
        over = {s for s in free if target[s] > cap * size[s]}
        if not over:
            return target
        capped |= over


def test_mixing_targets_and_taken_words(spark, sf_small):
    got = mixing.op5_mixing(spark, sf_small).toPandas().merge(spark.read.parquet(f"{sf_small}/documents.parquet").select("doc_id", "source", "text").toPandas())
    per = got.groupby("source").agg(size=("size", "sum"), target=("target", "first"), taken=("taken", "sum"))
    want = brute_targets(per["size"].to_dict())
    for s, r in per.iterrows():
        assert abs(r["target"] - want[s]) < 1e-6 * want[s] and abs(r["taken"] - r["target"]) <= 0.02 * want[s]
    assert (got["taken"] <= 3 * got["size"]).all()
    again = mixing.op5_mixing(spark, sf_small).toPandas()
    assert sorted(map(tuple, again.to_numpy())) == sorted(map(tuple, got[again.columns].to_numpy()))


def test_small_sources_stop_at_three_times_their_size(spark):
    rows = [(i, "w " * 50, "big") for i in range(100)] + [(1000, "a b c", "c"), (1001, "x y", None), (1002, None, "d")]
    out = mixing.mix(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    want = brute_targets({"big": 5000, "c": 3, "d": 0, None: 2})
    for r in out:
        assert abs(r["target"] - want[r["source"]]) < 1e-6
    assert sum(r["size"] * r["copies"] for r in out) == 5000 + 9 + 6  # 4,990 is met by 100 documents of 50 words


def test_mixing_cases(odd, empty):
    assert mixing.mix(odd).count() == odd.count()
    assert mixing.mix(empty).count() == 0 and mixing.mixed_documents(empty).count() == 0
    assert mixing.mixed_documents(odd).columns == odd.columns


def brute_syncmers(b: bytes, k: int, s: int) -> list[int]:
    def h(i: int) -> int:
        d = np.frombuffer(b[i : i + s], np.uint8)
        return int(X.span_hash(X.prefix_hash(d), np.array([0]), np.array([s]))[0])

    out = []
    for i in range(len(b) - k + 1):
        inner = [h(j) for j in range(i, i + k - s + 1)]
        if min(inner) in (inner[0], inner[-1]):
            out.append(i)
    return out


def test_syncmers_equal_their_definition(spark):
    texts = ["abracadabra abracadabra alakazam", "short", "", "ééééééééééééééé x", "the quick brown fox jumps over the lazy dog"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    got = {(r["doc_id"], r["pos"]) for r in syncmers.anchors(df).collect()}
    assert got == {(i, p) for i, t in enumerate(texts) for p in brute_syncmers(t.encode(), syncmers.K, syncmers.S)}


def test_fingerprints_of_edits(spark, texts, sf_small):
    got = {r["doc_id"]: r for r in syncmers.fingerprints_with_edit(spark.read.parquet(f"{sf_small}/documents.parquet"), part_bytes=20_000).collect()}
    ids, t = list(texts["doc_id"]), list(texts["text"])
    assert len(got) == len(ids)
    prints: dict[str, str] = {}
    for i, doc in enumerate(ids):
        following, half = t[(i + 1) % len(t)], len(t[i]) // 2
        edited = t[i][: len(t[i]) - half] + following[:half]
        r = got[doc]
        assert r["n_chars"] == len(t[i]) and r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        assert prints.setdefault(t[i], r["fingerprint"]) == r["fingerprint"]
        if following == t[i]:
            assert r["near_next"] == 1.0
    assert np.mean([r["near_edited"] for r in got.values()]) > np.mean([r["near_next"] for r in got.values()]) + 0.2


def test_fingerprint_cases(odd, empty):
    rows = syncmers.fingerprints_with_edit(odd).collect()
    assert len(rows) == odd.count()
    assert all((r["fingerprint"] == "") == (r["n_chars"] == 0) for r in rows)
    assert syncmers.fingerprints_with_edit(empty).count() == 0
    assert syncmers.fingerprints_with_edit(odd.filter("doc_id = 3")).collect()[0]["near_next"] == 1.0


def test_pipeline_runs_and_passes_empty_tables(spark, sf_small, empty, tmp_path):
    docs = spark.read.parquet(f"{sf_small}/documents.parquet")
    before = docs.count()
    for name, stage in corpus_pipeline.STAGES[:-1]:
        after = stage(spark, docs, sf_small).persist()
        assert after.columns == docs.columns and 0 < after.count() <= 3 * before, name
        docs = after
    rows = corpus_pipeline.run(spark, sf_small).collect()
    assert {r["doc_id"] for r in rows} <= set(range(before)) and max(r["length"] for r in rows) <= 2048
    empty.drop("size").write.parquet(str(tmp_path / "documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
