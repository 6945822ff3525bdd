from __future__ import annotations

import math
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from freqspark.llm import katz, language_id, toxicity, weak_labels
from freqspark.llm.common import crc_mod

from .test_dedup import WORD, lower

END = "\0end"


class BruteKatz:
    """The model by plain dictionaries: contexts of up to ``order - 1`` words, the first word's context is the end."""

    def __init__(self, docs: dict, held: dict, order: int) -> None:
        self.order = order
        self.tokens = {i: WORD.findall(lower(t or "")) + [END] for i, t in docs.items()}
        self.one, self.after = Counter(), [defaultdict(Counter) for _ in range(order + 1)]
        for i, w in self.tokens.items():
            if held[i]:
                continue
            self.one.update(w)
            for m in range(2, order + 1):
                for at in range(m - 2, len(w)):
                    self.after[m][tuple(([END] + w)[at - m + 2 : at + 1])][w[at]] += 1
        self.n = sum(self.one.values())
        of_counts = lambda counts: np.bincount([min(x, 7) for x in counts], minlength=8)[:7]
        self.d = [None, katz.discounts(of_counts(self.one.values()))]
        self.d += [katz.discounts(of_counts([c for x in self.after[m].values() for c in x.values()])) for m in range(2, order + 1)]
        self.unknown = 1 - sum(self.d[1][min(c, 6)] * c / self.n for c in self.one.values())
        self.spread: dict = {}

    def context(self, h: tuple) -> tuple[dict, float]:
        if h not in self.spread:
            own = self.after[len(h) + 1][h]
            total = sum(own.values())
            seen = {w: self.d[len(h) + 1][min(c, 6)] * c / total for w, c in own.items()}
            left = 1 - sum(seen.values())
            if all(c > 5 for c in own.values()):
                seen, left = {w: p * total / (total + 1) for w, p in seen.items()}, 1 / (total + 1)
            self.spread[h] = seen, left / (1 - sum(self.p(h[1:], w) for w in seen))
        return self.spread[h]

    def p(self, h: tuple, w: str) -> float:
        if not h:
            return self.d[1][min(self.one[w], 6)] * self.one[w] / self.n if self.one[w] else self.unknown
        if h not in self.after[len(h) + 1]:
            return self.p(h[1:], w)
        seen, weight = self.context(h)
        return seen[w] if w in seen else weight * self.p(h[1:], w)

    def score(self, w: list) -> float:
        back = [END] + w
        return sum(math.log10(self.p(tuple(back[max(0, i - self.order + 2) : i + 1]), x)) for i, x in enumerate(w))


@pytest.mark.parametrize(("sizes", "order"), [({}, 3), ({"block_bytes": 40_000, "bucket_bytes": 50_000}, 3), ({"block_bytes": 40_000, "bucket_bytes": 50_000}, 4), ({}, 2), ({}, 1)])
def test_katz_equals_brute_force_and_sums_to_one(spark, texts, sf_small, sizes, order):
    docs = spark.read.parquet(f"{sf_small}/documents.parquet").select("doc_id", (crc_mod("doc_id", 7) == 2).alias("held_out"), "text")
    held = {i: zlib.crc32(str(i).encode()) % 7 == 2 for i in texts["doc_id"]}
    want = BruteKatz(dict(zip(texts["doc_id"], texts["text"], strict=True)), held, order)
    one, n = want.one, want.n
    for r in katz.fit(docs, **sizes, order=order).scores().collect():
        w = want.tokens[r["doc_id"]]
        assert (r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"]) == (held[r["doc_id"]], len(w), sum(one[x] > 0 for x in w), n)
        assert math.isclose(r["score"], want.score(w), rel_tol=1e-9)
        assert math.isclose(r["base_score"], sum(math.log10((one[x] + 1) / (n + len(one) + 1)) for x in w), rel_tol=1e-9)
    for m in range(2, order + 1):
        for h in list(want.after[m])[:15]:
            assert math.isclose(want.p(h, "\0unknown") + sum(want.p(h, w) for w in one), 1, rel_tol=1e-9)


def test_katz_cases(odd, empty):
    rows = odd.select("doc_id", (F.col("doc_id") == 5).alias("held_out"), "text").na.fill({"held_out": False})
    out = katz.fit(rows).scores().collect()
    assert len(out) == odd.count() and all(math.isfinite(r["score"]) for r in out)
    assert katz.fit(rows.filter("false")).scores().count() == 0
    none = katz.fit(rows.withColumn("held_out", F.lit(True))).scores().collect()
    assert all(r["score"] == 0 and r["train_tokens"] == 0 for r in none)


def test_packed_arrays_come_back():
    for a in ([], [0], [1, 255, 256], [2**40, 3], list(range(1000))):
        a = np.array(a, dtype=np.uint64)
        assert katz.stretch(katz.squeeze(a)).tolist() == a.tolist()


def brute_segments(word: str, pieces: dict[str, int], prob: np.ndarray) -> float:
    if not word:
        return 1.0
    total = 0.0
    for i in range(1, min(len(word), language_id.LONGEST_PIECE) + 1):
        n = pieces.get(word[:i], len(pieces) if i == 1 else None)
        if n is not None:
            total += prob[n, 0] * brute_segments(word[i:], pieces, prob)
    return total


def test_forward_pass_sums_all_segmentations():
    pieces = {p: i for i, p in enumerate(["a", "b", "ab", "ba", "aba", "▁", "▁a"])}
    prob = np.concatenate([np.random.default_rng(0).random((7, 1)) / 7, [[1e-7]], [[0.0]]])
    words = ["▁abab", "▁ba", "▁xab", "▁aaaab"]
    for which, grid in language_id.lattices(words, pieces):
        got = language_id.forward(grid, prob)[:, -1, 0]
        assert np.allclose(got, [brute_segments(words[i], pieces, prob) for i in which])
        assert np.allclose(language_id.backward(grid, prob)[:, 0, 0], got)


def test_whole_vocabulary_and_long_words_are_summed():
    """Long pieces of the public vocabulary count, and a word of over 40 letters is not cut."""
    pieces = language_id.vocabulary(language_id.default_pieces())
    assert {"▁information", "▁different", "formation"} <= set(pieces)
    prob = np.concatenate([np.random.default_rng(0).random((len(pieces), 2)) / len(pieces), np.full((1, 2), 1e-7), np.zeros((1, 2))])
    model = language_id.LanguageModel(["a", "b"], prob, language_id.default_pieces())
    model.start()
    words = ["information", "different", "xinformationdifferent" * 3, "information" * 200]
    got = model.word_rows(words)
    for row, w in zip(got, words, strict=True):
        marked = "▁" + w
        sums, scale = [np.ones(2)], np.zeros(2)
        for j in range(len(marked)):
            new = np.zeros(2)
            for size in range(min(language_id.LONGEST_PIECE, j + 1)):
                n = pieces.get(marked[j - size : j + 1], None if size else len(pieces))
                if n is not None:
                    new = new + sums[-1 - size] * prob[n]
            sums = [s / new for s in sums] + [np.ones(2)]
            scale += np.log(new)
            sums = sums[-language_id.LONGEST_PIECE :]
        assert np.allclose(row, scale)
    fitted = language_id.fit(["▁" + w for w in words], np.ones((4, 2)), pieces)
    assert np.isfinite(fitted).all() and fitted[pieces["▁information"], 0] > fitted[0, 0]


def test_language_accuracy_and_cases(spark, texts, sf_small, odd, empty):
    got = {r["doc_id"]: r for r in language_id.op3_language_id(spark, sf_small).collect()}
    held = [(r["lang_pred"], lang) for r, lang in ((got[i], g) for i, g in zip(texts["doc_id"], texts["lang"], strict=True)) if r["held_out"] and lang]
    assert np.mean([a == b for a, b in held]) > 0.97
    model = language_id.train(odd)
    out = language_id.identify(odd, model).collect()
    assert all((r["lang_pred"] == "und") == (not re.search(r"[^\W\d_]", r["text"] or "")) for r in out)
    assert language_id.keep_identified(empty).count() == 0
    assert {r["lang_pred"] for r in language_id.identify(odd, language_id.train(empty)).collect()} == {"und"}
    assert language_id.keep_identified(odd).columns == odd.columns


def test_toxicity_separates_and_cases(spark):
    rng = np.random.default_rng(0)
    rows = []
    for i in range(600):
        bad = i % 3 == 0
        w = [f"w{x}" for x in rng.zipf(1.4, 80) % 400]
        if bad:
            for j in rng.integers(0, 80, 4):
                w[j] = rng.choice(["grumblesnitch", "zonkerhead"])
        rows.append((i, " ".join(w), int(bad)))
    df = spark.createDataFrame(rows, "doc_id long, text string, toxic int")
    model = toxicity.train(df.filter("doc_id % 2 = 0").select("text", "toxic"))
    out = toxicity.score_toxicity(df.filter("doc_id % 2 = 1"), model).collect()
    assert np.mean([r["predicted"] == r["toxic"] for r in out]) > 0.95
    blank = toxicity.score_toxicity(spark.createDataFrame([(1, None), (2, ""), (3, " ")], "doc_id long, text string"), model).collect()
    assert all(abs(r["score"] - model.share) < 1e-12 for r in blank)
    none = toxicity.train(df.filter("false").select("text", "toxic"))
    assert all(0 <= r["score"] <= 1 for r in toxicity.score_toxicity(df.limit(5), none).collect())


def test_weak_labels_recover_known_accuracies():
    rng = np.random.default_rng(1)
    truth = rng.random(20_000) < 0.7
    right = np.array([0.9, 0.8, 0.7, 0.85, 0.6])
    votes = np.where(rng.random((20_000, 5)) < right, np.where(truth, 1, -1)[:, None], np.where(truth, -1, 1)[:, None])
    patterns, counts = np.unique(votes, axis=0, return_counts=True)
    share, table, post = weak_labels.estimate(patterns, counts.astype(float))
    assert abs(share - 0.7) < 0.03
    assert np.abs(table[1, :, 2] - right).max() < 0.03


def test_weak_label_query_and_cases(spark, sf_small, odd, empty):
    got = weak_labels.op7_weak_labels(spark, sf_small).toPandas().merge(spark.read.parquet(f"{sf_small}/labels.parquet").toPandas())
    assert (got["kept"] == (got["quality"] == 1)).mean() > 0.8
    out = weak_labels.classify(odd)
    assert out.count() == odd.count() and {"votes", "posterior", "score", "good"} <= set(out.columns)
    assert weak_labels.classify(empty).count() == 0


def test_samples_of_one_repeated_text_are_near_their_limit(spark):
    """Copies fall one by one, and a class of few huge texts is bounded by bytes."""
    from freqspark.llm.common import bounded_sample, row_key

    rows = spark.range(20_000).select(F.col("id").alias("doc_id"), F.lit("one text for all").alias("text"), F.lit("a").alias("c"))
    for key in ("doc_id", row_key(rows.drop("doc_id"))):
        assert 380 < bounded_sample(rows, "c", 500, key, "text").count() < 640
    long = spark.range(2_000).select(F.col("id").alias("doc_id"), F.repeat(F.lit("x"), 10_000).alias("text"), F.lit("a").alias("c"))
    assert 50 < bounded_sample(long, "c", 5_000, "doc_id", "text", 1_000_000).count() < 160
    assert bounded_sample(rows, "c", {"b": 5}, "doc_id").count() == 0


def test_toxicity_backs_off_from_words_to_stems(spark):
    """An unseen form of a toxic word is judged by its stem; words that share four bytes only are told apart."""
    rows = [(i, ("so the snarkle" if i % 2 else "so the snarfle") + f" went home w{i % 30} today", i % 2) for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id long, text string, toxic int")
    model = toxicity.train(df.select("text", "toxic"))
    texts = [(1, "so the snarkle went home w3 today"), (2, "so the snarfle went home w3 today"), (3, "die größte Überraschung"), (4, "ü")]
    out = {r["doc_id"]: r["score"] for r in toxicity.score_toxicity(spark.createDataFrame(texts, "doc_id long, text string"), model).collect()}
    assert out[1] > 0.7 > 0.3 > out[2] and all(0 <= s <= 1 for s in out.values())


def test_toxicity_cases(odd, empty):
    """Null ids and texts, repeated rows, clashing names, a very long text, an empty table."""
    labelled = odd.withColumn("toxic", (F.col("doc_id") % 2).cast("int"))
    model = toxicity.train(labelled.select("text", "toxic"))
    out = toxicity.score_toxicity(odd.withColumn("score", F.lit("x")).withColumn("predicted", F.lit("y")), model)
    rows = out.collect()
    assert len(rows) == odd.count() and all(0 <= r["score"] <= 1 for r in rows)
    assert len({r["score"] for r in rows if r["text"] and r["text"].startswith("alpha")}) == 1
    assert toxicity.score_toxicity(empty, model).count() == 0


def test_weak_labels_with_clashing_names(odd):
    out = weak_labels.classify(odd.withColumn("votes", F.lit(1)).withColumn("posterior", F.lit("x")).withColumn("row", F.lit(3)))
    rows = out.collect()
    assert len(rows) == odd.count() and all(0 <= r["posterior"] <= 1 for r in rows) and all(r["row"] == 3 for r in rows)
    assert len({(r["score"], r["posterior"]) for r in rows if r["text"] and r["text"].startswith("alpha")}) == 1


def test_language_posterior_equals_brute_force(spark):
    """The whole query on a small corpus: every word by summing its segmentations, every text by Bayes over languages."""
    rows = [(i, t, g) for i, (t, g) in enumerate([("the cat and the dog", "en"), ("the house of the man", "en"), ("der hund und die katze", "de"), ("das haus und der mann", "de")] * 3)]
    df = spark.createDataFrame([*rows, (99, "the hund", None), (100, "12 34", None)], "doc_id long, text string, lang string")
    model = language_id.train(df)
    model.start()
    for r in language_id.identify(df, model).collect():
        words = re.findall(r"[^\W\d_]+", r["text"].lower())
        if not words:
            assert (r["lang_pred"], r["score"]) == ("und", 0.0)
            continue
        like = [sum(math.log(brute_segments("▁" + w, model.pieces, model.prob[:, [g]])) for w in words) / math.sqrt(len(words)) for g in range(2)]
        odds = [math.exp(x - max(like)) for x in like]
        best = max(range(2), key=lambda g: odds[g])
        assert r["lang_pred"] == model.languages[best] and math.isclose(r["score"], odds[best] / sum(odds), rel_tol=1e-9)
