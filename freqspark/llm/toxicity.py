"""Toxicity from class-conditional Kneser-Ney models.

Two interpolated Kneser-Ney word-pair models, one of toxic and one of ordinary texts, over whole words. A pair backs off
to its class's words by continuation counts, a word to its class's stems (first STEM code points) by theirs, and a stem to
counts shared by both classes; how a stem's mass falls on its words is shared too. So rare forms of one expression count
together, and an expression that neither class has seen says nothing. A text is judged by its mean log-likelihood ratio per
word, by that of its most toxic window and by those of its few most toxic words, which keeps single expressions in a
long text visible; a logistic curve fitted on labelled texts that the models have not seen turns these into a score.

Fitting uses near ``sample_docs`` toxic and twice as many ordinary labelled texts; the driver holds their words and frequent pairs. Defined cases: null,
empty and blank texts score as the share of toxic labels; without both classes in the labels every text scores that
share. Rows are scored one by one, so repeated rows agree. Labels whose id or mark is null are not learned from.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import use_library
from . import textops as X
from .common import bounded_sample, crc_mod, documents, drop_written, labels, row_key, written

SAMPLE_DOCS = 2000
STEM = 4
PEAKS = (1, 3, 8)
DISCOUNT = 8.5  # rarer expressions are left to the backoff as a whole
WINDOW = 48
_COUNTS = "v long, w long, stem long, tox long, ordinary long"


def _words(b: pa.RecordBatch, column: str = "text") -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Hash of every word and of its stem, and per text the index of its first."""
    data, off = X.column_bytes(b.column(column))
    starts, ends, first = X.word_spans(data, off, X.SIGNS)
    if not len(starts):
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64), first
    chars = np.flatnonzero((data & 0xC0) != 0x80)
    at = np.searchsorted(chars, starts) + STEM
    stop = np.minimum(ends, np.append(chars, np.full(STEM, len(data)))[np.minimum(at, len(chars) + STEM - 1)])
    prefix = X.prefix_hash(data, True)
    return X.span_hash(prefix, starts, ends), X.span_hash(prefix, starts, stop), first


def _pair_key(v: np.ndarray, w: np.ndarray) -> np.ndarray:
    return X.mix(v * np.uint64(0x9FB21C651E98DF25) + w)


def _count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Distinct word pairs of each slice with their count per class; the first word of a text has no pair."""
    for whole in batches:
        for b in X.slices(whole):
            h, stem, first = _words(b)
            mark = np.repeat(b.column("toxic").to_numpy(zero_copy_only=False), np.diff(first))
            ok = np.ones(len(h), dtype=bool)
            ok[first[:-1][first[:-1] < len(h)]] = False
            at = np.flatnonzero(ok)
            if not len(at):
                continue
            v, w, y = h[at - 1], h[at], mark[at]
            key, one, where = np.unique(_pair_key(v, w), return_index=True, return_inverse=True)
            tox = np.bincount(where, y == 1, minlength=len(key))
            both = np.bincount(where, minlength=len(key))
            yield pa.RecordBatch.from_arrays([pa.array(v[one].view(np.int64)), pa.array(w[one].view(np.int64)), pa.array(stem[at][one].view(np.int64)), pa.array(tox.astype(np.int64)), pa.array((both - tox).astype(np.int64))], names=["v", "w", "stem", "tox", "ordinary"])


class ToxicityModel:
    """Log-likelihood ratios by pair and by word in sorted arrays; as large as the bounded sample's pairs."""

    def __init__(self, words: pd.DataFrame, contexts: pd.DataFrame, pairs: pd.DataFrame, discount: float = DISCOUNT) -> None:
        hashed = lambda t, c: t[c].to_numpy(np.int64).view(np.uint64)
        w, v = hashed(words, "w"), hashed(contexts, "v")
        by, at = np.argsort(w), np.argsort(v)
        self.word, self.context = w[by], v[at]
        stems, of = np.unique(hashed(words, "stem")[by], return_inverse=True)
        together = words["together"].to_numpy(float)[by]  # contexts before each word, over both classes
        stem_together = np.bincount(of, together, minlength=len(stems))
        shared = (np.maximum(stem_together - discount, 0) + np.minimum(stem_together, discount).sum() / (max(len(stems), 1) + 1)) / max(stem_together.sum(), 1.0)
        part = together / stem_together[of]  # of its stem's mass, in both classes
        before, after = np.searchsorted(self.context, hashed(pairs, "v")), np.searchsorted(self.word, hashed(pairs, "w"))
        uni, pair, weight, by_stem = [], [], [], []

        def smoothed(cont: np.ndarray, below: np.ndarray) -> tuple[np.ndarray, float]:
            mass = max(cont.sum(), 1.0)
            lam = max(np.minimum(cont, discount).sum(), 1.0) / mass
            return np.maximum(cont - discount, 0) / mass + lam * below, lam

        for y in ("tox", "ordinary"):
            cont = words[f"after_{y}"].to_numpy(float)[by]
            stemmed, _ = smoothed(np.bincount(of, cont, minlength=len(stems)), shared)
            one, lam = smoothed(cont, stemmed[of] * part)
            total, low = contexts[y].to_numpy(float)[at], contexts[f"low_{y}"].to_numpy(float)[at]
            back = np.where(total > 0, low / np.maximum(total, 1), 1.0)
            uni.append(one)
            weight.append(back)
            by_stem.append(lam * stemmed)
            pair.append(np.maximum(pairs[y].to_numpy(float) - discount, 0) / np.maximum(total[before], 1) + back[before] * one[after])
        key = _pair_key(hashed(pairs, "v"), hashed(pairs, "w"))
        order = np.argsort(key)
        self.pair_key, self.pair_ratio = key[order], np.log(pair[0] / pair[1])[order]
        self.word_ratio, self.back_ratio = np.log(uni[0] / uni[1]), np.log(weight[0] / weight[1])
        self.stem, self.stem_ratio = stems, np.log(by_stem[0] / by_stem[1])
        self.curve = np.zeros(3 + len(PEAKS))
        self.share = 0.0

    def ratios(self, h: np.ndarray, stem: np.ndarray, first: np.ndarray) -> np.ndarray:
        """Log ratio of every word given the one before it in its text; a word not counted has its stem's, or none."""
        at, known = X.find(self.word, h)
        like, like_known = X.find(self.stem, stem)
        one = np.where(like_known, self.stem_ratio[like], 0.0) if len(self.stem) else np.zeros(len(h))
        if len(self.word):
            one = np.where(known, self.word_ratio[at], one)
        led, known = X.find(self.context, h)
        back = np.where(known, self.back_ratio[led], 0.0) if len(self.context) else np.zeros(len(h))
        out = one.copy()
        if len(h) > 1:
            begins = np.zeros(len(h), dtype=bool)
            begins[first[:-1][first[:-1] < len(h)]] = True
            place, there = X.find(self.pair_key, _pair_key(h[:-1], h[1:]))
            given = np.where(there, self.pair_ratio[place] if len(self.pair_key) else 0.0, back[:-1] + one[1:])
            out[1:] = np.where(begins[1:], one[1:], given)
        return out

    def features(self, h: np.ndarray, stem: np.ndarray, first: np.ndarray) -> np.ndarray:
        """Per text: mean ratio per word, the mean over its most toxic WINDOW words in a row, and means of its peaks."""
        r = self.ratios(h, stem, first)
        n = np.diff(first)
        total = np.concatenate(([0.0], np.cumsum(r)))
        mean = (total[first[1:]] - total[first[:-1]]) / np.maximum(n, 1)
        top = mean * n / np.maximum(WINDOW, 1)
        long = np.flatnonzero(n > WINDOW)
        if len(long):
            sums = (total[WINDOW:] - total[:-WINDOW]) / WINDOW
            for i in long:
                top[i] = sums[first[i] : first[i + 1] - WINDOW + 1].max()
        peaks = np.zeros((len(n), len(PEAKS)))
        for i in np.flatnonzero(n):
            high = np.sort(r[first[i] : first[i + 1]])[-max(PEAKS) :][::-1]
            for j, k in enumerate(PEAKS):
                peaks[i, j] = high[:k].sum() / k
        return np.concatenate([np.stack([mean, top], axis=1), peaks], axis=1)

    def score(self, features: np.ndarray, n: np.ndarray) -> np.ndarray:
        z = np.clip(self.curve[0] + features @ self.curve[1:], -500, 500)
        return np.where(n > 0, 1 / (1 + np.exp(-z)), self.share)


def fit_curve(x: np.ndarray, y: np.ndarray, ridge: float = 0.001, rounds: int = 60) -> np.ndarray:
    """Logistic regression by Newton steps on standardised features, given back on the original scale."""
    mean, spread = x.mean(axis=0), np.maximum(x.std(axis=0), 1e-9)
    z = np.concatenate([np.ones((len(x), 1)), (x - mean) / spread], axis=1)
    b = np.zeros(z.shape[1])
    penalty = np.diag([1e-6, *[ridge] * x.shape[1]]) * len(x)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ b, -30, 30)))
        step = np.linalg.solve((z.T * np.maximum(p * (1 - p), 1e-6)) @ z + penalty, z.T @ (y - p) - penalty @ b)
        b += step
        if np.abs(step).max() < 1e-8:
            break
    return np.concatenate([[b[0] - (b[1:] * mean / spread).sum()], b[1:] / spread])


def _feature_rows(shared):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in X.slices(whole):
                x = shared.value.features(*_words(b))
                yield pa.RecordBatch.from_arrays([b.column("toxic").cast(pa.int64()), pa.array(x.tolist(), pa.list_(pa.float64()))], names=["toxic", "x"])

    return run


def train_on(docs: DataFrame, marks: DataFrame, sample_docs: int = SAMPLE_DOCS) -> ToxicityModel:
    """Fit on the texts of ``docs`` that ``marks`` (doc_id, toxic) labels.

    The sample is drawn from the marks, so at most three times ``sample_docs`` small rows are broadcast to the texts' scan
    and no text is shuffled.
    """
    known = marks.filter("toxic IS NOT NULL AND doc_id IS NOT NULL").select("doc_id", F.col("toxic").cast("long").alias("toxic"))
    totals = {r["toxic"]: r["n"] for r in known.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    few = bounded_sample(known.filter("toxic IN (0, 1)"), "toxic", {1: sample_docs, 0: 2 * sample_docs}, "doc_id")
    return train(docs.select("doc_id", "text").join(F.broadcast(few), "doc_id"), sample_docs, totals=totals)


def train(labelled: DataFrame, sample_docs: int = SAMPLE_DOCS, discount: float = DISCOUNT, totals: dict | None = None) -> ToxicityModel:
    """Fit on (text, toxic): two thirds of the sample for the counts, one third for the curve.

    ``totals`` (rows per class) says that ``labelled`` is a sample already.
    """
    spark = use_library(labelled.sparkSession)
    rows = labelled.filter("toxic IN (0, 1) AND text IS NOT NULL").select(F.col("toxic").cast("long").alias("toxic"), "text", F.pmod(F.xxhash64(F.lit(3), "text"), F.lit(3)).alias("fold"), row_key(labelled).alias("__row"))
    drawn_already = totals is not None
    if not drawn_already:
        totals = {r["toxic"]: r["n"] for r in rows.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    share = totals.get(1, 0) / max(sum(totals.values()), 1)
    sample = written(bounded_sample(rows, "toxic", {1: 1 << 40, 0: 1 << 40} if drawn_already else {1: sample_docs, 0: 2 * sample_docs}, "__row", "text"), "toxicity-sample")
    counted = sample.filter("fold <> 0").select("text", "toxic").mapInArrow(_count, _COUNTS).groupBy("v", "w", "stem").agg(F.sum("tox").alias("tox"), F.sum("ordinary").alias("ordinary"))
    counted = written(counted, "toxicity-pairs")
    # a pair at or below the discount in both classes is its backoff alone: the driver gets words, contexts and the pairs above
    words = counted.groupBy("w", "stem").agg(F.count(F.lit(1)).alias("together"), F.count_if(F.col("tox") > 0).alias("after_tox"), F.count_if(F.col("ordinary") > 0).alias("after_ordinary")).toPandas()
    low = lambda c: F.sum(F.least(F.col(c).cast("double"), F.lit(discount))).alias(f"low_{c}")
    contexts = counted.groupBy("v").agg(F.sum("tox").alias("tox"), F.sum("ordinary").alias("ordinary"), low("tox"), low("ordinary")).toPandas()
    pairs = counted.filter((F.col("tox") > discount) | (F.col("ordinary") > discount)).toPandas()
    model = ToxicityModel(words, contexts, pairs, discount)
    drop_written(counted)
    model.share = share
    shared = spark.sparkContext.broadcast(model)
    seen = sample.filter("fold = 0").select("toxic", "text").mapInArrow(_feature_rows(shared), "toxic long, x array<double>").orderBy("toxic", "x").toPandas()
    y = (seen["toxic"] == 1).to_numpy(float)
    if 0 < y.sum() < len(y):
        model.curve = fit_curve(np.array(seen["x"].tolist()), y)
        drawn = {c: min(n, sample_docs * (2 - c)) / n for c, n in totals.items() if n and c in (0, 1)}
        model.curve[0] += np.log(drawn.get(0, 1.0) / drawn.get(1, 1.0))  # the sample's odds back to the labels'
    else:
        model.curve = np.array([np.log(max(share, 1e-6) / max(1 - share, 1e-6)), *[0.0] * (2 + len(PEAKS))])
    return model


def score_toxicity(df: DataFrame, model: ToxicityModel, cut: float = 0.7) -> DataFrame:
    """``df`` with ``score`` and ``predicted``; one narrow stage."""
    spark = use_library(df.sparkSession)
    plain = df.drop(*[c for c in ("score", "predicted") if c in df.columns])
    shared = spark.sparkContext.broadcast(model)  # bounded by the fitting sample

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in X.slices(whole):
                h, stem, first = _words(b)
                s = shared.value.score(shared.value.features(h, stem, first), np.diff(first))
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(s), pa.array((s >= cut).astype(np.int32))], names=[*b.schema.names, "score", "predicted"])

    return plain.mapInArrow(run, T.StructType([*plain.schema.fields, T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())]))


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents; labels are learned where the id's crc32 does not leave 1 modulo 3."""
    docs = documents(spark, sf_dir)
    marks = labels(spark, sf_dir).filter(crc_mod("doc_id", 3) != 1).select("doc_id", "toxic")
    model = train_on(docs, marks)
    rows = docs.select("doc_id", (F.coalesce(crc_mod("doc_id", 3), F.lit(-1)) == 1).alias("held_out"), "text")
    return score_toxicity(rows, model).select("doc_id", "held_out", "score", "predicted")


QUERIES = {"op9_toxicity": op9_toxicity}
ORACLES: dict[str, str] = {}
