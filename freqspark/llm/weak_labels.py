"""Quality classifier from weak labels.

Heuristic labellers vote good, bad or nothing on every text. Expectation-maximisation over the counts of vote patterns
estimates each labeller's accuracy and the share of good texts; the posteriors label texts, and those labels train a linear
scorer on hashed words and word shapes, which then scores every text.

Votes and patterns cover all rows (a pattern table has at most 3^labellers rows); the scorer is fitted on a sample of
near ``sample_docs`` texts and at most near SAMPLE_BYTES of text per side, drawn row by row. Defined cases: null, empty and blank texts get the labellers' verdict of a short text;
repeated rows agree; an empty table gives an empty result. Columns named like a result are replaced.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..session import use_library
from . import textops as X
from .common import SAMPLE_BYTES, documents, drawn, row_key
from .quality_rules import STOP_WORDS

FEATURES = 1 << 14
SAMPLE_DOCS = 3000
LABELLERS = ("length", "symbols", "repeats", "lines", "stop_words", "capitals", "word_size")

_SHAPE = np.arange(256, dtype=np.uint8)
_SHAPE[97:123] = 97
_SHAPE[65:91] = 65
_SHAPE[48:58] = 48
_SHAPE[128:] = 97
_SIGN = np.zeros(256, dtype=np.float64)
_SIGN[[ord(c) for c in "#*$%&|<>{}\\~^=_"]] = 1
_UPPER = np.zeros(256, dtype=np.float64)
_UPPER[65:91] = 1


def _known_words() -> np.ndarray:
    data = "\n".join(STOP_WORDS).encode()
    h, _ = X.word_hashes(np.frombuffer(data, dtype=np.uint8), np.array([0, len(data)]))
    return np.unique(h)


def votes(data: np.ndarray, off: np.ndarray) -> np.ndarray:
    """Votes (texts x labellers): 1 good, -1 bad, 0 none."""
    starts, ends, first = X.word_spans(data, off)
    n = np.diff(first).astype(np.float64)
    some = np.maximum(n, 1)
    h = X.span_hash(X.prefix_hash(data, True), starts, ends) if len(starts) else np.zeros(0, np.uint64)
    runs, begin = X.shingles(h, first, 3)
    distinct, bounds = X.distinct_per_text(runs, begin)
    again = 1 - np.diff(bounds) / np.maximum(np.diff(begin), 1)
    per = lambda table: X.sums_per_text(table[data], off) if len(data) else np.zeros(len(n))
    stop = X.sums_per_text(np.isin(h, _known_words()).astype(float), first) / some
    chars = X.sums_per_text((ends - starts).astype(float), first)
    lines = []
    for a, b in zip(off[:-1], off[1:], strict=True):
        own = [x for x in data[a:b].tobytes().split(b"\n") if x.strip()]
        lines.append(1 - len(set(own)) / len(own) if own else 0.0)
    pick = lambda bad, good: np.where(bad, -1, np.where(good, 1, 0))
    sign, upper, size = per(_SIGN) / some, per(_UPPER) / np.maximum(chars, 1), chars / some
    return np.stack(
        [
            pick(n < 25, n > 80),
            pick(sign > 0.4, sign < 0.05),
            pick(again > 0.4, again < 0.1),
            pick(np.array(lines) > 0.4, np.zeros(len(n), bool)),
            pick(stop < 0.04, stop > 0.12),
            pick(upper > 0.4, upper < 0.1),
            pick((size < 2.5) | (size > 11), (size > 3.5) & (size < 9)),
        ],
        axis=1,
    ).astype(np.int8)


def estimate(patterns: np.ndarray, counts: np.ndarray, rounds: int = 200) -> tuple[float, np.ndarray, np.ndarray]:
    """Share of good texts, vote probabilities (class, labeller, vote + 1) and posterior of each pattern.

    Starts from the majority of votes; a labeller's chance to vote one way depends on the class alone.
    """
    start = patterns.sum(axis=1)
    post = np.clip(0.5 + 0.4 * np.sign(start), 0.05, 0.95)
    share, table = 0.5, np.full((2, patterns.shape[1], 3), 1 / 3)
    for _ in range(rounds):
        weight = np.stack([counts * (1 - post), counts * post])
        total = weight.sum(axis=1)
        share = (total[1] + 1) / (total.sum() + 2)
        for v in (-1, 0, 1):
            table[:, :, v + 1] = (weight @ (patterns == v) + 0.5) / (total[:, None] + 1.5)
        log = np.log([1 - share, share])[:, None] + sum(np.log(table[:, j, patterns[:, j] + 1]) for j in range(patterns.shape[1]))
        after = 1 / (1 + np.exp(np.clip(log[0] - log[1], -500, 500)))
        done = np.abs(after - post).max() < 1e-9 if len(post) else True
        post = after
        if done:
            break
    return share, table, post


def hashed(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sparse features: text, slot and value (square root of the count over the text's norm) of words and shapes."""
    starts, ends, first = X.word_spans(data, off)
    row = np.repeat(np.arange(len(off) - 1), np.diff(first))
    if not len(starts):
        return row, row.copy(), np.zeros(0)
    word = X.span_hash(X.prefix_hash(data, True), starts, ends)
    shape = X.mix(X.span_hash(X.prefix_hash(_SHAPE[data]), np.maximum(ends - 6, starts), ends) + np.uint64(77))
    slot = np.concatenate([word, shape]) % np.uint64(FEATURES)
    key, n = np.unique(np.concatenate([row, row]) * FEATURES + slot.astype(np.int64), return_counts=True)
    r, value = key // FEATURES, np.sqrt(n)
    norm = np.sqrt(np.bincount(r, value**2, minlength=len(off) - 1))
    return r, key % FEATURES, value / norm[r]


def fit_linear(r: np.ndarray, slot: np.ndarray, value: np.ndarray, y: np.ndarray, rounds: int = 150, ridge: float = 1e-4) -> np.ndarray:
    """Logistic regression on soft labels by accelerated gradient steps; the last entry is the intercept."""
    n = len(y)
    w, ahead = np.zeros(FEATURES + 1), np.zeros(FEATURES + 1)
    for t in range(rounds):
        z = np.bincount(r, value * ahead[slot], minlength=n) + ahead[-1]
        gap = 1 / (1 + np.exp(-np.clip(z, -30, 30))) - y
        grad = np.append(np.bincount(slot, value * gap[r], minlength=FEATURES) / n + ridge * ahead[:-1], gap.mean())
        after = ahead - 2.0 * grad
        ahead = after + t / (t + 3) * (after - w)
        w = after
    return w


_VOTES = T.ArrayType(T.IntegerType())


def with_votes(df: DataFrame) -> DataFrame:
    """``df`` with ``votes``, one entry per labeller of LABELLERS."""
    use_library(df.sparkSession)
    plain = df.drop("votes")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in X.slices(whole):
                v = votes(*X.column_bytes(b.column("text")))
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(v.tolist(), pa.list_(pa.int32()))], names=[*b.schema.names, "votes"])

    return plain.mapInArrow(run, T.StructType([*plain.schema.fields, T.StructField("votes", _VOTES)]))


def classify(df: DataFrame, sample_docs: int = SAMPLE_DOCS, cut: float = 0.5) -> DataFrame:
    """``df`` with votes, posterior (label model), score (linear scorer) and good (score at least ``cut``).

    Votes are counted by pattern in one pass and joined to nothing: the scoring
    pass works them out again beside the features, in one narrow stage.
    """
    spark = use_library(df.sparkSession)
    plain = df.drop("votes", "posterior", "score", "good")
    table = plain.select("text").transform(with_votes).groupBy("votes").agg(F.count(F.lit(1)).alias("n"), F.sum(F.octet_length("text")).alias("b")).orderBy("votes").collect()
    patterns = np.array([r["votes"] for r in table], dtype=np.int64).reshape(len(table), len(LABELLERS))
    _, _, post = estimate(patterns, np.array([r["n"] for r in table], dtype=float))
    posterior = {tuple(p): float(q) for p, q in zip(patterns.tolist(), post, strict=True)}

    def look_up(batches):
        for whole in batches:
            for b in X.slices(whole):
                v = votes(*X.column_bytes(b.column("text")))
                q = np.array([posterior.get(tuple(x), 0.5) for x in v.tolist()])
                yield pa.RecordBatch.from_arrays([b.column("row"), b.column("text"), pa.array(q), pa.array((q >= 0.5).astype(np.int32))], names=["row", "text", "q", "side"])

    share = []  # of each side's rows, by its rows and by their bytes
    for good in (False, True):
        own = [r for r, q in zip(table, post, strict=True) if (q >= 0.5) == good]
        n, size = sum(r["n"] for r in own), sum(r["b"] or 0 for r in own)
        share.append(min(1.0, sample_docs / max(n, 1), SAMPLE_BYTES / max(size, 1)))
    few = plain.select(row_key(plain).alias("row"), "text").filter(drawn(F.lit(max(share)), 9, "row")).mapInArrow(look_up, "row long, text string, q double, side int")
    few = few.filter(drawn(F.when(F.col("side") == 1, F.lit(share[1])).otherwise(F.lit(share[0])), 9, "row"))

    def features(batches):
        for whole in batches:
            for b in X.slices(whole):
                r, slot, value = hashed(*X.column_bytes(b.column("text")))
                cut_ = np.searchsorted(r, np.arange(b.num_rows + 1))
                yield pa.RecordBatch.from_arrays(
                    [b.column("q"), pa.ListArray.from_arrays(pa.array(cut_, pa.int32()), pa.array(slot.astype(np.int32))), pa.ListArray.from_arrays(pa.array(cut_, pa.int32()), pa.array(value.astype(np.float32)))],
                    names=["q", "slots", "values"],
                )

    sample = few.mapInArrow(features, "q double, slots array<int>, values array<float>").toPandas()
    sample = sample.assign(k=[hash((q, tuple(s[:8]))) for q, s in zip(sample["q"], sample["slots"], strict=True)]).sort_values(["q", "k"], kind="stable")
    n = [len(s) for s in sample["slots"]]
    if len(sample):
        weights = fit_linear(np.repeat(np.arange(len(sample)), n), np.concatenate(sample["slots"].tolist()).astype(np.int64), np.concatenate(sample["values"].tolist()).astype(float), sample["q"].to_numpy())
    else:
        weights = np.zeros(FEATURES + 1)
    shared = spark.sparkContext.broadcast(weights)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w = shared.value
        for whole in batches:
            for b in X.slices(whole):
                data, off = X.column_bytes(b.column("text"))
                v = votes(data, off)
                r, slot, value = hashed(data, off)
                z = np.bincount(r, value * w[slot], minlength=b.num_rows) + w[-1]
                s = 1 / (1 + np.exp(-np.clip(z, -500, 500)))
                q = np.array([posterior.get(tuple(x), 0.5) for x in v.tolist()])
                s = np.where(np.diff(np.searchsorted(r, np.arange(b.num_rows + 1))) > 0, s, q)
                yield pa.RecordBatch.from_arrays([*b.columns, pa.array(v.tolist(), pa.list_(pa.int32())), pa.array(q), pa.array(s), pa.array(s >= cut)], names=[*b.schema.names, "votes", "posterior", "score", "good"])

    out = T.StructType([*plain.schema.fields, T.StructField("votes", _VOTES), T.StructField("posterior", T.DoubleType()), T.StructField("score", T.DoubleType()), T.StructField("good", T.BooleanType())])
    return plain.mapInArrow(run, out)


def op7_weak_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents; no label table is read."""
    out = classify(documents(spark, sf_dir).select("doc_id", "text"))
    return out.select("doc_id", F.array_join(F.transform("votes", lambda v: v.cast("string")), ",").alias("votes"), "posterior", "score", F.col("good").alias("kept"))


QUERIES = {"op7_weak_labels": op7_weak_labels}
ORACLES: dict[str, str] = {}
