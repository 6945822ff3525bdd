"""Language identification by unigram piece models, summed over all segmentations.

The pieces are a fixed public vocabulary; each language has a probability per piece, fitted by expectation-maximisation
on a bounded sample of labelled texts (SAMPLE_DOCS rows and SAMPLE_BYTES of text a language). The probability of a word is the sum over all ways to cut it into pieces, found
by a forward pass; a text's is the product over its words.

Defined cases: null texts and texts without a letter are ``und`` with score 0, as is everything when no labelled text
exists. Rows with a null language are never learned from. Repeated rows get equal answers. Words over 40 characters
are summed in logarithms, where their products would leave the range of numbers; they are not cut. Other columns are
kept by the stage and not read by the model.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import use_library
from . import textops as X
from .common import bounded_sample, crc_mod, documents, row_key

SAMPLE_DOCS = 500
LONGEST_PIECE = 16  # the vocabulary's longest; vocabulary() refuses a longer one
RUN = 40
ROUNDS = 3
FLOOR = 1e-7
CACHE_WORDS = 400_000

# runs of letters: signs and digits say nothing of a language
_LETTERS = re.compile(r"[^\W\d_]+").findall


def default_pieces() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def vocabulary(path: str, longest: int = LONGEST_PIECE) -> dict[str, int]:
    """Lower-case pieces of the public model by dense number."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    pieces = (model.id_to_piece(i) for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i)))
    kept = [p for p in dict.fromkeys(pieces) if p == p.lower() and p]
    if max(map(len, kept), default=0) > longest:
        raise ValueError(f"the vocabulary has a piece of {max(map(len, kept))} characters, more than {longest}")
    return {p: n for n, p in enumerate(kept)}


def lattices(words: list[str], pieces: dict[str, int], longest: int = LONGEST_PIECE) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Per word length: the words' positions in the list, and the piece ending at each place by its length.

    Entry [m, j, l] is the number of the piece ``word[j - l : j + 1]``, -1 for none, and the last number for a single
    character outside the vocabulary.
    """
    by_length: dict[int, list[int]] = {}
    for n, w in enumerate(words):
        by_length.setdefault(len(w), []).append(n)
    get, unknown = pieces.get, len(pieces)
    for length, which in by_length.items():
        step = max(1, 20_000 * RUN // max(RUN, length))
        for at in range(0, len(which), step):
            some = which[at : at + step]
            grid = np.full((len(some), length, min(longest, length)), -1, dtype=np.int32)
            own = [words[i] for i in some]
            for j in range(length):
                for size in range(min(longest, j + 1)):
                    grid[:, j, size] = [get(w[j - size : j + 1], -1 if size else unknown) for w in own]
            yield np.array(some), grid


def forward(grid: np.ndarray, prob: np.ndarray) -> np.ndarray:
    """Sums over segmentations of every prefix: shape (words, length + 1, languages). ``prob`` ends with a zero row."""
    m, length, longest = grid.shape
    out = np.zeros((m, length + 1, prob.shape[1]))
    out[:, 0] = 1.0
    for j in range(length):
        for size in range(min(longest, j + 1)):
            piece = grid[:, j, size]
            on = np.flatnonzero(piece >= 0)
            if 2 * len(on) > m:
                out[:, j + 1] += out[:, j - size] * prob[piece]
            elif len(on):  # long pieces are rare
                out[on, j + 1] += out[on, j - size] * prob[piece[on]]
    return out


def log_forward(grid: np.ndarray, prob: np.ndarray) -> np.ndarray:
    """Logarithms of :func:`forward`, for words of any length."""
    m, length, longest = grid.shape
    out = np.full((m, length + 1, prob.shape[1]), -np.inf)
    out[:, 0] = 0.0
    for j in range(length):
        for size in range(min(longest, j + 1)):
            on = np.flatnonzero(grid[:, j, size] >= 0)
            if len(on):
                out[on, j + 1] = np.logaddexp(out[on, j + 1], out[on, j - size] + np.log(prob[grid[on, j, size]]))
    return out


def log_backward(grid: np.ndarray, prob: np.ndarray) -> np.ndarray:
    m, length, longest = grid.shape
    out = np.full((m, length + 1, prob.shape[1]), -np.inf)
    out[:, length] = 0.0
    for j in range(length - 1, -1, -1):
        for size in range(min(longest, j + 1)):
            on = np.flatnonzero(grid[:, j, size] >= 0)
            if len(on):
                out[on, j - size] = np.logaddexp(out[on, j - size], out[on, j + 1] + np.log(prob[grid[on, j, size]]))
    return out


def backward(grid: np.ndarray, prob: np.ndarray) -> np.ndarray:
    m, length, longest = grid.shape
    out = np.zeros((m, length + 1, prob.shape[1]))
    out[:, length] = 1.0
    for j in range(length - 1, -1, -1):
        for size in range(min(longest, j + 1)):
            out[:, j - size] += out[:, j + 1] * prob[grid[:, j, size]]
    return out


def _table(counts: np.ndarray) -> np.ndarray:
    """Probabilities from expected counts (pieces x languages), with the unknown character's floor and a zero row."""
    smooth = counts + 0.05
    return np.concatenate([smooth / smooth.sum(axis=0), np.full((1, counts.shape[1]), FLOOR), np.zeros((1, counts.shape[1]))])


def fit(words: list[str], weight: np.ndarray, pieces: dict[str, int], rounds: int = ROUNDS) -> np.ndarray:
    """Expectation-maximisation: ``weight`` (words x languages) holds how often each language has each word."""
    n = len(pieces)
    prob = _table(np.ones((n, weight.shape[1])))
    grids = list(lattices(words, pieces))
    for _ in range(rounds):
        expected = np.zeros((n + 1, weight.shape[1]))
        for which, grid in grids:
            long = grid.shape[1] > RUN
            ahead, behind = (log_forward(grid, prob), log_backward(grid, prob)) if long else (forward(grid, prob), backward(grid, prob))
            scale = weight[which] if long else weight[which] / ahead[:, -1]
            for j in range(grid.shape[1]):
                for size in range(min(grid.shape[2], j + 1)):
                    piece = grid[:, j, size]
                    on = piece >= 0
                    if on.any():
                        if long:
                            part = np.exp(ahead[on, j - size] + behind[on, j + 1] - ahead[on, -1]) * prob[piece[on]] * scale[on]
                        else:
                            part = ahead[on, j - size] * prob[piece[on]] * behind[on, j + 1] * scale[on]
                        for g in range(weight.shape[1]):
                            expected[:, g] += np.bincount(piece[on], part[:, g], minlength=n + 1)
        prob = _table(expected[:n])
    return prob


class LanguageModel:
    """Piece probabilities per language; small and fixed in size, so it travels with the tasks."""

    def __init__(self, languages: list[str], prob: np.ndarray, pieces_path: str) -> None:
        self.languages, self.prob, self.pieces_path = languages, prob, pieces_path

    def __getstate__(self):
        return (self.languages, self.prob, self.pieces_path)

    def __setstate__(self, state):
        self.languages, self.prob, self.pieces_path = state

    def start(self) -> None:
        self.pieces = vocabulary(self.pieces_path)
        self._clear()

    def _clear(self) -> None:
        self.at: dict[str, int] = {}
        self.rows = np.zeros((0, len(self.languages)))

    def word_rows(self, words: list[str]) -> np.ndarray:
        """Log probability of each word under each language."""
        found = list(map(self.at.get, words))
        if None in found:
            new = list({w for w, f in zip(words, found, strict=True) if f is None})
            if len(self.at) + len(new) > CACHE_WORDS and self.at:
                self._clear()
                return self.word_rows(words)
            log = np.zeros((len(new), len(self.languages)))
            for which, grid in lattices(["▁" + w for w in new], self.pieces):
                log[which] = log_forward(grid, self.prob)[:, -1] if grid.shape[1] > RUN else np.log(forward(grid, self.prob)[:, -1])
            base = len(self.rows)
            self.rows = np.concatenate([self.rows, log])
            self.at.update((w, base + i) for i, w in enumerate(new))
            found = list(map(self.at.get, words))
        return self.rows[np.array(found, dtype=np.int64)] if found else np.zeros((0, len(self.languages)))

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        import regex

        letter = regex.compile(r"\p{L}").search
        split = [_LETTERS(t.lower()) or t.lower().split() if t and letter(t) else [] for t in texts]
        begin = np.concatenate(([0], np.cumsum([len(w) for w in split]))).astype(np.int64)
        like = X.sums_per_text(self.word_rows([w for ws in split for w in ws]), begin)
        n = np.diff(begin)
        tempered = like / np.sqrt(np.maximum(n, 1))[:, None]
        odds = np.exp(tempered - tempered.max(axis=1, keepdims=True)) if len(self.languages) else tempered
        best = tempered.argmax(axis=1) if len(self.languages) else np.zeros(len(n), int)
        share = odds[np.arange(len(n)), best] / odds.sum(axis=1) if len(self.languages) else np.zeros(len(n))
        known = [bool(k) and bool(self.languages) for k in n]
        return [self.languages[b] if k else "und" for b, k in zip(best, known, strict=True)], [float(s) if k else 0.0 for s, k in zip(share, known, strict=True)]


def train(df: DataFrame, text: str = "text", lang: str = "lang", sample_docs: int = SAMPLE_DOCS, pieces_path: str | None = None) -> LanguageModel:
    """Fit on near ``sample_docs`` whole texts of each language; the sample's word counts come to the driver."""
    path = pieces_path or default_pieces()
    known = df.filter(F.col(lang).isNotNull() & F.col(text).isNotNull())
    rows = bounded_sample(known.select(lang, text, row_key(known).alias("__row")), lang, sample_docs, "__row", text)
    words = rows.select(lang, F.explode(F.split(F.lower(text), r"[^\p{L}]+")).alias("w")).filter("w != ''").groupBy(lang, "w").agg(F.count(F.lit(1)).alias("n")).toPandas()
    languages = sorted(words[lang].unique())
    pieces = vocabulary(path)
    code = {w: i for i, w in enumerate(sorted(words["w"].unique()))}
    place = {g: i for i, g in enumerate(languages)}
    weight = np.zeros((len(code), len(languages)))
    np.add.at(weight, (words["w"].map(code).to_numpy(dtype=int), words[lang].map(place).to_numpy(dtype=int)), words["n"].to_numpy())
    if not languages:
        return LanguageModel([], np.zeros((len(pieces) + 2, 0)), path)
    return LanguageModel(languages, fit(["▁" + w for w in code], weight, pieces), path)


def identify(df: DataFrame, model: LanguageModel, text: str = "text") -> DataFrame:
    """``df`` with ``lang_pred`` and ``score``; one narrow stage, in which the text alone leaves the JVM."""
    from pyspark.sql.functions import ArrowUDFType, arrow_udf

    spark = use_library(df.sparkSession)
    plain = df.drop(*[c for c in ("lang_pred", "score") if c in df.columns])
    shared = spark.sparkContext.broadcast(model)  # its size is pieces times languages, whatever the input
    kind = pa.struct([("lang_pred", pa.string()), ("score", pa.float64())])

    def run(texts: Iterator[pa.Array]) -> Iterator[pa.Array]:
        m = shared.value
        m.start()
        try:
            for whole in texts:
                out = []
                for b in X.slices(pa.RecordBatch.from_arrays([whole], names=["t"]), "t"):
                    best, score = m.predict(b.column("t").to_pylist())
                    out.append(pa.StructArray.from_arrays([pa.array(best, pa.string()), pa.array(score, pa.float64())], fields=list(kind)))
                yield pa.concat_arrays(out) if out else pa.array([], kind)
        finally:
            m._clear()
            X.release()

    predict = arrow_udf(run, "struct<lang_pred:string,score:double>", ArrowUDFType.SCALAR_ITER)
    return plain.withColumn("_named", predict(text)).select(*plain.columns, "_named.lang_pred", "_named.score")


def keep_identified(df: DataFrame, least: float = 0.4, **options) -> DataFrame:
    """The rows whose language the model names with at least ``least``; ``und`` rows go. Columns stay as they are."""
    model = train(df, **options)
    named = identify(df.withColumnsRenamed({"lang_pred": "_lang_pred", "score": "_score"}), model)
    kept = named.filter((F.col("lang_pred") != "und") & (F.col("score") >= least)).drop("lang_pred", "score")
    return kept.withColumnsRenamed({"_lang_pred": "lang_pred", "_score": "score"}).select(*df.columns)


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents; learned from the labelled texts whose id's crc32 leaves no remainder 0 modulo 5."""
    docs = documents(spark, sf_dir)
    model = train(docs.filter(crc_mod("doc_id", 5) != 0))
    rows = docs.select("doc_id", (F.coalesce(crc_mod("doc_id", 5), F.lit(-1)) == 0).alias("held_out"), "text")
    return identify(rows, model).select("doc_id", "held_out", "lang_pred", "score")


QUERIES = {"op3_language_id": op3_language_id}
ORACLES: dict[str, str] = {}
