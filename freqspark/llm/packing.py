"""Packing along a space-filling curve.

Documents become hashed bag-of-token vectors, projected to a few dimensions; the Hilbert index of the projection orders
them, so neighbours on the curve are alike. Each range of the curve is packed end to end into full sequences.

Defined cases: null and empty texts are the end token alone; null ids stay null; repeated rows are packed once each;
a document longer than a sequence is cut freely. Documents at one curve position are ordered by id and length, so a
large group of copies is cut into ranges as any other rows. Only the last sequence of a range may be short. Other
columns are not read.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import use_library
from . import textops as X
from .common import documents, parts_for, written

END = 1
LENGTH = 2048
FEATURES, DIMS, BITS = 256, 3, 10
CACHE_WORDS = 400_000
MARK = "\x01"
# letters of ASCII and Latin-1, whose lower case and composed form are themselves, then signs other than apostrophes
_PLAIN = re.compile(r"([A-Za-zÀ-ÖØ-öø-ÿ]{0,60})([!#$%&()*+,\-./:;<=>?@\[\]^_`{|}~\"]{0,20})").fullmatch
_loaded: dict[str, tuple] = {}


def default_tokenizer() -> str:
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class WordTokens:
    """Token ids of whole texts by way of a bounded cache of words.

    The vocabulary's pre-tokeniser drops white space and never joins across it, so a text's ids are its words' ids
    end to end; tests hold this against the tokeniser on whole texts.
    """

    def __init__(self, path: str) -> None:
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # tasks are the unit of parallelism
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        self.kind = np.dtype("<u2" if self.tokenizer.get_vocab_size() <= 1 << 16 else "<u4")
        self.known: dict[str, bytes] = {"": b""}
        marked = self.tokenizer.encode(MARK, add_special_tokens=False).ids
        self.join, self.raw_ids = self._merger(path)
        self.mark = marked[0] if len(marked) == 1 else -1

    def _merger(self, path: str):
        """The same merges as byte ranks, for words whose normal form and cut are plain: a faster way to equal ids.

        The vocabulary's word end becomes the byte 0xFF, which no text holds, and joins the last byte before any merge.
        """
        import json

        import tiktoken

        with open(path, encoding="utf-8") as f:
            model = json.load(f)["model"]
        printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
        rest = [b for b in range(256) if b not in printable]
        byte_of = {chr(b): b for b in printable} | {chr(256 + i): b for i, b in enumerate(rest)}
        suffix = model["end_of_word_suffix"]
        ends, bytes_, joined = [], [], []
        for token, number in sorted(model["vocab"].items(), key=lambda x: x[1]):
            end = token.endswith(suffix)
            body = token[: len(token) - len(suffix)] if end else token
            if not body or any(c not in byte_of for c in body):
                continue
            raw = bytes(byte_of[c] for c in body)
            if b"\xff" in raw:
                if raw != b"\xff" or end:
                    continue
            if len(raw) == 1:
                (ends if end else bytes_).append((raw + b"\xff" * end, number))
            else:
                joined.append((raw + b"\xff" * end, number))
        ranked = ends + bytes_ + joined
        ranks = {raw: i for i, (raw, _) in enumerate(ranked)}
        core = tiktoken.Encoding("words", pat_str=r"[\s\S]+", mergeable_ranks=ranks, special_tokens={})
        return core._core_bpe.encode_single_piece, [np.array([n], dtype=self.kind).tobytes() for _, n in ranked]

    def _encode_words(self, words: list[str]) -> dict[str, bytes]:
        """Ids of each word. Letters with signs after them take the fast way; the rest goes to the tokeniser, many
        words at a time with a mark between them whose id is known."""
        out, hard = {}, []
        join, raw = self.join, self.raw_ids
        for w in words:
            m = _PLAIN(w)
            if m:
                stem, signs = m.groups()
                ids = join(stem.lower().encode() + b"\xff") if stem else []
                if signs:
                    ids += join(signs.encode() + b"\xff")
                out[w] = b"".join([raw[i] for i in ids])
            else:
                hard.append(w)
        words = hard
        plain = [w for w in words if MARK not in w]
        for at in range(0, len(plain), 2000):
            some = plain[at : at + 2000]
            ids = np.array(self.tokenizer.encode_batch_fast([f" {MARK} ".join(some)], add_special_tokens=False)[0].ids, dtype=self.kind)
            cut = np.flatnonzero(ids == self.mark)
            if len(cut) != len(some) - 1:  # a word that yields the mark's id by itself
                plain_ids = self.tokenizer.encode_batch_fast(some, add_special_tokens=False)
                out.update((w, np.array(e.ids, dtype=self.kind).tobytes()) for w, e in zip(some, plain_ids, strict=True))
                continue
            whole = ids.tobytes()
            edges = np.concatenate(([-1], cut, [len(ids)])) * self.kind.itemsize
            step = self.kind.itemsize
            out.update((w, whole[a + step : b]) for w, a, b in zip(some, edges[:-1].tolist(), edges[1:].tolist(), strict=True))
        rest = [w for w in words if MARK in w]
        if rest:
            out.update((w, np.array(e.ids, dtype=self.kind).tobytes()) for w, e in zip(rest, self.tokenizer.encode_batch_fast(rest, add_special_tokens=False), strict=True))
        return out

    def encode(self, text: str) -> bytes:
        words = text.replace("\n", " ").replace("\t", " ").replace("\r", " ").split(" ")
        found = list(map(self.known.get, words))
        new = list({w for w, f in zip(words, found, strict=True) if f is None})
        if new:
            if len(self.known) + len(new) > CACHE_WORDS:
                self.known = {"": b""}
                new = list(set(words) - {""})
            fresh = self._encode_words(new)
            self.known.update((w, v) for w, v in fresh.items() if len(w) <= 64)
            get = self.known.get
            found = [fresh[w] if w in fresh else get(w) for w in words]
        return b"".join(found)


def tokens_of(path: str) -> WordTokens:
    if path not in _loaded:
        _loaded[path] = WordTokens(path)
    return _loaded[path]


def hilbert(points: np.ndarray, bits: int) -> np.ndarray:
    """Hilbert index of integer points (rows), each coordinate below 2^bits: axes to transposed index, then interleave."""
    x = points.astype(np.int64).T.copy()
    dims = len(x)
    q = 1 << (bits - 1)
    while q > 1:
        low = q - 1
        for i in range(dims):
            on = (x[i] & q) != 0
            swap = np.where(on, 0, (x[0] ^ x[i]) & low)
            x[0] = np.where(on, x[0] ^ low, x[0] ^ swap)
            if i:
                x[i] ^= swap
        q >>= 1
    for i in range(1, dims):
        x[i] ^= x[i - 1]
    turn = np.zeros_like(x[0])
    q = 1 << (bits - 1)
    while q > 1:
        turn ^= np.where((x[-1] & q) != 0, q - 1, 0)
        q >>= 1
    x ^= turn
    out = np.zeros_like(x[0])
    for b in range(bits - 1, -1, -1):
        for i in range(dims):
            out = (out << 1) | ((x[i] >> b) & 1)
    return out


def curve_keys(ids: list[np.ndarray], dims: int = DIMS, bits: int = BITS, features: int = FEATURES, seed: int = 5) -> np.ndarray:
    """Curve position of each document: square-rooted hashed counts, unit length, seeded projection, Hilbert index."""
    rng = np.random.Generator(np.random.PCG64(seed))
    directions = rng.standard_normal((features, dims))
    n = len(ids)
    slot = (np.concatenate(ids).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(40)) % np.uint64(features)
    row = np.repeat(np.arange(n), [len(i) for i in ids])
    counts = np.sqrt(np.bincount(row * features + slot.astype(np.int64), minlength=n * features).reshape(n, features))
    unit = counts / np.sqrt((counts**2).sum(axis=1, keepdims=True))
    spread = np.clip((unit @ directions + 3.0) / 6.0, 0, 1 - 1e-9)
    return hilbert((spread * (1 << bits)).astype(np.int64), bits)


def _encode(path: str, end: int, dims: int, bits: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok = tokens_of(path)
        tail = np.array([end], dtype=tok.kind).tobytes()
        for whole in batches:
            for b in X.slices(whole):
                raw = [tok.encode(t or "") + tail for t in b.column("text").to_pylist()]
                ids = [np.frombuffer(r, dtype=tok.kind) for r in raw]
                yield pa.RecordBatch.from_arrays(
                    [b.column("doc_id"), pa.array(curve_keys(ids, dims, bits)), pa.array([len(i) for i in ids], pa.int64()), pa.array(raw, pa.binary())],
                    names=["doc_id", "curve_key", "doc_tokens", "ids"],
                )
        tok.known = {"": b""}
        X.release()

    return run


def encoded(df: DataFrame, tokenizer: str | None = None, end: int = END, dims: int = DIMS, bits: int = BITS) -> DataFrame:
    """(doc_id, curve_key, doc_tokens, ids as little-endian bytes of the vocabulary's width)."""
    use_library(df.sparkSession)
    return df.select("doc_id", "text").mapInArrow(_encode(tokenizer or default_tokenizer(), end, dims, bits), "doc_id long, curve_key long, doc_tokens long, ids binary")


_PIECE = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, curve_key long"


def _pack(width: int, length: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = np.dtype("<u2" if width == 2 else "<u4")
        at = 0
        first = TaskContext.get().partitionId() << 40
        for b in batches:
            rows: list[tuple] = []
            for doc, key, n, raw in zip(b.column("doc_id").to_pylist(), b.column("curve_key").to_pylist(), b.column("doc_tokens").to_pylist(), b.column("ids").to_pylist(), strict=True):
                ids = np.frombuffer(raw, dtype=kind).astype("<u4")
                start = 0
                while start < n:
                    take = min(n - start, length - at % length)
                    rows.append((doc, start, take, zlib.crc32(ids[start : start + take].tobytes()), n, first + at // length, at % length, key))
                    start += take
                    at += take
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], names=[c.split()[0] for c in _PIECE.split(", ")])

    return run


def pack(df: DataFrame, length: int = LENGTH, tokenizer: str | None = None, end: int = END, dims: int = DIMS, bits: int = BITS, part_tokens: int = 4_000_000) -> DataFrame:
    """Pieces of all documents in curve order; see the module for what is defined.

    Tokenising happens once: its result is written to the shared folder, then range-sorted by curve position.
    """
    path = tokenizer or default_tokenizer()
    table = written(encoded(df, path, end, dims, bits), "packing-ids")
    total = int(table.agg(F.sum("doc_tokens").alias("n")).first()["n"] or 0)
    width = tokens_of(path).kind.itemsize
    order = ["curve_key", "doc_id", "doc_tokens"]
    ranged = table.repartitionByRange(parts_for(total, part_tokens), *order).sortWithinPartitions(*order, F.crc32("ids"))
    return ranged.mapInArrow(_pack(width, length), _PIECE)


def op1_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents packed into sequences of 2048."""
    return pack(documents(spark, sf_dir))


QUERIES = {"op1_packing": op1_packing}
ORACLES: dict[str, str] = {}
