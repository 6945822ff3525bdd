"""Katz backoff of any order: Good-Turing discounts, exactly normalised backoff weights, partitioned count tables.

Words, then word pairs, then three-word runs and so on up to ``order`` are counted in one exchange each between blocks of
documents and buckets of keys. A block sends each bucket its distinct keys once, packed; the bucket adds the counts of all
blocks and answers every block in the order asked. So a word or run that all documents share costs one entry per block,
never a row per occurrence, and no table of the vocabulary is ever broadcast. Runs are dealt by their context, those of
the most frequent contexts by the whole run. A context that only one block has is counted by that block alone. A block
sends at most one message to a bucket and at most one per distinct key, so messages never outnumber the rows of a plain
exchange of keys.

The model, evaluated per token from the longest context down: for a context h with count c(h), P(w | h) = d(c) c(h, w) /
c(h) for seen runs and a(h) P(w | h') otherwise, where h' drops the first word of h and a(h) shares what the discounts
leave over the words not seen after h. A context without training count hands on to h' with weight one. Single words
are discounted in the same way; the remainder is the probability of any unknown word. The end token is the first word's
context, and no context reaches further back. Where discounts leave a context nothing (all its runs are frequent) every
count of it is scaled by c(h) / (c(h) + 1), so sums stay exactly one.

Words are known by 64-bit hashes, runs of two words and more by 64-bit hashes of their words' numbers.

Defined cases: null and empty texts are one end token. A row without an id is training text, since its remainder is
unknown. With no training text every token is unknown and has probability 1. Equal rows count as often as they stand.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import use_library
from . import textops as X
from .common import crc_mod, documents, drop_part, free_shuffles, parts_for, text_bytes, written

END_HASH = np.uint64(0x9D5F3B21C7A46E0D)
KEPT = 5  # counts above this are not discounted
ORDER = 3
BLOCK_BYTES, BUCKET_BYTES = 5 << 20, 8 << 20
_MESSAGE = "kind int, bucket int, block long, load binary"
_CHAIN = np.uint64(0x9FB21C651E98DF25)


def squeeze(a: np.ndarray) -> tuple:
    """A non-negative integer array as compressed byte planes of its least width."""
    top = int(a.max()) if len(a) else 0
    kind = np.uint8 if top < 1 << 8 else np.uint16 if top < 1 << 16 else np.uint32 if top < 1 << 32 else np.uint64
    narrow = a.astype(kind)
    planes = narrow.view(np.uint8).reshape(-1, narrow.itemsize).T.tobytes() if len(a) else b""
    return np.dtype(kind).char, len(a), zstandard.ZstdCompressor(level=1).compress(planes)


def stretch(packed: tuple) -> np.ndarray:
    kind, n, planes = packed
    width = np.dtype(kind).itemsize
    raw = np.frombuffer(zstandard.ZstdDecompressor().decompress(planes, max_output_size=max(n * width, 1)), dtype=np.uint8)
    return np.ascontiguousarray(raw.reshape(width, n).T).reshape(-1).view(kind).astype(np.uint64) if n else np.zeros(0, np.uint64)


def _longs(packed: tuple) -> np.ndarray:
    return stretch(packed).view(np.int64)


def _gaps(a: np.ndarray) -> np.ndarray:
    return np.diff(a, prepend=np.uint64(0))


def _ungap(packed: tuple) -> np.ndarray:
    return np.cumsum(stretch(packed), dtype=np.uint64)


def _dump(*parts) -> bytes:
    return pickle.dumps(parts, protocol=5)


def _rows(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int32(), pa.int32(), pa.int64(), pa.binary())
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=["kind", "bucket", "block", "load"])


def discounts(n: np.ndarray, kept: int = KEPT) -> np.ndarray:
    """Good-Turing ratios for counts 0..kept+1 from how many keys have each count (``n[r]``, r up to kept + 1).

    Katz's form, which leaves counts above ``kept`` whole. Where the data give no ratio in (0, 1) for a count, it is
    r / (r + 1), so counts keep their order.
    """
    out = np.ones(kept + 2)
    common = (kept + 1) * n[kept + 1] / n[1] if n[1] else 1.0
    for r in range(1, kept + 1):
        turing = (r + 1) * n[r + 1] / (r * n[r]) if n[r] else 0.0
        ratio = (turing - common) / (1 - common) if common < 1 else 0.0
        out[r] = ratio if 0 < ratio < 1 else r / (r + 1)
    return out


def _of_counts(c: np.ndarray) -> np.ndarray:
    """How many keys have each count up to KEPT + 1."""
    return np.bincount(c[(c > 0) & (c <= KEPT + 1)], minlength=KEPT + 2)


class Unigrams:
    """Discounted unigram probabilities from totals alone: c(w) is all that is needed of a word."""

    def __init__(self, total: int, words: int, n: np.ndarray) -> None:
        self.total, self.words = total, words
        self.d = discounts(n)
        mass = sum((1 - self.d[r]) * r * n[r] for r in range(1, KEPT + 1)) / total if total else 1.0
        self.over = max(total, 1)  # what counts are divided by
        if total and mass <= 0:
            self.over, mass = total + 1, 1 / (total + 1)
        self.unknown = mass if total else 1.0

    def p(self, c: np.ndarray) -> np.ndarray:
        return np.where(c > 0, self.d[np.minimum(c, KEPT + 1)] * c / self.over, self.unknown)


def backoff(d: np.ndarray, c: np.ndarray, rare: np.ndarray, known: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Per context: factor on its seen runs and backoff weight. ``rare[:, r - 1]`` runs have count r; ``known`` is the
    mass that the next shorter context gives all seen words."""
    left = (rare * ((1 - d[1 : KEPT + 1]) * np.arange(1, KEPT + 1))).sum(axis=1) / np.maximum(c, 1)
    none = left <= 0
    factor = np.where(none, c / (c + 1), 1.0)
    left = np.where(none, 1 / (c + 1), left)
    return factor, left / np.maximum(1 - known, 1e-12)


def _bucket(h: np.ndarray, buckets: int) -> np.ndarray:
    return ((h >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)).astype(np.int64)


def _blocks(buckets: int, block_bytes: int):
    """kind 0: a block's documents and local tokens; kind 1: its distinct words and their training counts, by bucket."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        base = TaskContext.get().partitionId() << 32
        number, held = 0, 0
        parts: list[tuple] = []

        def flush() -> pa.RecordBatch:
            nonlocal number, held, parts
            ids = [i for p in parts for i in p[0]]
            out = np.array([o for p in parts for o in p[1]], dtype=bool)
            size = np.concatenate([p[2] for p in parts])
            words, local, _ = X.distinct(np.concatenate([p[3] for p in parts]))
            train = np.repeat(~out, size)
            count = np.bincount(local[train], minlength=len(words))
            common = np.argsort(-np.bincount(local, minlength=len(words)), kind="stable")  # small numbers pack better
            rank = np.empty(len(words), dtype=np.int64)
            rank[common] = np.arange(len(words))
            block = base + number
            rows = [(0, 0, block, _dump(ids, out, squeeze(size), squeeze(rank[local]), squeeze(common)))]
            cut = np.searchsorted(_bucket(words, buckets), np.arange(buckets + 1))
            for k in range(buckets):
                a, b = cut[k], cut[k + 1]
                if b > a:
                    rows.append((1, k, block, _dump(squeeze(_gaps(words[a:b])), squeeze(count[a:b]))))
            number, held, parts = number + 1, 0, []
            return _rows(rows)

        for whole in batches:
            for b in X.slices(whole):
                data, off = X.column_bytes(b.column("text"))
                h, first = X.word_hashes(data, off)
                n = np.diff(first)
                tokens = np.insert(h, first[1:], END_HASH)  # an end after each text's words
                parts.append((b.column("doc_id").to_pylist(), b.column("held_out").to_pylist(), n + 1, tokens))
                held += len(data) + 64 * len(n)
                if held >= block_bytes:
                    yield flush()
        if parts:
            yield flush()
        X.release()

    return run


def _per_bucket(batches: Iterator[pa.RecordBatch], answer):
    """Rows arrive sorted by bucket; ``answer(bucket, blocks, loads)`` gives the rows to send back."""
    at, blocks, loads = None, [], []
    for b in batches:
        for bucket, block, load in zip(b.column("bucket").to_pylist(), b.column("block").to_pylist(), b.column("load"), strict=True):
            if bucket != at:
                if loads:
                    yield _rows(answer(at, blocks, loads))
                at, blocks, loads = bucket, [], []
            blocks.append(block)
            loads.append(load.as_py())
    if loads:
        yield _rows(answer(at, blocks, loads))
    X.release()


def _numbers(place: np.ndarray, c: np.ndarray, bucket: int, buckets: int) -> np.ndarray:
    return np.where(c > 0, (place + 1) * buckets + bucket, 0)


def _count_words(buckets: int):
    """kind 2: places in the bucket and counts in the order asked, from which numbers follow that are unique and 0 for
    words without training count; kind 3: totals."""

    def answer(bucket: int, blocks: list[int], loads: list[bytes]) -> list[tuple]:
        hashes, counts = [], []
        for raw in loads:
            h, c = pickle.loads(raw)
            hashes.append(_ungap(h))
            counts.append(_longs(c))
        words, where, _ = X.distinct(np.concatenate(hashes))
        c = np.bincount(where, np.concatenate(counts), minlength=len(words)).astype(np.int64)
        rows, at = [], 0
        for block, h in zip(blocks, hashes, strict=True):
            mine = where[at : at + len(h)]
            rows.append((2, bucket, block, _dump(bucket, squeeze(_gaps(mine.astype(np.uint64))), squeeze(c[mine]))))
            at += len(h)
        top = np.argsort(-c, kind="stable")[:64]
        rows.append((3, bucket, 0, _dump(int(c.sum()), int((c > 0).sum()), _of_counts(c), _numbers(top, c[top], bucket, buckets).astype(np.uint64), c[top])))
        return rows

    def run(batches):
        yield from _per_bucket(batches, answer)

    return run


class _Grams:
    """A block's distinct runs of one length, seen before their last word and in their context; private ones come last.

    Others are in one fixed order (bucket, context, word), in which they are asked for and answered.
    """

    def __init__(self, block: _Block, level: int, buckets: int, hot: np.ndarray) -> None:
        local, c = block.local, block.c
        self.context = np.full(len(local), -1, dtype=np.int32)
        valid = np.zeros(len(local), bool)
        if level == 2:
            self.context[1:] = local[:-1]
            self.context[block.first] = local[-1]  # every text's last token is the end
            valid = block.count[self.context] > 0
            self.ids, self.ids_count, alone = block.number.view(np.uint64), block.count, np.zeros(len(block.number), bool)
        else:
            last = block.grams
            self.context[1:] = last.code[:-1]
            valid[1:] = c[:-1] > 0  # the run that ends before a token is its context
            valid &= block.place >= level - 2
            self.ids, self.ids_count, alone = X.mix(last.id * _CHAIN + last.word.astype(np.uint64)), last.count, last.private
        self.valid = valid
        known = np.flatnonzero(valid & (c > 0))
        n = max(len(block.number), 1)
        key, inverse, one = X.distinct(self.context[known] * np.int64(n) + local[known])
        context = key // n
        word = block.number[key - context * n]
        by, bucket = self._order(context, word, alone, level, buckets, hot)
        one = known[one[by]]
        place = np.empty(len(by), dtype=np.int32)
        place[by] = np.arange(len(by), dtype=np.int32)
        self.code = np.full(len(local), -1, dtype=np.int32)  # of every token's run
        self.code[known] = place[inverse]
        self.bucket, self.asked = bucket, int(np.searchsorted(bucket, buckets))
        self.at, self.word = context[by], word[by]
        self.id = self.ids[self.at]
        self.base, self.over = c[one], block.over[one]
        self.times = np.bincount(self.code[known[block.train[known]]], minlength=len(by))
        # contexts before words unseen at the shorter context, whose weights are needed though no run is asked
        lone = np.unique(self.context[valid & (c == 0)])
        lone = np.unique(self.ids[lone[~alone[lone]]]) if len(lone) else np.zeros(0, np.uint64)
        self.lone = lone[~np.isin(lone, hot)]
        self.lone_bucket = _bucket(X.mix(self.lone) if level == 2 else self.lone, buckets)
        self.level, self.hot = level, hot

    def _order(self, context: np.ndarray, word: np.ndarray, alone: np.ndarray, level: int, buckets: int, hot: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Runs, which come by context, ordered by bucket and context, and their buckets; private ones go last."""
        spread = lambda ids: X.mix(ids) if level == 2 else ids
        runs, split = np.arange(len(context)), np.zeros(len(context), np.int64)
        if len(hot):
            at = np.flatnonzero(np.isin(self.ids, hot)[context])
            ids = self.ids[context[at]]
            split[at] = 1 + _bucket(X.mix(spread(ids) * np.uint64(3) + word[at].astype(np.uint64)), buckets)
            runs[at] = at[np.lexsort((split[at], context[at]))]
            context, split = context[runs], split[runs]
        start = np.ones(len(context), bool)
        start[1:] = (context[1:] != context[:-1]) | (split[1:] != split[:-1])
        heads = np.flatnonzero(start)
        own, ids = context[heads], self.ids[context[heads]]
        bucket = np.where(split[heads] > 0, split[heads] - 1, _bucket(spread(ids), buckets))
        bucket = np.where(alone[own], buckets, bucket)
        if level == 2:
            group = np.lexsort((ids, bucket))
        else:  # hashes: their first bits order them
            width = np.uint64(int(buckets).bit_length())
            group = X.ascending((bucket.astype(np.uint64) << (np.uint64(64) - width)) | (ids >> width))
        size = np.diff(np.append(heads, len(context)))[group]
        by = np.repeat(heads[group] - (np.cumsum(size) - size), size) + np.arange(len(context))
        return runs[by], np.repeat(bucket[group], size)

    def questions(self, block: int, buckets: int) -> list[tuple]:
        """kind 4: asked runs by context with their training counts here, and what their shorter runs' mass follows from;
        kind 8: counts of counts of the private ones."""
        rows = []
        cut = np.searchsorted(self.bucket, np.arange(buckets + 1))
        by = np.argsort(self.lone_bucket, kind="stable")
        lone, ends = self.lone[by], np.searchsorted(self.lone_bucket[by], np.arange(buckets + 1))
        for k in range(buckets):
            a, z = cut[k], cut[k + 1]
            alone = lone[ends[k] : ends[k + 1]]
            if z > a or len(alone):
                ids = self.id[a:z]
                heads = np.flatnonzero(np.concatenate(([z > a], ids[1:] != ids[:-1])))
                over = squeeze(self.over[a:z][heads]) if self.level > 2 else None
                rows.append((4, k, block, _dump(squeeze(_gaps(ids[heads])), squeeze(np.diff(np.append(heads, z - a))), squeeze(self.word[a:z]), squeeze(self.times[a:z]), squeeze(self.base[a:z]), over, squeeze(_gaps(alone)))))
        n = _of_counts(self.times[self.asked :])
        if n.any():
            rows.append((8, block % buckets, block, _dump(n)))
        return rows

    def settle(self, answers: list[bytes], d: np.ndarray, hot_rare: np.ndarray, hot_known: np.ndarray) -> None:
        """Counts of all runs, and rare counts and known mass of the contexts that need them. ``d`` discounts the shorter runs."""
        got = [pickle.loads(a) for a in answers]
        code = np.concatenate([_longs(x[0]) for x in got] + [np.zeros(0, np.int64)])
        own = slice(self.asked, None)
        self.count = np.concatenate([code >> 1, self.times[own]])
        self.private = np.concatenate([(code & 1).astype(bool), np.ones(len(self.times) - self.asked, bool)])
        ids, rare = [*(_ungap(x[1]) for x in got), self.hot], [*(_longs(x[2]).reshape(-1, KEPT) for x in got), hot_rare]
        known = [*(x[3] for x in got), hot_known]
        if self.asked < len(self.times):  # private contexts: all their runs are here
            context, row = np.unique(self.at[own], return_inverse=True)
            c, seen = self.times[own], self.times[own] > 0
            p = d[np.minimum(self.base[own], KEPT + 1)] * self.base[own] / self.over[own]
            few = seen & (c <= KEPT)
            ids.append(self.ids[context])
            rare.append(np.bincount(row[few] * KEPT + c[few] - 1, minlength=len(context) * KEPT).reshape(-1, KEPT))
            known.append(np.bincount(row[seen], p[seen], minlength=len(context)))
        ids = np.concatenate(ids)
        by = np.argsort(ids)
        at, self.there = X.find(ids[by], self.ids)
        there = by[at[self.there]]
        self.rare, self.known = np.concatenate(rare)[there], np.concatenate(known)[there]
        self.bare = np.zeros(len(self.ids), bool)  # contexts whose seen runs are scaled: nothing to discount
        self.bare[self.there] = self.rare.sum(axis=1) == 0

    def refine(self, p: np.ndarray, c: np.ndarray, d: np.ndarray) -> np.ndarray:
        """Probabilities of all tokens given this level's contexts, from those given the shorter ones."""
        factor, weight = np.ones(len(self.ids)), np.ones(len(self.ids))
        factor[self.there], weight[self.there] = backoff(d, self.ids_count[self.there].astype(np.float64), self.rare, self.known)
        on = np.flatnonzero(self.valid)
        h, k = self.context[on], c[on]
        out = p.copy()
        out[on] = np.where(k > 0, d[np.minimum(k, KEPT + 1)] * k / self.ids_count[h] * factor[h], weight[h] * p[on])
        return out


class _Block:
    """A block's tokens, with what is known of its runs of each length from the answers so far."""

    def __init__(self, load: bytes, words: list[bytes], unigrams: Unigrams, buckets: int) -> None:
        self.ids, self.out, size, rank, common = pickle.loads(load)
        self.size, self.local = _longs(size), _longs(common).astype(np.int32)[_longs(rank)]
        loads = [pickle.loads(x) for x in words]  # words are in hash order, so by bucket
        counts = [_longs(x[2]) for x in loads]
        self.number = np.concatenate([_numbers(_ungap(x[1]).view(np.int64), c, x[0], buckets) for x, c in zip(loads, counts, strict=True)])
        self.count = np.concatenate(counts)
        self.begin = np.concatenate(([0], np.cumsum(self.size)))
        self.first = self.begin[:-1]
        self.place = np.arange(len(self.local), dtype=np.int32) - np.repeat(self.first.astype(np.int32), self.size)
        self.train = np.repeat(~self.out, self.size)
        self.c = self.count[self.local]  # training count of each token's run of the level reached
        self.over = np.full(len(self.local), unigrams.over, dtype=np.int64)
        self.grams: _Grams | None = None

    def rise(self, level: int, buckets: int, hot: np.ndarray) -> _Grams:
        self.grams = _Grams(self, level, buckets, hot)
        return self.grams

    def settle(self, answers: list[bytes], d: np.ndarray, hot_rare: np.ndarray, hot_known: np.ndarray) -> None:
        """Take the answers of the level: counts and divisors of each token's run."""
        g = self.grams
        g.settle(answers, d, hot_rare, hot_known)
        on = np.flatnonzero(g.valid)
        h = g.context[on]
        self.over[on] = g.ids_count[h] + g.bare[h]
        self.c = np.append(g.count, 0)[g.code]  # code -1 is the zero at the end


def _count_runs(level: int, buckets: int, total: int, over: int, d: np.ndarray, hot: np.ndarray):
    """kind 5: counts in the order asked (with a mark where no other block asks), then rare counts and known mass of the
    contexts whose weight or scale the block needs. kind 6: counts of counts and the most frequent runs as contexts of
    the next level. kind 7: rare counts and mass of hot contexts, whose runs lie in many buckets."""

    def answer(bucket: int, blocks: list[int], loads: list[bytes]) -> list[tuple]:
        ids, words, times, base, divide, lone = [], [], [], [], [], []
        private = np.zeros(KEPT + 2, dtype=np.int64)
        asking = []
        for block, raw in zip(blocks, loads, strict=True):
            x = pickle.loads(raw)
            if len(x) == 1:
                private += x[0]
                continue
            heads, runs, wn, t, c, o, alone = x
            runs = _longs(runs)
            asking.append(block)
            ids.append(np.repeat(_ungap(heads), runs))
            words.append(_longs(wn))
            times.append(_longs(t))
            base.append(_longs(c))
            if level > 2:
                divide.append(np.repeat(_longs(o), runs))
            lone.append(_ungap(alone))
        loads.clear()
        size = [len(x) for x in ids]
        v = np.concatenate([*ids, np.zeros(0, np.uint64)])
        w = np.concatenate([*words, np.zeros(0, np.int64)])
        del ids, words
        key = X.mix(v * _CHAIN + w.astype(np.uint64))  # the runs as contexts of the next level
        key, where, one = X.distinct(key)
        v = v[one]
        c = np.bincount(where, np.concatenate([*times, np.zeros(0, np.int64)]), minlength=len(v)).astype(np.int64)
        alone_asked = np.bincount(where, minlength=len(v)) == 1
        b = np.concatenate([*base, np.zeros(0, np.int64)])[one]
        p = d[np.minimum(b, KEPT + 1)] * b / (np.concatenate(divide)[one] if divide else over)
        del times, base, divide, one, b, w
        contexts, row, _ = X.distinct(v)
        seen = c > 0
        known = np.bincount(row[seen], p[seen], minlength=len(contexts))
        few = seen & (c <= KEPT)
        rare = np.bincount(row[few] * KEPT + c[few] - 1, minlength=len(contexts) * KEPT).reshape(-1, KEPT)
        bare = rare.sum(axis=1) == 0
        mark = 2 * c + alone_asked
        is_hot = np.isin(contexts, hot)
        rows, at = [], 0
        for block, n, alone in zip(asking, size, lone, strict=True):
            mine = where[at : at + n]
            at += n
            wanted = np.zeros(len(contexts), bool)
            wanted[row[mine[(c[mine] == 0) | bare[row[mine]]]]] = True
            wanted[np.searchsorted(contexts, alone)] = True
            open_ = np.flatnonzero(wanted & ~is_hot)
            rows.append((5, bucket, block, _dump(squeeze(mark[mine]), squeeze(_gaps(contexts[open_])), squeeze(rare[open_].reshape(-1)), known[open_])))
        top = np.flatnonzero(c * 4 * buckets > total)
        rows.append((6, bucket, 0, _dump(_of_counts(c) + private, key[top])))
        own = np.flatnonzero(is_hot)
        if len(own):
            rows.append((7, bucket, 0, _dump(contexts[own], rare[own], known[own])))
        return rows

    def run(batches):
        yield from _per_bucket(batches, answer)

    return run


class Level:
    """What tasks need of a finished level: its discounts, and its hot contexts with their totals."""

    def __init__(self, hot: np.ndarray, d: np.ndarray, rare: np.ndarray, known: np.ndarray) -> None:
        self.hot, self.d, self.rare, self.known = hot, d, rare, known


def _raised(unigrams: Unigrams, levels: list[Level], buckets: int, rows: Iterator[pa.RecordBatch], scored: bool = False) -> Iterator[tuple[int, _Block, np.ndarray | None]]:
    """Rows of (block, kind, bucket, load), sorted so: each block's tokens, then its answers level by level. Gives the
    block with all finished levels settled, and its tokens' probabilities if ``scored``."""

    def build(block: int, parts: dict[int, list[bytes]]) -> tuple[int, _Block, np.ndarray | None]:
        b = _Block(parts[0][0], parts[2], unigrams, buckets)
        p = unigrams.p(b.c) if scored else None
        d = unigrams.d
        for m, level in enumerate(levels, 2):
            b.rise(m, buckets, level.hot)
            b.settle(parts.get(10 * m, []), d, level.rare, level.known)
            if scored:
                p = b.grams.refine(p, b.c, level.d)
            d = level.d
        return block, b, p

    at, parts = None, {}
    for batch in rows:
        for block, kind, load in zip(batch.column("block").to_pylist(), batch.column("kind").to_pylist(), batch.column("load"), strict=True):
            if block != at:
                if parts:
                    yield build(at, parts)
                at, parts = block, {}
            parts.setdefault(kind, []).append(load.as_py())
    if parts:
        yield build(at, parts)
    X.release()


def _ask(unigrams: Unigrams, levels: list[Level], buckets: int, hot: np.ndarray):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for number, b, _ in _raised(unigrams, levels, buckets, batches):
            rows = b.rise(len(levels) + 2, buckets, hot).questions(number, buckets)
            if rows:
                yield _rows(rows)

    return run


_SCORES = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"


def _evaluate(unigrams: Unigrams, levels: list[Level], buckets: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for _, b, p in _raised(unigrams, levels, buckets, batches, True):
            count = b.count[b.local]
            base = np.log10((count + 1) / (unigrams.total + 1 * (unigrams.words + 1)))
            yield pa.RecordBatch.from_arrays(
                [
                    pa.array(b.ids, pa.int64()),
                    pa.array(b.out),
                    pa.array(b.size),
                    pa.array(np.add.reduceat((count > 0).astype(np.int64), b.first)),
                    pa.array(np.full(len(b.size), unigrams.total, dtype=np.int64)),
                    pa.array(np.add.reduceat(base, b.first)),
                    pa.array(np.add.reduceat(np.log10(p), b.first)),
                ],
                names=[c.split()[0] for c in _SCORES.split(", ")],
            )

    return run


class KatzModel:
    """Fitted totals, and the written tables of word and run counts that the scores are read from."""

    def __init__(self, blocks: DataFrame, words: DataFrame, unigrams: Unigrams, buckets: int) -> None:
        self.blocks, self.words, self.unigrams, self.buckets = blocks, words, unigrams, buckets
        self.levels: list[Level] = []
        self.counts: list[DataFrame] = []

    def by_block(self) -> DataFrame:
        """Every block's tokens and the answers it got, side by side."""
        rows = self.blocks.filter("kind = 0").unionByName(self.words.filter("kind = 2"))
        for m, table in enumerate(self.counts, 2):
            rows = rows.unionByName(table.filter("kind = 5").withColumn("kind", F.lit(10 * m)))
        return rows.repartition(self.buckets, "block").sortWithinPartitions("block", "kind", "bucket").select("block", "kind", "load")

    def scores(self) -> DataFrame:
        return self.by_block().mapInArrow(_evaluate(self.unigrams, self.levels, self.buckets), _SCORES)


def _totals(table: DataFrame, kind: int) -> list[tuple]:
    """The packed totals of one kind: a few numbers per bucket."""
    return [pickle.loads(bytes(r["load"])) for r in table.filter(F.col("kind") == kind).select("load").toLocalIterator()]


def fit(df: DataFrame, block_bytes: int = BLOCK_BYTES, bucket_bytes: int = BUCKET_BYTES, order: int = ORDER) -> KatzModel:
    """Count and fit on the rows of ``df`` (doc_id, held_out, text) that are not held out; all rows can be scored."""
    if order < 1:
        raise ValueError(f"order is {order}; it must be at least 1")
    spark = use_library(df.sparkSession)
    buckets = parts_for(text_bytes(df), bucket_bytes)
    blocks = written(df.select("doc_id", "held_out", "text").mapInArrow(_blocks(buckets, block_bytes), _MESSAGE), "katz-blocks", by="kind")
    deal = lambda t: t.repartition(buckets, "bucket").sortWithinPartitions("bucket", "block").select("kind", "bucket", "block", "load")
    words = written(deal(blocks.filter("kind = 1")).mapInArrow(_count_words(buckets), _MESSAGE), "katz-words", by="kind")
    drop_part(blocks, "kind=1")
    free_shuffles(spark)
    totals = _totals(words, 3)
    total, distinct = sum(t[0] for t in totals), sum(t[1] for t in totals)
    unigrams = Unigrams(total, distinct, sum((t[2] for t in totals), np.zeros(KEPT + 2, dtype=np.int64)))
    model = KatzModel(blocks, words, unigrams, buckets)
    # contexts with more than a quarter of a bucket's share: at most four per bucket
    hot = np.array([n for t in totals for n, c in zip(t[3], t[4], strict=True) if c * 4 * buckets > total and n > 0], dtype=np.uint64)
    d = unigrams.d
    for level in range(2, order + 1):
        hot = np.unique(hot)
        asked = model.by_block().mapInArrow(_ask(unigrams, model.levels, buckets, hot), _MESSAGE)
        counts = written(deal(asked).mapInArrow(_count_runs(level, buckets, total, unigrams.over, d, hot), _MESSAGE), f"katz-runs-{level}", by="kind")
        del asked
        free_shuffles(spark)
        ends = _totals(counts, 6)
        d = discounts(sum((t[0] for t in ends), np.zeros(KEPT + 2, dtype=np.int64)))
        rare, known = np.zeros((len(hot), KEPT), dtype=np.int64), np.zeros(len(hot))
        for own, r, k in _totals(counts, 7):
            at = np.searchsorted(hot, own)
            np.add.at(rare, at, r)
            np.add.at(known, at, k)
        model.levels.append(Level(hot, d, rare, known))
        model.counts.append(counts)
        hot = np.concatenate([*(t[1] for t in ends), np.zeros(0, np.uint64)])
    return model


def op2_katz(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All documents, learned from those whose id's crc32 does not leave 2 modulo 7."""
    docs = documents(spark, sf_dir)
    return fit(docs.select("doc_id", (F.coalesce(crc_mod("doc_id", 7), F.lit(-1)) == 2).alias("held_out"), "text")).scores()


QUERIES = {"op2_katz": op2_katz}
ORACLES: dict[str, str] = {}
