"""Array operations over Arrow text batches: words, hashes, windows. Everything is whole-text and per batch."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

U = np.uint64
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
#: Also breaks at ASCII signs: words of letters, digits and all beyond ASCII.
SIGNS = np.array([i < 128 and not chr(i).isalnum() for i in range(256)])
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
_BYTE_CODE = np.random.Generator(np.random.PCG64(20240917)).integers(0, 1 << 64, 256, dtype=np.uint64)
_powers: list[np.ndarray] = []


def mix(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads every input bit over 64 output bits."""
    x = x.astype(U, copy=True)
    x ^= x >> U(30)
    x *= U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse modulo 2^64, at least n + 1 of them."""
    if not _powers or len(_powers[0]) < n + 1:
        size = max(n + 1, 1 << 16)
        up, down = np.full(size, _BASE, dtype=U), np.full(size, _INVERSE, dtype=U)
        up[0] = down[0] = 1
        _powers[:] = [np.cumprod(up, dtype=U), np.cumprod(down, dtype=U)]
    return _powers[0], _powers[1]


def slices(batch: pa.RecordBatch, column: str = "text", limit: int = 2 << 20) -> Iterator[pa.RecordBatch]:
    """The batch in runs of rows whose text stays near ``limit`` bytes (one row at least), so arrays stay small."""
    n = batch.num_rows
    if not n:
        return
    size = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64))
    at = 0
    while at < n:
        base = size[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(size, base + limit, side="right")))
        yield batch.slice(at, to - at)
        at = to


def release() -> None:
    """Give freed memory back to the system: a reused worker must not keep the peak of the task before it."""
    import ctypes

    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc only
    if trim is not None:
        trim(0)


def column_bytes(array: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """All texts' UTF-8 bytes end to end, and the offsets of each; null is empty."""
    if isinstance(array, pa.ChunkedArray):
        array = array.combine_chunks()
    array = pc.fill_null(array, b"" if pa.types.is_binary(array.type) else "")
    wide = pa.types.is_large_string(array.type) or pa.types.is_large_binary(array.type)
    _, offsets, data = array.buffers()
    off = np.frombuffer(offsets, dtype=np.int64 if wide else np.int32)[array.offset : array.offset + len(array) + 1].astype(np.int64)
    if data is None or off[-1] == off[0]:
        return np.zeros(0, dtype=np.uint8), off - off[0]
    return np.frombuffer(data, dtype=np.uint8)[off[0] : off[-1]], off - off[0]


def word_spans(data: np.ndarray, off: np.ndarray, breaks: np.ndarray = _SPACE) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words `[^\\x20\\x09-\\x0D]+`, and per text the index of its first word (n + 1 entries)."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(off), np.int64)
    word = ~breaks[data]
    before = np.empty(len(data) + 1, dtype=bool)
    before[0] = False
    before[1:] = word
    edge = off[(off > 0) & (off < len(data))]
    left = before[:-1].copy()
    left[edge] = False
    starts = np.flatnonzero(word & ~left)
    right = np.empty(len(data), dtype=bool)
    right[:-1] = word[1:]
    right[-1] = False
    right[edge - 1] = False
    ends = np.flatnonzero(word & ~right) + 1
    return starts, ends, np.searchsorted(starts, off)


def prefix_hash(data: np.ndarray, lower: bool = False) -> np.ndarray:
    """Running sum from which the hash of any span follows; entry i covers the bytes before i."""
    up, _ = powers(len(data))
    out = np.empty(len(data) + 1, dtype=U)
    out[0] = 0
    np.cumsum(_BYTE_CODE[_LOWER[data] if lower else data] * up[: len(data)], out=out[1:])
    return out


def span_hash(prefix: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of spans; equal bytes give equal hashes wherever they stand."""
    _, down = powers(len(prefix))
    return mix((prefix[ends] - prefix[starts]) * down[starts] + (ends - starts).astype(U) * U(0xD6E8FEB86659FD93))


def word_hashes(data: np.ndarray, off: np.ndarray, lower: bool = True, breaks: np.ndarray = _SPACE) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every word in order, and per text the index of its first word."""
    starts, ends, first = word_spans(data, off, breaks)
    if not len(starts):
        return np.zeros(0, U), first
    return span_hash(prefix_hash(data, lower), starts, ends), first


def shingles(words: np.ndarray, first: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all k-word runs inside each text; a text with 1..k-1 words has one run, its whole sequence.

    Returns the hashes and per text the index of its first (n + 1 entries); runs are not yet distinct.
    """
    n = np.diff(first)
    count = np.where(n == 0, 0, np.maximum(n - k + 1, 1))
    begin = np.concatenate(([0], np.cumsum(count)))
    if not begin[-1]:
        return np.zeros(0, U), begin
    at = np.arange(begin[-1]) - np.repeat(begin[:-1], count) + np.repeat(first[:-1], count)
    stop = np.repeat(first[1:], count)
    h = np.full(len(at), 0x632BE59BD9B4E019, dtype=U)
    for j in range(k):
        inside = at + j < stop
        w = words[np.where(inside, at + j, 0)]
        h = np.where(inside, mix(h * U(0x9FB21C651E98DF25) + w), h)
    return h, begin


def distinct_per_text(values: np.ndarray, begin: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct values of each text, end to end, with new bounds."""
    if not len(values):
        return values, np.zeros(len(begin), np.int64)
    parts = [np.unique(values[a:b]) for a, b in zip(begin[:-1], begin[1:], strict=True)]
    return np.concatenate(parts), np.concatenate(([0], np.cumsum([len(p) for p in parts])))


def minhash(values: np.ndarray, begin: np.ndarray, samples: int, seed: int = 11) -> np.ndarray:
    """MinHash table, one row per text and one column per sample; texts without values get all ones."""
    rng = np.random.Generator(np.random.PCG64(seed))
    a = rng.integers(0, 1 << 64, samples, dtype=np.uint64) | U(1)
    b = rng.integers(0, 1 << 64, samples, dtype=np.uint64)
    n = len(begin) - 1
    out = np.full((n, samples), np.iinfo(np.uint64).max, dtype=U)
    full = np.flatnonzero(np.diff(begin) > 0)
    if not len(full):
        return out
    base = (values >> U(32)) ^ values
    at = begin[full]
    for i in range(samples):
        x = base * a[i]
        x += b[i]
        x ^= x >> U(32)
        x *= a[samples - 1 - i]
        out[full, i] = np.minimum.reduceat(x, at)
    return out


def find(table: np.ndarray, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Positions of ``keys`` in a sorted table, and whether each is there."""
    if not len(table):
        return np.zeros(len(keys), np.int64), np.zeros(len(keys), bool)
    at = np.minimum(np.searchsorted(table, keys), len(table) - 1)
    return at, table[at] == keys


def ascending(key: np.ndarray) -> np.ndarray:
    """Positions that sort 64-bit keys: the position rides in each key's low bits, as plain sorts beat indirect ones."""
    bits = U(max(len(key), 1).bit_length())
    low = (U(1) << bits) - U(1)
    key = key.view(U)
    small = not len(key) or not int(key.max()) >> (64 - int(bits))
    packed = (key << bits if small else key & ~low) | np.arange(len(key), dtype=U)
    packed.sort()
    at = (packed & low).view(np.int64)
    if not small:
        s = key[at]
        if (s[1:] < s[:-1]).any():  # keys that differ in their low bits alone
            return np.argsort(key, kind="stable")
    return at


def distinct(key: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sorted distinct 64-bit keys (in unsigned order), the number of each entry's key, and one entry of each."""
    at = ascending(key)
    s = key[at]
    new = np.ones(len(s), bool)
    new[1:] = s[1:] != s[:-1]
    number = np.empty(len(s), dtype=np.int32)
    number[at] = np.cumsum(new, dtype=np.int32) - 1
    return s[new], number, at[new]


def sums_per_text(values: np.ndarray, begin: np.ndarray) -> np.ndarray:
    """Sum of each text's run of values; 0 for texts without any."""
    total = np.concatenate((np.zeros((1, *values.shape[1:]), dtype=np.float64), np.cumsum(values, axis=0, dtype=np.float64)))
    return total[begin[1:]] - total[begin[:-1]]
