"""Two-stage suffix sorting of one block of bytes, in array operations.

A suffix is of the lower type if it is smaller than its successor, else of the upper type. Only lower suffixes are
sorted directly, by eight bytes at a time to a bounded depth. Upper suffixes follow from a scan of the buckets in
order of their first byte: the predecessor of a suffix already in place, if it is upper, belongs next in its own bucket.
Order is exact to ``depth`` bytes; beyond that equal suffixes keep any order, which no common prefix up to ``depth``
depends on.
"""

from __future__ import annotations

import numpy as np


def words_at(data: np.ndarray) -> np.ndarray:
    """The eight bytes from every position as one big-endian number; past the end there are zeros."""
    wide = np.concatenate([data, np.zeros(8, np.uint8)]).astype(np.uint64)
    out = np.zeros(len(data), dtype=np.uint64)
    for i in range(8):
        out = (out << np.uint64(8)) | wide[i : i + len(data)]
    return out


def lower_type(data: np.ndarray) -> np.ndarray:
    """Which suffixes are smaller than their successors; runs of one byte follow the byte after the run."""
    n = len(data)
    out = np.zeros(n, dtype=bool)
    if n < 2:
        return out
    step = np.sign(data[1:].astype(np.int16) - data[:-1].astype(np.int16))  # of i against i + 1
    change = np.flatnonzero(step)
    following = np.searchsorted(change, np.arange(n - 1))
    has = following < len(change)
    out[:-1][has] = step[change[following[has]]] > 0
    return out


def sort_directly(where: np.ndarray, key8: np.ndarray, depth: int) -> np.ndarray:
    """Positions ordered by their first ``depth`` bytes: refine groups of ties eight bytes at a time."""
    n = len(key8)
    order = where[np.argsort(key8[where], kind="stable")]
    if len(order) < 2:
        return order
    new = np.empty(len(order), dtype=bool)
    new[0] = True
    new[1:] = key8[order[1:]] != key8[order[:-1]]
    group = np.cumsum(new)
    at = 8
    while at < depth:
        size = np.bincount(group)
        tied = np.flatnonzero(size[group] > 1)
        if not len(tied):
            break
        pos = order[tied] + at
        k = np.where(pos < n, key8[np.minimum(pos, n - 1)], np.uint64(0))
        again = np.lexsort((k, group[tied]))
        order[tied] = order[tied][again]
        k, g = k[again], group[tied]
        fresh = np.zeros(len(tied), dtype=bool)
        fresh[1:] = (g[1:] == g[:-1]) & (k[1:] != k[:-1])
        split = np.zeros(len(order), dtype=bool)
        split[tied] = fresh
        group = group + np.cumsum(split)
        at += 8
    return order


def suffix_array(data: np.ndarray, depth: int) -> np.ndarray:
    """All suffix positions in order, exact to ``depth`` bytes."""
    n = len(data)
    if not n:
        return np.zeros(0, np.int64)
    lower = lower_type(data)
    placed = sort_directly(np.flatnonzero(lower), words_at(data), depth)
    out = np.empty(n, dtype=np.int64)
    size = np.bincount(data, minlength=256)
    begin = np.concatenate(([0], np.cumsum(size)))
    n_lower = np.bincount(data[placed], minlength=256) if len(placed) else np.zeros(256, np.int64)
    lower_begin = np.concatenate(([0], np.cumsum(n_lower)))
    for c in np.flatnonzero(n_lower):  # lower suffixes fill their bucket's end
        out[begin[c + 1] - n_lower[c] : begin[c + 1]] = placed[lower_begin[c] : lower_begin[c + 1]]
    next_free = begin[:-1].copy()

    def induce(done: np.ndarray, own: int) -> np.ndarray:
        """Put the upper predecessors of ``done`` in their buckets; return those of bucket ``own`` itself."""
        before = done[done > 0] - 1
        before = before[~lower[before]]
        first = data[before]
        mine = before[first == own]
        others, bucket = before[first != own], first[first != own]
        if len(others):
            by = np.argsort(bucket, kind="stable")
            others, bucket = others[by], bucket[by]
            count = np.bincount(bucket, minlength=256)
            start = np.concatenate(([0], np.cumsum(count)))[:-1]
            out[next_free[bucket] + np.arange(len(others)) - start[bucket]] = others
            next_free[:] += count
        if len(mine):
            out[next_free[own] : next_free[own] + len(mine)] = mine
            next_free[own] += len(mine)
        return mine

    last = int(data[-1])  # the last suffix is upper (its successor is empty) and first in its bucket
    for c in np.flatnonzero(size):
        if c == last:
            # it precedes every other suffix of its bucket, also those placed from smaller buckets
            own = out[begin[c] : next_free[c]].copy()
            out[begin[c] + 1 : next_free[c] + 1] = own
            out[begin[c]] = n - 1
            next_free[c] += 1
        fresh = out[begin[c] : next_free[c]].copy()
        while len(fresh):  # runs of the bucket's own byte extend it from within
            fresh = induce(fresh, int(c))
        if n_lower[c]:
            induce(out[begin[c + 1] - n_lower[c] : begin[c + 1]].copy(), int(c))
    return out


def common_prefixes(data: np.ndarray, order: np.ndarray, depth: int) -> np.ndarray:
    """Common prefix of each entry with the one before it, counted up to ``depth`` bytes (first entry 0)."""
    n = len(data)
    out = np.zeros(len(order), dtype=np.int64)
    key8 = words_at(data)
    live = np.arange(1, len(order))
    at = 0
    while len(live) and at < depth:
        a, b = order[live] + at, order[live - 1] + at
        room = np.minimum(n - np.maximum(a, b), 8)
        x = np.where(room > 0, key8[np.minimum(a, n - 1)] ^ key8[np.minimum(b, n - 1)], np.uint64(1) << np.uint64(63))
        same = np.full(len(live), 8)
        for i in range(8):  # leading equal bytes
            same = np.where((same == 8) & ((x >> np.uint64(56 - 8 * i)) & np.uint64(255) != 0), i, same)
        same = np.minimum(same, np.maximum(room, 0))
        out[live] += same
        live = live[same == 8]
        at += 8
    return np.minimum(out, depth)
