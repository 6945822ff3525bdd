"""One-item-at-a-time counter kernels over plain Python values."""

from __future__ import annotations

import heapq
from collections.abc import Iterable
from dataclasses import dataclass, field


@dataclass
class Summary:
    """``counters``: item -> [estimate, maximum error]; ``floor``: what an item without a counter may have at most."""

    n: int = 0
    floor: int = 0
    counters: dict = field(default_factory=dict)

    def rows(self) -> list[tuple]:
        return [(item, est, err) for item, (est, err) in self.counters.items()]


def _order(item) -> tuple:
    """Total order over values of one type, null first; the fields of a struct one by one."""
    if isinstance(item, tuple):
        return tuple(_order(x) for x in item)
    return (item is not None, item if item is not None else 0)


def scalar_kernel(items: Iterable, k: int, tie: str = "item", weights: Iterable[int] | None = None, weighted: bool = False) -> Summary:
    """Summary of exactly k counters where an unseen item takes over the smallest counter and inherits its estimate.

    Among equal smallest counters ``tie='item'`` gives up the least item and ``'oldest'`` the one that reached the
    estimate first. A heap holds one entry per counter and is corrected only when a counter must be given up, so an
    increment costs one dictionary access. With ``weighted`` the items come as pairs with their weights.
    """
    s = Summary()
    counters = s.counters
    reached: dict = {}
    heap: list[tuple] = []
    rank = (lambda item: _order(item)) if tie == "item" else (lambda item: reached[item])
    steps = items if weighted else ((x, 1) for x in items) if weights is None else zip(items, weights, strict=True)
    for now, (item, w) in enumerate(steps):
        if w == 0:
            continue
        s.n += w
        own = counters.get(item)
        if own is not None:
            own[0] += w
            reached[item] = now
            continue
        reached[item] = now
        if len(counters) < k:
            counters[item] = [w, 0]
        else:
            while True:
                est, _, _, oldest = heap[0]
                actual = counters[oldest][0]
                if actual == est:
                    break
                heapq.heapreplace(heap, (actual, rank(oldest), id(oldest), oldest))
            heapq.heappop(heap)
            del counters[oldest], reached[oldest]
            counters[item] = [est + w, est]
        heapq.heappush(heap, (counters[item][0], rank(item), id(item), item))
    s.floor = min((c[0] for c in counters.values()), default=0) if len(counters) >= k else 0
    return s


def misra_gries_kernel(items: Iterable, k: int) -> Summary:
    """At most k - 1 counters that never over-count; an unseen item without room takes one from every counter.

    ``floor`` is how often that happened: the most by which any estimate falls short.
    """
    s = Summary()
    counters: dict = {}
    for item in items:
        s.n += 1
        if item in counters:
            counters[item] += 1
        elif len(counters) < k - 1:
            counters[item] = 1
        else:
            s.floor += 1
            counters = {x: c - 1 for x, c in counters.items() if c > 1}
    s.counters = {x: [c, 0] for x, c in counters.items()}
    return s
