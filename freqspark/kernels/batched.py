"""Batch-at-a-time kernel: count rows exactly in large batches, then merge each into the running summary.

A batch that is counted exactly has floor 0, so merging it leaves the bound as it is and adds no error of its own. The
running summary is a pair of Arrow columns per counter: what it has above the floor, and how much of that may be too much.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa

from .scalar import Summary, _order

GATHERED = 1 << 19  # rows counted at once, whatever the size of the batches that arrive


def cut(counters: dict, k: int, floor: int, rule: str) -> tuple[dict, int]:
    """The k largest by (estimate, least item) and the floor that follows; ``floor`` is what the inputs' floors sum to.

    An under-full result keeps that sum: its inputs may have cancelled items without a counter to show for it.
    """
    if len(counters) <= k:
        if rule == "tight":
            return counters, floor
        least = min((c[0] for c in counters.values()), default=floor)
        return counters, least if len(counters) == k or rule == "stored_min" else floor
    ranked = sorted(counters.items(), key=lambda x: (-x[1][0], _order(x[0])))
    kept = dict(ranked[:k])
    if rule == "tight":
        return kept, max(floor, ranked[k][1][0])
    return kept, ranked[k - 1][1][0]


def merge_pair(a: Summary, b: Summary, k: int, rule: str = "spare_zero") -> Summary:
    """Both summaries' counters in one: an item that one side lacks may have had up to that side's floor there."""
    out = {x: [est + b.floor, err + b.floor] for x, (est, err) in a.counters.items()}
    for x, (est, err) in b.counters.items():
        if x in a.counters:
            out[x] = [a.counters[x][0] + est, a.counters[x][1] + err]
        else:
            out[x] = [est + a.floor, err + a.floor]
    counters, floor = cut(out, k, a.floor + b.floor, rule)
    return Summary(a.n + b.n, floor, counters)


class Columns:
    """Items as one or more columns (the fields of a struct), so that Arrow can group and sort them."""

    def __init__(self, kind: pa.DataType) -> None:
        self.kind = kind
        self.names = [f"i{j}" for j in range(kind.num_fields)] if pa.types.is_struct(kind) else ["i0"]

    def split(self, items: pa.Array) -> list[pa.Array]:
        return items.flatten() if pa.types.is_struct(self.kind) else [items]

    def join(self, table: pa.Table) -> pa.Array:
        parts = [table.column(c).combine_chunks() for c in self.names]
        if pa.types.is_struct(self.kind):
            return pa.StructArray.from_arrays(parts, fields=list(self.kind))
        return parts[0]


class ArrowSummary:
    """A summary in Arrow columns: ``above`` is the estimate less the floor, ``slack`` the error less the floor."""

    def __init__(self, kind: pa.DataType, k: int) -> None:
        self.items, self.k, self.n, self.floor = Columns(kind), k, 0, 0
        self.table: pa.Table | None = None

    def add(self, items: list[pa.Array], weights: list[pa.Array] | None) -> None:
        columns = [pa.chunked_array(c) for c in zip(*(self.items.split(i) for i in items), strict=True)]
        rows = pa.table(columns, names=self.items.names)
        if weights is None:
            counted = rows.group_by(self.items.names, use_threads=False).aggregate([([], "count_all")]).rename_columns([*self.items.names, "above"])
            self.n += rows.num_rows
        else:
            rows = rows.append_column("w", pa.chunked_array(weights))
            counted = rows.group_by(self.items.names, use_threads=False).aggregate([("w", "sum")]).rename_columns([*self.items.names, "above"])
            counted = counted.filter(np.nan_to_num(counted.column("above").to_numpy()) > 0)
            self.n += int(np.sum(counted.column("above").to_numpy(), dtype=np.int64))
        counted = counted.append_column("slack", pa.array(np.zeros(counted.num_rows, np.int64)))
        if self.table is not None:
            both = pa.concat_tables([self.table, counted])
            counted = both.group_by(self.items.names, use_threads=False).aggregate([("above", "sum"), ("slack", "sum")]).rename_columns(self.table.column_names)
        self.table = counted
        if counted.num_rows > 4 * self.k:
            self.cut()

    def cut(self) -> None:
        """Keep the k largest, ties by the least item; the floor rises to the largest that goes."""
        if self.table is None or self.table.num_rows <= self.k:
            return
        above = self.table.column("above").to_numpy()
        at = len(above) - self.k
        parted = np.partition(above, (at - 1, at))
        kth, following = int(parted[at]), int(parted[at - 1])
        sure, tied = np.flatnonzero(above > kth), np.flatnonzero(above == kth)
        room = self.k - len(sure)
        if len(tied) > room:
            tied = tied[_least(self.table.select(self.items.names).take(tied), self.items.names, room)]
        kept = self.table.take(np.concatenate([sure, tied]))
        self.floor += following
        less = lambda c: pa.array(kept.column(c).to_numpy() - following)
        self.table = pa.table([*(kept.column(c) for c in self.items.names), less("above"), less("slack")], names=self.table.column_names)

    def columns(self) -> tuple[pa.Array, np.ndarray, np.ndarray]:
        """Items, estimates and errors of the k counters."""
        self.cut()
        if self.table is None:
            return pa.array([], self.items.kind), np.zeros(0, np.int64), np.zeros(0, np.int64)
        return self.items.join(self.table), self.table.column("above").to_numpy() + self.floor, self.table.column("slack").to_numpy() + self.floor


def _least(table: pa.Table, names: list[str], room: int) -> np.ndarray:
    import pyarrow.compute as pc

    return pc.sort_indices(table, sort_keys=[(c, "ascending") for c in names], null_placement="at_start").to_numpy()[:room]


def arrow_kernel(batches: Iterable[tuple[pa.Array, pa.Array | None]], k: int, gathered: int = GATHERED) -> ArrowSummary | None:
    """Summary of all batches (items, weights or None); None without any batch."""
    s: ArrowSummary | None = None
    items: list[pa.Array] = []
    weights: list[pa.Array] = []
    held = 0
    for i, w in batches:
        s = s or ArrowSummary(i.type, k)
        items.append(i)
        if w is not None:
            weights.append(w)
        held += len(i)
        if held >= gathered:
            s.add(items, weights or None)
            items, weights, held = [], [], 0
    if held:
        s.add(items, weights or None)
    return s


def batched_kernel(batches: Iterable[tuple[pa.Array, pa.Array | None]], k: int, gathered: int = GATHERED) -> Summary:
    """The same as a plain summary."""
    s = arrow_kernel(batches, k, gathered)
    if s is None:
        return Summary()
    items, est, err = s.columns()
    return Summary(s.n, s.floor, {_value(x): [e, r] for x, e, r in zip(items.to_pylist(), est.tolist(), err.tolist(), strict=True)})


def _value(x):
    return tuple(x.values()) if isinstance(x, dict) else x


def fold(summaries: Iterator[Summary], k: int, rule: str = "spare_zero") -> Summary:
    """Many summaries into one inside a task, pair by pair."""
    out = None
    for s in summaries:
        out = s if out is None else merge_pair(out, s, k, rule)
    return out or Summary()
