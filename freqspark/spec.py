"""What is asked of a frequent-item query, and the threshold it implies."""

from __future__ import annotations

import warnings
from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F

_CHOICES = {
    "setting": ("verified", "one_pass"),
    "kernel": ("batched", "scalar", "exact_local", "misra_gries"),
    "merge": ("flat", "tree"),
    "floor_rule": ("spare_zero", "stored_min", "tight"),
    "nulls": ("skip", "item"),
    "tie": ("item", "oldest"),
}


def threshold_count(n: int, k: int) -> int:
    """Least count that is more than n / k, in integers."""
    return n // k + 1


def threshold_col(n: str, k: int) -> Column:
    """The same as a column over the long column ``n``: integer division, never a rounded quotient."""
    return F.expr(f"({n} div {k}) + 1")


@dataclass(frozen=True)
class FrequentSpec:
    """k sets the threshold (count > n / k); ``counters`` of a summary may exceed it."""

    k: int
    counters: int | None = None
    setting: str = "verified"
    kernel: str = "batched"
    levels: int = 1
    group: int = 8
    fan_in: int | None = None
    merge: str = "flat"
    floor_rule: str = "spare_zero"
    nulls: str = "skip"
    tie: str = "item"
    weight: str | None = None
    blocks_per_core: int | None = None
    by: tuple[str, ...] = field(default_factory=tuple)

    def __post_init__(self) -> None:
        if self.k < 2:
            raise ValueError(f"k is {self.k}; it must be at least 2")
        if self.counters is not None and self.counters < self.k:
            raise ValueError(f"counters is {self.counters}; it must be at least k = {self.k}")
        if self.levels not in (1, 2):
            raise ValueError(f"levels is {self.levels}; it must be 1 or 2")
        if self.group < 1:
            raise ValueError(f"group is {self.group}; it must be at least 1")
        if self.fan_in is not None and self.fan_in < 2:
            raise ValueError(f"fan_in is {self.fan_in}; it must be at least 2")
        if self.blocks_per_core is not None and self.blocks_per_core < 1:
            raise ValueError(f"blocks_per_core is {self.blocks_per_core}; it must be at least 1")
        for name, allowed in _CHOICES.items():
            if getattr(self, name) not in allowed:
                raise ValueError(f"{name} is {getattr(self, name)!r}; it must be one of {', '.join(allowed)}")

    @property
    def size(self) -> int:
        return self.counters or self.k

    def validate(self, n: int) -> int:
        """The threshold for n items; k above n is allowed and means every item."""
        if self.k > n:
            warnings.warn(f"k = {self.k} exceeds the {n} items: the threshold is 1", stacklevel=2)
        return threshold_count(n, self.k)
