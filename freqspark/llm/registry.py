"""Queries and reference SQL of this subpackage, for the driver's entry module."""

from __future__ import annotations

from importlib import import_module

_MODULES = (
    "packing", "katz", "language_id", "near_dedup", "mixing", "suffix_dedup", "weak_labels", "quality_rules", "toxicity", "syncmers",
)


def queries() -> dict:
    return {name: q for m in _MODULES for name, q in import_module(f"{__package__}.{m}").QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: q for m in _MODULES for name, q in import_module(f"{__package__}.{m}").ORACLES.items()}
