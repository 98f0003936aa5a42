"""Named queries of the engine over the given tables, each with its SQL twin where SQL can express it."""

from __future__ import annotations

from importlib import import_module

from .registry import ORACLES, QUERIES

MODULES = ("windows", "correlation", "scoring", "sampling", "blocks", "grading", "baselines", "experiments", "relational", "live")
for _m in MODULES:
    import_module(f"{__name__}.{_m}")


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
