"""Every method as a query over the given tables, beside SQL that another engine can run."""

from __future__ import annotations

from . import evaluation, losses, relational, selection, streams, windows

MODULES = (windows, losses, selection, evaluation, relational, streams)


def queries() -> dict:
    return {k: f for m in MODULES for k, f in m.QUERIES.items()}


def oracles() -> dict:
    return {k: q for m in MODULES for k, q in m.ORACLES.items()}
