"""Workloads, registered queries and their SQL."""

from __future__ import annotations


def queries():
    from ..streaming import queries as _streams  # noqa: F401
    from . import kit, methods, pandas_kit, real  # noqa: F401
    from .registry import QUERIES

    return QUERIES


def oracles():
    queries()
    from .registry import ORACLES

    return ORACLES
