"""Queries and oracle SQL of the engine's own operators."""

from __future__ import annotations

from ..operators import benchmark, construct, relational
from ..streaming import log
from . import workloads

_MODULES = (workloads, construct, benchmark, relational, log)


def queries() -> dict:
    return {k: v for m in _MODULES for k, v in m.QUERIES.items()}


def oracles() -> dict[str, str]:
    found = {k: v for m in (workloads, relational, log) for k, v in m.ORACLES.items()}
    return found | construct.oracles(workloads._BASE) | benchmark.oracles(workloads._BASE, workloads._LABELS)
