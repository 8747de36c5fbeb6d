"""All queries of the engine proper, by name, and their DuckDB counterparts."""

from __future__ import annotations

from fadegossip import experiments, methods, operators
from fadegossip.streaming import queries as streams


def queries() -> dict:
    return methods.QUERIES | experiments.QUERIES | streams.QUERIES | operators.QUERIES


def oracles() -> dict[str, str]:
    return methods.ORACLES | experiments.ORACLES | streams.ORACLES | operators.ORACLES
