"""How a module collects its queries."""

from __future__ import annotations


def registry() -> tuple[dict, dict, object]:
    queries: dict = {}
    oracles: dict[str, str] = {}

    def op(name: str, oracle: str | None = None):
        def put(f):
            queries[f"op_{name}"] = f
            if oracle:
                oracles[f"op_{name}"] = oracle
            return f

        return put

    return queries, oracles, op
