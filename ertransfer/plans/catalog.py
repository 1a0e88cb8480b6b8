"""All queries of the engine and the DuckDB SQL of those that SQL can state."""

from __future__ import annotations

from ertransfer.plans import encoding_queries, engine_queries, experiment_queries, selection_queries, transfer_queries

_MODULES = (encoding_queries, transfer_queries, selection_queries, experiment_queries, engine_queries)


def queries() -> dict:
    out: dict = {}
    for module in _MODULES:
        out |= module.QUERIES
    return out


def oracle_sql() -> dict[str, str]:
    out: dict[str, str] = {}
    for module in _MODULES:
        out |= module.SQL
    return out
