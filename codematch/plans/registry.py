"""Queries of the library itself and their DuckDB SQL."""

from __future__ import annotations


def _modules():
    from codematch.plans import methods, ops, workloads

    return [methods, workloads, ops]


def queries() -> dict:
    out: dict = {}
    for m in _modules():
        out |= m.Q
    return out


def oracle_sql() -> dict:
    out: dict = {}
    for m in _modules():
        out |= m.SQL
    return out
