"""The experiment workloads, each registered as a query with its SQL."""

from __future__ import annotations


def _registries():
    from pagelift.workloads import cells, functions, relational, scans, synthesis, tpch

    return (scans.REG, tpch.REG, relational.REG, functions.REG, synthesis.REG, cells.REG)


def queries() -> dict:
    return {name: f for r in _registries() for name, f in r.queries.items()}


def oracle_sql() -> dict:
    return {name: s for r in _registries() for name, s in r.sql.items()}
