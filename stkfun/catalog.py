"""Queries of the library and their SQL."""

from __future__ import annotations

from stkfun.plans import workloads


def queries() -> dict:
    return {name: run for name, (run, _) in workloads.entries().items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for name, (_, sql) in workloads.entries().items() if sql}
