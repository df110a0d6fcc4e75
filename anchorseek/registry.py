"""Queries over the given tables, with the DuckDB SQL that checks them."""

from __future__ import annotations

from . import experiments, workloads
from .operators import relational
from .streaming import queries as streams
from .workloads import flagship  # noqa: F401


def queries():
    return {**workloads.QUERIES, **experiments.QUERIES, **relational.QUERIES, **streams.QUERIES}


def oracle_sql():
    return {**workloads.SQL, **experiments.SQL, **relational.SQL, **streams.SQL}
