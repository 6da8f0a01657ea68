"""All queries of the library by name, with their SQL."""

from __future__ import annotations

from recblock.plans import experiments, methods, surface


def queries():
    return methods.QUERIES | experiments.QUERIES | surface.QUERIES


def oracle_sql():
    return methods.SQL | experiments.SQL | surface.SQL
