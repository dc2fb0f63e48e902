"""Registered queries: name to a callable of (spark, sf_dir), and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from carepath.queries._registry import ORACLES, QUERIES


def queries():
    from carepath.queries import modelling, visits, workshop  # noqa: F401

    return dict(QUERIES)


def oracle_sql():
    queries()
    return dict(ORACLES)
