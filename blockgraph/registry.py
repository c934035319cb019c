"""Queries of the vector-search methods and their SQL."""

from __future__ import annotations


def _modules() -> list:
    from . import relational_queries, stream_queries, vector_queries

    return [vector_queries, relational_queries, stream_queries]


def flagship(spark, sf_dir):
    from . import vector_queries

    return vector_queries.curve_anns(spark, sf_dir)


def queries() -> dict:
    return {name: f for m in _modules() for name, f in m.Q.items()}


def oracle_sql() -> dict:
    return {name: s for m in _modules() for name, s in m.SQL.items()}
