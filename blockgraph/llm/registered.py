"""What ``__spark_entry__`` adds if this subpackage is there."""

from __future__ import annotations

from .oracles import oracle_sql as _sql
from .queries import queries as _queries


def queries() -> dict:
    found = _queries()
    try_pipeline = _pipeline()
    return found | {"pipeline": try_pipeline.run}


def oracle_sql() -> dict[str, str]:
    sql = _pipeline().ORACLE_SQL
    return _sql() | ({"pipeline": sql} if sql else {})


def _pipeline():
    import corpus_pipeline

    return corpus_pipeline
