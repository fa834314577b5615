"""Registered queries of the semantic operators and their SQL twins."""

from . import directives, measures, relational, semantic, streams, surface, workloads  # noqa: F401
from .registry import QUERIES, SQL

FLAGSHIP = "d01_chunked_extract"


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict:
    return dict(SQL)
