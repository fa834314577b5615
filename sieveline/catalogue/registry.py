"""Where queries register with their SQL twins."""

from __future__ import annotations

QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            SQL[f.__name__] = sql
        return f

    return add


#: SQL twins of token lists and buckets.
def toks(x: str) -> str:
    return f"list_filter(string_split_regex(coalesce({x}, ''), '[ \\n]+'), lambda t: t <> '')"


def slot(x: str) -> str:
    return f"(('0x' || substr(md5({x}), 1, 8))::BIGINT % 1000)"


def spans(types: dict[str, str], source: str = "documents", text: str = "text", doc: str = "doc_id") -> str:
    """SQL of distinct (doc_id, type, span) rows."""
    return " UNION ALL ".join(f"SELECT DISTINCT {doc} AS doc_id, '{t}' AS type, unnest(regexp_extract_all({text}, '{p}')) AS span FROM {source}" for t, p in types.items())
