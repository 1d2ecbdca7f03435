"""All registered queries of the library."""

from __future__ import annotations


def load_all():
    """(queries, SQL twins) of every group."""
    from semcat.queries import analysis_queries, catalog_queries, profile_queries, stream_queries  # noqa: F401
    from semcat.queries.registry import QUERIES, SQL

    return dict(QUERIES), dict(SQL)
