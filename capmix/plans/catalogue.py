"""The registered queries of the caption-curation engine, with their SQL."""

from __future__ import annotations

from . import caption_queries, model_queries, pool_queries, prep_queries, relational_queries, stream_queries

MODULES = (pool_queries, model_queries, caption_queries, prep_queries, relational_queries, stream_queries)


def queries():
    return {k: v for m in MODULES for k, v in m.queries().items()}


def oracle_sql():
    return {k: v for m in MODULES for k, v in m.oracle_sql().items()}
