"""Queries of the sampling engine, by name, and their DuckDB twins."""

from rangekeep.plans import operator_queries, product_queries, sampling_queries, stream_queries

FLAGSHIP = "flagship_monthly"
PARTS = (sampling_queries, product_queries, operator_queries, stream_queries)


def queries():
    return {n: f for part in PARTS for n, f in part.queries().items()}


def oracle_sql():
    return {n: q for part in PARTS for n, q in part.oracle_sql().items()}
