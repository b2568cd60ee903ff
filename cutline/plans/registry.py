"""All queries of the graph engine, and the SQL that checks them."""

from __future__ import annotations

from ..streaming import feed_queries
from . import catalog, graph_queries, index_queries, method_queries, relational_queries, workloads

_MODULES = (graph_queries, method_queries, index_queries, workloads, relational_queries, feed_queries)


def flagship(spark, sf_dir):
    """The front of four sweep-pierce cutters on the customer graph."""
    return method_queries.front_query("cust", "SP4")(spark, sf_dir)


def queries() -> dict:
    return dict(catalog.QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(catalog.ORACLES)
