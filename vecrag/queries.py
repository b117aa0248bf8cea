"""All registered queries of the engine and their SQL."""

from vecrag.plans import ann_queries, cost_queries, rag_queries, rel_queries, store_queries, workload_queries
from vecrag.plans.shared import QUERIES, SQL

MODULES = (ann_queries, cost_queries, rag_queries, rel_queries, store_queries, workload_queries)
__all__ = ["QUERIES", "SQL"]
