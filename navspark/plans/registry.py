"""All queries of the engine and their SQL twins, by key."""

from __future__ import annotations

from navspark.plans import base, corpus_queries, general_queries, perception_queries, policy_queries

__all__ = ["corpus_queries", "general_queries", "perception_queries", "policy_queries"]


def queries():
    return dict(base.QUERIES)


def oracle_sql():
    return dict(base.ORACLE)
