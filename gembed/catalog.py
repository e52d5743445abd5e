"""Registry of the engine's queries and of the SQL that checks them."""

from __future__ import annotations

from .operators import experiments
from .queries import graph_queries, model_queries, operator_queries, training_queries  # noqa: F401  (registration)
from .queries.base import QUERIES, SQL


def flagship(spark, sf_dir):
    return experiments.flagship(spark, sf_dir)


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict:
    return dict(SQL)
