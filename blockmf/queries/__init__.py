"""Queries for the driver: name -> function(spark, sf_dir), and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

from blockmf.queries import measures, models, plans, relational, streams, workloads

MODULES = (models, plans, measures, relational, streams, workloads)


def all_queries() -> dict:
    return {k: v for m in MODULES for k, v in m.QUERIES.items()}


def all_sql() -> dict:
    return {k: v for m in MODULES for k, v in m.SQL.items()}
