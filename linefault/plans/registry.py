"""All queries of the engine by name, and their SQL. Each takes (spark, sf_dir) and runs over whole tables."""

from __future__ import annotations

from . import clusters_queries, experiments_queries, faults_queries, features_queries, general_queries, tickets_queries
from .book import QUERIES, SQL

__all__ = ["QUERIES", "SQL", "clusters_queries", "experiments_queries", "faults_queries", "features_queries", "general_queries", "tickets_queries"]
