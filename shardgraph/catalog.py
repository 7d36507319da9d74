"""Importing this module fills the registry."""

from shardgraph.plans import methods, relational, udf_queries, vector_queries, workloads  # noqa: F401
from shardgraph.registry import CORE

__all__ = ["CORE"]
