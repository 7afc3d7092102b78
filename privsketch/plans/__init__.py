"""Queries of the engine, registered beside the SQL that must give the same rows."""

from . import core, relational, streams, workloads
from .registry import QUERIES, SQL

__all__ = ["QUERIES", "SQL", "core", "relational", "streams", "workloads"]
