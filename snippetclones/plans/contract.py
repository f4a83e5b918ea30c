"""All registered queries; importing the modules registers them."""

from . import clone_queries, corpus_queries, relational_queries, stream_queries, table_queries  # noqa: F401
from .registry import ORACLE, QUERIES

__all__ = ["ORACLE", "QUERIES"]
