"""Queries and SQL of the training-data operators, as __spark_entry__.py adds them."""

from __future__ import annotations

from .oracles import oracle_sql
from .queries import queries

__all__ = ["oracle_sql", "queries"]
