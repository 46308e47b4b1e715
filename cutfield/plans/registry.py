"""All registered queries of the core library."""

from __future__ import annotations

from . import queries_extra, queries_more  # noqa: F401  each registers its queries
from .queries_core import QUERIES, SQL

__all__ = ["QUERIES", "SQL"]
