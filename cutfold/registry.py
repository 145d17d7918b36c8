"""All registered graph queries and their SQL counterparts."""

from __future__ import annotations

from cutfold.plans.queries import QUERIES, SQL, flagship

__all__ = ["QUERIES", "SQL", "flagship"]
