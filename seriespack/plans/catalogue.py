"""All queries and all their oracles."""

from __future__ import annotations

from . import experiments, oracles, oracles_more, queries, surfaces  # noqa: F401  (importing registers queries)
from .queries import QUERIES, entry  # noqa: F401

ORACLES = oracles.ORACLES | oracles_more.ORACLES
