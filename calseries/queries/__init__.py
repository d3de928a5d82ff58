"""The registered queries, one module per group, and their DuckDB texts."""

from __future__ import annotations

from . import apps, model, more, plans, relational, windows

GROUPS = (model, windows, apps, plans, relational, more)
QUERIES = {k: v for g in GROUPS for k, v in g.QUERIES.items()}
ORACLES = {k: v for g in GROUPS for k, v in g.ORACLES.items()}
