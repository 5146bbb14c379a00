"""Loads every module that registers queries."""

from __future__ import annotations

from veilgrid import registry
from veilgrid.functions import scalars  # noqa: F401
from veilgrid.operators import relational  # noqa: F401
from veilgrid.plans import experiments, method_queries, surface_queries  # noqa: F401

QUERIES = registry.QUERIES
ORACLES = registry.ORACLES
