"""All registered queries of the view engine."""

from __future__ import annotations

from ctxviews.queries import ORACLE_SQL, QUERIES, contracts, delivery, measured, operators, plans, upkeep, views  # noqa: F401
