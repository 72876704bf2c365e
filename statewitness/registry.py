"""All registered queries of the audit engine, with their oracle SQL."""

from __future__ import annotations

from statewitness.plans import conformance_plans, extension_plans, measure_plans, operator_plans, replay_plans, stream_plans, trace_plans  # noqa: F401
from statewitness.plans.base import ORACLES, QUERIES


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict:
    return dict(ORACLES)
