"""All queries of the engine by name, with their SQL."""

from __future__ import annotations

from importlib import import_module

MODULES = ("core", "compare", "relational", "runs")


def _modules():
    return [import_module(f"phasewise.queries.{m}") for m in MODULES]


def queries() -> dict:
    return {name: f for m in _modules() for name, f in m.Q.items()}


def oracle_sql() -> dict:
    return {name: sql for m in _modules() for name, sql in m.SQL.items()}


def flagship(spark, sf_dir: str):
    """Phase log of the chunked miner on ``events``, one long stream."""
    from .operators.engine import Settings
    from .operators.miner import mine_single_stream
    from .sources.tables import events_points

    return mine_single_stream(events_points(spark, sf_dir), Settings(k=3, outlier_phases=2, num=100)).phase_log
