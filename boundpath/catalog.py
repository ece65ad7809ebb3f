"""All queries of the path engine and their DuckDB oracles, gathered from the workload modules."""

from __future__ import annotations

from boundpath.workloads import experiments, paths, services, streams, surrounding

_MODULES = [paths, services, surrounding, streams, experiments]


def entry(spark, sf_dir):
    """Layered double-pass search, fewest hops, low bounds."""
    return paths.QUERIES["ldp_hops_low"](spark, sf_dir)


def queries() -> dict:
    return {name: f for m in _MODULES for name, f in m.QUERIES.items()}


def oracle_sql() -> dict:
    return {name: sql for m in _MODULES for name, sql in m.ORACLES.items()}
