"""Named queries over the given tables, with oracle SQL where SQL can say the same."""

from . import baselines, checks, core, experiments, sketches, stream_queries, uses

MODULES = (core, sketches, stream_queries, baselines, checks, experiments, uses)


def queries() -> dict:
    return {name: f for m in MODULES for name, f in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for m in MODULES for name, sql in m.ORACLES.items()}
