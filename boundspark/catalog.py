"""All queries of the engine with their oracle SQL."""

from __future__ import annotations

from boundspark.experiments import archives, measures, studies
from boundspark.operators import relational
from boundspark.streaming import encoders

MODULES = (measures, studies, archives, relational, encoders)


def queries() -> dict:
    return {name: fn for m in MODULES for name, (fn, _) in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: sql for m in MODULES for name, (_, sql) in m.QUERIES.items() if sql}
