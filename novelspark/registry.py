"""All queries of the library with their SQL counterparts."""

from __future__ import annotations

from .plans import detectors, live, novelty, relational, workloads

FLAGSHIP = "vsm_weights"
MODULES = (novelty, detectors, workloads, relational, live)


def queries() -> dict:
    return {name: q for m in MODULES for name, q in m.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: q for m in MODULES for name, q in m.SQL.items()}
