"""Every method as a named query over the given tables, with SQL that checks it where SQL can."""

from __future__ import annotations

from cardest.catalog import baselines, bounds, estimates, experiments, operators, plans, samples, streams

MODULES = (bounds, samples, estimates, baselines, experiments, plans, operators, streams)

QUERIES = {k: f for m in MODULES for k, f in m.QUERIES.items()}
ORACLE = {k: q for m in MODULES for k, q in m.ORACLE.items()}
