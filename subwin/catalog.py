"""All queries by name and the SQL that they are compared with."""

from __future__ import annotations

from subwin import metrics, workloads
from subwin.functions import exact
from subwin.operators import alternatives, baselines, eh, kll, relational, sampling, smooth, univ
from subwin.plans import cache, rules
from subwin.sources import generator
from subwin.streaming import live

_MODULES = (exact, eh, kll, sampling, univ, smooth, alternatives, baselines, rules, cache, metrics, workloads, relational, live, generator)
QUERIES: dict = {name: query for module in _MODULES for name, query in module.QUERIES.items()}
SQL: dict = {name: sql for module in _MODULES for name, sql in module.SQL.items()}


flagship = kll.flagship
