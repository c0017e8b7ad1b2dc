"""All queries of the engine and the SQL that defines their results."""

from __future__ import annotations

from thriftline.plans import methods, surface, workloads
from thriftline.streaming import events

_MODULES = [workloads, methods, surface, events]

QUERIES: dict = {k: v for m in _MODULES for k, v in m.QUERIES.items()}
ORACLES: dict = {k: v for m in _MODULES for k, v in m.ORACLES.items()}
