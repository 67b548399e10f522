
from __future__ import annotations

from .plans import queries_core, queries_serving

QUERIES = {}
ORACLES = {}
for _module in (queries_core, queries_serving):
    QUERIES |= _module.QUERIES
    ORACLES |= _module.ORACLES
