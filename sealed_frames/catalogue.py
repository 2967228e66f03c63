"""All queries of the library and their SQL, by name."""

from __future__ import annotations

from .baselines import queries as baselines
from .workloads import micro, padded, prior, shared, studies, surrounding, tpch

_MODULES = (tpch, prior, padded, micro, shared, studies, surrounding, baselines)
QUERIES = {k: v for m in _MODULES for k, v in m.QUERIES.items()}
SQL = {k: v for m in _MODULES for k, v in m.SQL.items()}
