"""One place for every query of the engine and the SQL that checks it."""

from __future__ import annotations

from salvage import registry
from salvage.operators import aggregates, expressions, joins, reports, udfs, windows  # noqa: F401
from salvage.plans import queries_clusters, queries_correction, queries_fusion, queries_samples, queries_selection, queries_workloads  # noqa: F401
from salvage.sources import queries as source_queries  # noqa: F401
from salvage.streaming import queries as stream_queries  # noqa: F401

FLAGSHIP = "representatives"


def queries() -> dict:
    return dict(registry.QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(registry.ORACLES)
