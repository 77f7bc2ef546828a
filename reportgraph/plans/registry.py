"""All queries of the library: name to (query, SQL or None)."""

from __future__ import annotations

from reportgraph.plans import applications, experiments, mining, surrounding

QUERIES: dict[str, tuple] = {**mining.QUERIES, **applications.QUERIES, **experiments.QUERIES, **surrounding.QUERIES}
