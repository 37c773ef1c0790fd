"""All queries outside the llm subpackage."""

from __future__ import annotations

from corpus_audit.plans import catalog, relational  # noqa: F401  (the second adds its queries to the first's tables)

QUERIES = dict(catalog.QUERIES)
ORACLES = dict(catalog.ORACLES)
