"""All queries of the engine with their DuckDB counterparts."""

from __future__ import annotations

from . import catalog_data, catalog_experiments, catalog_families, catalog_sketch, catalog_sweeps

_PARTS = (catalog_data, catalog_sketch, catalog_experiments, catalog_families, catalog_sweeps)
QUERIES: dict = {name: f for part in _PARTS for name, f in part.QUERIES.items()}
ORACLES: dict[str, str] = {name: text for part in _PARTS for name, text in part.ORACLES.items()}
FLAGSHIP = "top_neighbors_docs"
