"""All queries of the engine and their DuckDB statements, by key."""

from gistloom.plans import catalog_core, catalog_experiments, catalog_ops, catalog_stream

QUERIES: dict = {**catalog_core.QUERIES, **catalog_experiments.QUERIES, **catalog_ops.QUERIES, **catalog_stream.QUERIES}
ORACLES: dict[str, str] = {**catalog_core.ORACLES, **catalog_experiments.ORACLES, **catalog_ops.ORACLES, **catalog_stream.ORACLES}
