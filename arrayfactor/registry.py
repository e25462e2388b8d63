"""All queries outside the training-data subpackage, with their SQL."""

from __future__ import annotations

from . import queries_arrays, queries_engine, queries_models

QUERIES = queries_arrays.QUERIES | queries_engine.QUERIES | queries_models.QUERIES
ORACLES: dict[str, str] = queries_arrays.ORACLES | queries_engine.ORACLES
FLAGSHIP = queries_models.flagship
