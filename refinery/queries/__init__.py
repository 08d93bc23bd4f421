"""Registered queries of the engine, and their SQL."""

from refinery.queries import curate, generate, ingest, ops, outputs  # noqa: F401  each registers its queries
from refinery.queries.base import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
