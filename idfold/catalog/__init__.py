"""All queries of the engine and their SQL equivalents."""

from __future__ import annotations


def load():
    """(queries, oracles) with every catalog module imported."""
    from idfold.catalog import core, measures, streams, surround, workloads  # noqa: F401
    from idfold.catalog.registry import ORACLES, QUERIES

    return QUERIES, ORACLES
