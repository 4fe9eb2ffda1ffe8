"""Registered queries of the engine with their SQL oracles."""

from __future__ import annotations

from nearcohort.queries import gallery, graph_queries, reports, searches


def queries():
    return {**searches.QUERIES, **graph_queries.QUERIES, **reports.QUERIES, **gallery.QUERIES}


def oracles():
    return {**searches.ORACLES, **graph_queries.ORACLES, **reports.ORACLES, **gallery.ORACLES}
