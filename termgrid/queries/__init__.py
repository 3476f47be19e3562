"""Queries of the search engine and their DuckDB twins, by topic."""

from . import grids, relational, search, streams

QUERIES = {**search.QUERIES, **grids.QUERIES, **relational.QUERIES, **streams.QUERIES}
ORACLES = {**search.ORACLES, **grids.ORACLES, **relational.ORACLES, **streams.ORACLES}
