"""Queries of the library and the SQL that says the same."""

from nearcopy.registry import relational, streams, vectors

QUERIES = relational.QUERIES | vectors.QUERIES | streams.QUERIES
ORACLES = relational.ORACLES | vectors.ORACLES | streams.ORACLES
