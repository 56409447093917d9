"""Registered queries and their SQL."""

from . import graph, relational

QUERIES = graph.QUERIES | relational.QUERIES
ORACLES = graph.ORACLES | relational.ORACLES
