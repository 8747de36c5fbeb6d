"""Relational operators around the methods, one query each, with DuckDB counterparts."""

from fadegossip.operators import functions, joins, relational, windows

QUERIES = relational.QUERIES | joins.QUERIES | windows.QUERIES | functions.QUERIES
ORACLES = relational.ORACLES | joins.ORACLES | windows.ORACLES | functions.ORACLES
