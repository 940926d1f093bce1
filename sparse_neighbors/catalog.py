"""Registry of the library's queries and their DuckDB SQL."""

from __future__ import annotations

from .queries import joins, relational, streams

QUERIES = {**joins.QUERIES, **relational.QUERIES, **streams.QUERIES}
ORACLES = {**joins.ORACLES, **relational.ORACLES, **streams.ORACLES}
