"""All queries of the engine by name, with the SQL that checks them."""

from __future__ import annotations

from .plans import core, experiments, relational, streams

QUERIES: dict = {**core.QUERIES, **relational.QUERIES, **streams.QUERIES, **experiments.QUERIES}
SQL: dict[str, str] = {**core.SQL, **relational.SQL, **streams.SQL, **experiments.SQL}
FLAGSHIP = "method_full"
