"""All queries of the engine by name, and their SQL twins."""

from __future__ import annotations

from . import relational, sorting

QUERIES = {**sorting.QUERIES, **relational.QUERIES}
ORACLES = {**sorting.ORACLES, **relational.ORACLES}
