"""All registered queries of the engine and the SQL that restates them."""

from __future__ import annotations

from . import relational, roundtrips, searches, sizes, streams

QUERIES = sizes.Q | roundtrips.Q | searches.Q | relational.Q | streams.Q
ORACLES = sizes.SQL | roundtrips.SQL | searches.SQL | relational.SQL | streams.SQL
