"""All registered queries of the engine and their SQL counterparts."""

from __future__ import annotations

from .catalogue import core, relational, streams

QUERIES = core.QUERIES | relational.QUERIES | streams.QUERIES
ORACLES = core.ORACLES | relational.ORACLES | streams.ORACLES
