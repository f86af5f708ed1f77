"""All queries of the similarity engine and their SQL, by name."""

from __future__ import annotations

from . import core, experiments, relational, streams

QUERIES: dict = {**core.QUERIES, **experiments.QUERIES, **relational.QUERIES, **streams.QUERIES}
ORACLES: dict = {**core.ORACLES, **experiments.ORACLES, **relational.ORACLES, **streams.ORACLES}
