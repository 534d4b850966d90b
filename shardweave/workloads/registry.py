"""Every query of the core library with its SQL, by name."""

from __future__ import annotations

from shardweave.workloads import core, experiments, relational

QUERIES = {**core.QUERIES, **relational.QUERIES, **experiments.QUERIES}
ORACLES: dict[str, str] = {**core.ORACLES, **relational.ORACLES}
