"""All queries of the engine and the SQL that must give the same rows."""

from __future__ import annotations

from . import bakeoff, baselines, catalogue, experiments, extensions, load, model, planning, relational, store, streams

QUERIES: dict = {}
ORACLES: dict = {}
for _part in (model, planning, store, load, baselines, catalogue, relational, streams, extensions, experiments, bakeoff):
    QUERIES |= _part.QUERIES
    ORACLES |= _part.ORACLES
