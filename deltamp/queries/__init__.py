"""All queries of the engine and their SQL twins, gathered from the modules of this folder."""

from deltamp.queries import layers, measures, parts, relational, streams, traces, training, windows  # noqa: F401
from deltamp.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
