"""All driver queries of the engine, by module; each stands beside its SQL."""

from . import batch, filtering, formats, grouping, loops, relational, sampling
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "batch", "filtering", "formats", "grouping", "loops", "relational", "sampling"]
