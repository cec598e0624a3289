"""Every method, operator, measure and workload as a named query, with SQL where SQL can express it."""

from . import detection, grids, measures, relational, streams, studies
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "detection", "grids", "measures", "relational", "streams", "studies"]
