"""Queries of the engine and their SQL."""

from farpoint.queries import detectors, operators, surface
from farpoint.queries.base import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "detectors", "operators", "surface"]
