"""The catalogue of queries with the SQL that checks them."""

from __future__ import annotations

from . import methods, relational, studies, surface
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "methods", "relational", "studies", "surface"]
