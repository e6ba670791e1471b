"""Every method of the engine as a named query with its SQL oracle."""

from . import methods, relational
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "methods", "relational"]
