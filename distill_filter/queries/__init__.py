"""The registered queries: engine methods, measures, workloads and the operators around them."""

from . import live, methods, relational, surface, workloads
from .methods import flagship
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "flagship", "live", "methods", "relational", "surface", "workloads"]
