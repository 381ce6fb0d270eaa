"""The engine's named queries."""

from . import basics, matching, models, search, streams  # noqa: F401
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
