"""All queries of the library proper."""

from __future__ import annotations

from . import regions, streams, surface, walks  # noqa: F401  registration
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
