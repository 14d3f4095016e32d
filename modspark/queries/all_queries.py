"""All queries but those of the corpus operators."""

from . import around, methods  # noqa: F401  they register their queries
from .base import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
