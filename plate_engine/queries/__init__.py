"""All registered queries of the engine (without the corpus operators)."""

from . import methods, preparation, relational  # noqa: F401
from .base import ORACLE, QUERIES

__all__ = ["ORACLE", "QUERIES"]
