"""A small parser for SELECT statements, and the commitments read from its trees."""

from .commitments_of_tree import commitments
from .parser import SqlError, parse

__all__ = ["SqlError", "commitments", "parse"]
