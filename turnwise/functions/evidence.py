"""Evidence notes: clauses that would settle a clarification beforehand are taken out."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def clauses(text: Column, breaks: str = r"(?<=[.;])\s+") -> Column:
    return F.split(F.coalesce(text, F.lit("")), breaks)


def _holds_any(clause: Column, words: Column) -> Column:
    return F.exists(words, lambda w: F.contains(clause, w))


def redact(text: Column, giveaway: Column, schema_terms: Column | None = None, breaks: str = r"(?<=[.;])\s+") -> Column:
    """Text without the clauses that hold a giveaway term, unless they also hold a schema term."""
    needed = F.array().cast("array<string>") if schema_terms is None else schema_terms
    return F.array_join(F.filter(clauses(text, breaks), lambda c: ~_holds_any(c, giveaway) | _holds_any(c, needed)), " ")
