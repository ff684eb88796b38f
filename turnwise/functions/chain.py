"""Chain ambiguity: the counterfactual test over the terms that each layer needs and supplies."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ELIMINATED, TRANSFORMED, INVARIANT = "eliminated", "transformed", "invariant"


def terms(text: Column) -> Column:
    return F.array_distinct(F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), "[^a-z0-9]+"), lambda w: w != ""))


def counterfactual(needed: Column, supplied: Column) -> Column:
    """Verdict on the second layer if the first had been answered otherwise: needed terms against those the other reading supplies."""
    common = F.size(F.array_intersect(needed, supplied))
    return F.when(common == 0, ELIMINATED).when(common < F.size(needed), TRANSFORMED).otherwise(INVARIANT)


def qualifies(verdict: Column) -> Column:
    return verdict.isin(ELIMINATED, TRANSFORMED)


def inject(anchors: DataFrame, templates: DataFrame) -> DataFrame:
    """Anchors with the layers of their family's template; templates are a handful of rows."""
    return anchors.join(F.broadcast(templates), "family")
