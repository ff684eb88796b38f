"""The user simulator's two stages: a router from clarification to layer, and a responder."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

L1, L2, OTHER = "L1", "L2", "Other"
THRESHOLD = 0.3
REFUSAL = "Please decide that yourself."


def jaccard(a: Column, b: Column) -> Column:
    union = F.size(F.array_union(a, b))
    return F.when(union == 0, F.lit(0.0)).otherwise(F.size(F.array_intersect(a, b)) / union)


def coverage(inside: Column, whole: Column) -> Column:
    """Share of the terms of inside that whole has."""
    return F.when(F.size(inside) == 0, F.lit(0.0)).otherwise(F.size(F.array_intersect(inside, whole)) / F.size(inside))


def cosine(a: Column, b: Column) -> Column:
    def dot(x: Column, y: Column) -> Column:
        return F.aggregate(F.zip_with(x, y, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)

    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))


def route(said: Column, l1: Column, l2: Column, l1_done: Column, threshold: float = THRESHOLD, similarity=jaccard) -> Column:
    """Layer asked about. The second layer opens only after the first; ties go to the first."""
    s1, s2 = similarity(said, l1), F.when(l1_done, similarity(said, l2)).otherwise(F.lit(0.0))
    return F.when((s1 < threshold) & (s2 < threshold), OTHER).when(s1 >= s2, L1).otherwise(L2)


def reply(rho: Column, l1_answer: Column, l2_answer: Column) -> Column:
    """The annotated answer of the layer; the same again when asked again."""
    return F.when(rho == L1, l1_answer).when(rho == L2, l2_answer).otherwise(F.lit(REFUSAL))


def validate(routed: DataFrame, truth: str = "truth", label: str = "routed") -> DataFrame:
    """Confusion counts of router labels against expert labels."""
    return routed.groupBy(F.col(truth).alias("truth"), F.col(label).alias("routed")).agg(F.count("*").alias("n"))
