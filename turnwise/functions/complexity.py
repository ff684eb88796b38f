"""A rule score of a query from its commitments, and tiers from score cuts."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Points for each item of a kind; a nested scope adds two, a chain verdict or a drift subtype as below.
WEIGHTS = {"FILTER": 1, "PROJECT": 1, "GROUP": 2, "ORDER": 1, "HAVING": 2, "LIMIT": 1, "OFFSET": 1}
CHAIN_POINTS = {"eliminated": 1, "transformed": 2}
DRIFT_POINTS = {"value": 0, "constraint": 1, "projection": 1}
CUTS = (5, 8)


def score(s: Column, verdict: Column | None = None, subtype: Column | None = None) -> Column:
    weight = F.create_map(*[F.lit(x) for pair in WEIGHTS.items() for x in pair])
    points = F.aggregate(s, F.lit(0), lambda n, x: n + F.coalesce(F.element_at(weight, x["kind"]), F.lit(0)))
    points = points + F.size(F.array_distinct(F.transform(F.filter(s, lambda x: x["scope"] != ""), lambda x: x["scope"]))) * 2
    for extra, table in ((verdict, CHAIN_POINTS), (subtype, DRIFT_POINTS)):
        if extra is not None:
            worth = F.lit(0)
            for name, p in table.items():
                worth = F.when(extra == name, p).otherwise(worth)
            points = points + worth
    return points.cast("int")


def tier(points: Column, cuts: tuple[int, int] = CUTS) -> Column:
    return F.when(points <= cuts[0], "basic").when(points <= cuts[1], "intermediate").otherwise("advanced")
