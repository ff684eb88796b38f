"""Stratified sampling, reproducible by a hash of seed and key."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def draw(key: str, seed: int = 42):
    return F.md5(F.concat(F.lit(f"{seed}|"), F.col(key).cast("string")))


def stratified(df: DataFrame, strata: list[str], key: str, per_stratum: int | None = None, n_total: int | None = None, seed: int = 42) -> DataFrame:
    """Exactly per_stratum rows of each stratum (all, if it has fewer), or n_total spread by largest remainder.

    Spark plans the rank as a group limit before the shuffle, so a stratum sends at most the quota from a task.
    """
    order = Window.partitionBy(*strata).orderBy(draw(key, seed), key)
    if per_stratum is not None:
        return df.withColumn("_r", F.row_number().over(order)).filter(F.col("_r") <= per_stratum).drop("_r")
    sizes = df.groupBy(*strata).count()
    total = Window.partitionBy()
    exact = F.lit(n_total) * F.col("count") / F.sum("count").over(total)
    rest = Window.orderBy(F.desc("frac"), *strata)  # one row a stratum
    quota = sizes.withColumn("exact", exact).withColumn("base", F.floor("exact")).withColumn("frac", F.col("exact") - F.col("base"))
    quota = quota.withColumn("left", F.lit(n_total) - F.sum("base").over(total)).withColumn("quota", F.col("base") + (F.row_number().over(rest) <= F.col("left")).cast("int"))
    ranked = df.withColumn("_r", F.row_number().over(order)).join(F.broadcast(quota.select(*strata, "quota")), strata)
    return ranked.filter(F.col("_r") <= F.col("quota")).drop("_r", "quota")


def approximate(df: DataFrame, stratum: str, fractions: dict, seed: int = 42) -> DataFrame:
    """One pass, sizes in expectation only."""
    return df.sampleBy(stratum, fractions, seed)


def audit_triplets(samples: DataFrame, strata: list[str], n_triplets: int, seed: int = 42) -> DataFrame:
    """All samples of n_triplets anchors, balanced over the strata."""
    anchors = samples.select("anchor_id", *strata).dropDuplicates(["anchor_id"])
    return samples.join(stratified(anchors, strata, "anchor_id", n_total=n_triplets, seed=seed).select("anchor_id"), "anchor_id", "left_semi")
