"""Panels of judges and raters: consensus, agreement, acceptance, Fleiss' kappa. Long rows in, one or two aggregates."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


RULES = ("unanimous", "majority", "any")


def rule_of(rule: str) -> Column:
    """The test of a rule over n votes of which n_good are good."""
    return {"unanimous": F.col("n_good") == F.col("n"), "majority": F.col("n_good") * 2 > F.col("n"), "any": F.col("n_good") > 0}[rule]


def consensus(votes: DataFrame, key: str, good: Column, rule: str = "unanimous") -> DataFrame:
    """key, n, n_good, accepted under a rule: unanimous, majority or any."""
    out = votes.groupBy(key).agg(F.count("*").alias("n"), F.count_if(good).alias("n_good"))
    return out.withColumn("accepted", rule_of(rule))


def agreement(votes: DataFrame, key: str, verdict: str, by: list[str] = ()) -> DataFrame:
    """Share of keys on which all judges gave the same verdict."""
    per = votes.groupBy(*by, key).agg((F.min(verdict) == F.max(verdict)).alias("same"))
    return per.groupBy(*by).agg(F.count("*").alias("n"), F.count_if("same").alias("n_agree"), F.avg(F.col("same").cast("int")).alias("agreement"))


def item_verdict(annotations: DataFrame, keys: list[str] = ("sample_id", "annotator"), passed: str = "pass") -> DataFrame:
    """An annotator passes a sample when every applicable item passes; items that do not apply do not count."""
    return annotations.groupBy(*keys).agg(F.coalesce(F.bool_and(F.when(F.col("applicable"), F.col(passed))), F.lit(True)).alias("ok"))


def acceptance(verdicts: DataFrame, key: str = "sample_id", ok: str = "ok", by: list[str] = (), k: int = 3) -> DataFrame:
    """Per group: number of samples, share accepted by at least k raters, share accepted by all."""
    per = verdicts.groupBy(*by, key).agg(F.count_if(ok).alias("yes"), F.bool_and(ok).alias("all_ok"))
    return per.groupBy(*by).agg(
        F.count("*").alias("n"), F.avg((F.col("yes") >= k).cast("int")).alias("majority"), F.avg(F.col("all_ok").cast("int")).alias("strict")
    )


def majority(verdicts: DataFrame, key: str = "sample_id", ok: str = "ok", k: int = 3) -> DataFrame:
    return verdicts.groupBy(key).agg((F.count_if(ok) >= k).alias("majority"))


def strict(verdicts: DataFrame, key: str = "sample_id", ok: str = "ok") -> DataFrame:
    return verdicts.groupBy(key).agg(F.bool_and(ok).alias("strict"))


def criterion_rates(annotations: DataFrame, passed: str = "pass") -> DataFrame:
    return annotations.filter("applicable").groupBy("item").agg(F.count("*").alias("n"), F.avg(F.col(passed).cast("int")).alias("rate"))


def fleiss_kappa(ratings: DataFrame, key: str, category: str, by: list[str] = ()) -> DataFrame:
    """Per group: n, kappa. Any number of categories and of raters (at least two a sample); null where chance agreement is 1."""
    cells = ratings.groupBy(*by, key, category).agg(F.count("*").alias("c"))
    samples = cells.groupBy(*by, key).agg(F.sum("c").alias("raters"), F.sum(F.col("c") * (F.col("c") - 1)).alias("pairs")).filter("raters > 1")
    observed = samples.groupBy(*by).agg(F.count("*").alias("n"), F.avg(F.col("pairs") / (F.col("raters") * (F.col("raters") - 1))).alias("p"))
    shares = cells.groupBy(*by, category).agg(F.sum("c").alias("c")).groupBy(*by).agg((F.sum(F.col("c") * F.col("c")) / F.pow(F.sum("c"), F.lit(2))).alias("pe"))
    both = observed.join(shares, list(by)) if by else observed.crossJoin(shares)  # one row each
    return both.select(*by, "n", F.when(F.col("pe") < 1, (F.col("p") - F.col("pe")) / (1 - F.col("pe"))).alias("kappa"))
