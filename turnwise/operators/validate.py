"""Automated checks of drift pairs, triplets and dialogues."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import drift

#: Which kinds a subtype may touch; all others have to be as they were.
TOUCHED = {drift.VALUE: ("FILTER",), drift.CONSTRAINT: ("FILTER",), drift.PROJECTION: ("PROJECT", "GROUP", "GROUP_MODE", "ORDER", "HAVING", "LIMIT", "OFFSET")}


def parses(error: Column) -> Column:
    return error.isNull()


def nonmonotone(pre: Column, post: Column) -> Column:
    return drift.is_drift(pre, post)


def subtype_matches(pre: Column, post: Column, assigned: Column) -> Column:
    return drift.classify(pre, post) == assigned


def preserved(pre: Column, post: Column, subtype: Column) -> Column:
    """Items outside the kinds that the subtype may touch are equal."""
    out = F.lit(False)
    for name, kinds in TOUCHED.items():
        rest = lambda s, k=kinds: F.filter(s, lambda x: ~x["kind"].isin(*k))
        out = F.when(subtype == name, drift.same_set(rest(pre), rest(post))).otherwise(out)
    return out


def check_pairs(pairs: DataFrame, different_results: Column | None = None) -> DataFrame:
    """pairs (pre_items, pre_error, post_items, post_error, subtype) with dropped_at: the first check that fails, or null."""
    pre, post = F.col("pre_items"), F.col("post_items")
    checks = {
        "parse": parses(F.col("pre_error")) & parses(F.col("post_error")),
        "same_results": F.lit(True) if different_results is None else different_results,
        "monotone": nonmonotone(pre, post),
        "subtype": subtype_matches(pre, post, F.col("subtype")),
        "scope": preserved(pre, post, F.col("subtype")),
    }
    reason = F.lit(None).cast("string")
    for name, ok in reversed(checks.items()):
        reason = F.when(~F.coalesce(ok, F.lit(False)), F.lit(name)).otherwise(reason)
    return pairs.withColumn("dropped_at", reason)


def single_drift(turns: DataFrame) -> DataFrame:
    """Runs with more than one drift turn."""
    return turns.groupBy("run_id").agg(F.count_if(F.col("act") == "DRIFT").alias("n_drift")).filter("n_drift > 1")


def triplets(samples: DataFrame) -> DataFrame:
    """anchor_key, reason of every broken triplet: each type once, one anchor query, one post query in D and J."""
    kind = F.col("sample_type")
    per = samples.groupBy("anchor_key").agg(
        F.count_if(kind == "C").alias("c"), F.count_if(kind == "D").alias("d"), F.count_if(kind == "J").alias("j"),
        F.count_distinct("pre").alias("pres"), F.count_distinct(F.when(kind != "C", F.col("post"))).alias("posts"), F.count_if(F.col("n_targets") != F.when(kind == "C", 1).otherwise(2)).alias("targets"),
    )
    reason = (
        F.when((F.col("c") != 1) | (F.col("d") != 1) | (F.col("j") != 1), "types").when(F.col("pres") != 1, "anchor").when(F.col("posts") != 1, "post").when(F.col("targets") > 0, "targets")
    )
    return per.select("anchor_key", reason.alias("reason")).filter("reason IS NOT NULL")
