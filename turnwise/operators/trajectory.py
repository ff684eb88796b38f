"""Fold of dialogue turns to one row per run, in one exchange by run."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def fold(turns: DataFrame, keys: list[str] = ("run_id",), first_sql: bool = False) -> DataFrame:
    """Per run: asked, rho (sorted distinct), n_sql, n_drift, drift_turn, sql_pre, sql_post.

    turns has turn_no, act, rho, sql, and drift_turn (the run's drift turn or null, see with_drift_turn). The last
    SQL before the drift is the pre query (the first with first_sql), the last one after it the post query.
    """
    is_sql, at = F.col("act") == "SQL", F.col("drift_turn")
    before, after = is_sql & (at.isNull() | (F.col("turn_no") < at)), is_sql & (F.col("turn_no") > at)
    pre = F.min_by if first_sql else F.max_by
    return turns.groupBy(*keys).agg(
        F.bool_or(F.col("act") == "ASK").alias("asked"),
        F.array_sort(F.collect_set("rho")).alias("rho"),
        F.count_if(is_sql).alias("n_sql"),
        F.count_if(F.col("act") == "DRIFT").alias("n_drift"),
        F.max("drift_turn").alias("drift_turn"),
        pre(F.when(before, F.col("sql")), F.when(before, F.col("turn_no"))).alias("sql_pre"),
        F.max_by(F.when(after, F.col("sql")), F.when(after, F.col("turn_no"))).alias("sql_post"),
    )


def with_drift_turn(turns: DataFrame, keys: list[str] = ("run_id",)) -> DataFrame:
    per = turns.groupBy(*keys).agg(F.min(F.when(F.col("act") == "DRIFT", F.col("turn_no"))).alias("drift_turn"))
    return turns.join(per, list(keys))


def all_matched(ex: Column, n_targets: Column) -> Column:
    """Every target met; a missing query is a failure."""
    return F.coalesce((F.size(ex) == n_targets) & F.forall(ex, lambda x: F.coalesce(x, F.lit(0)) == 1), F.lit(False))
