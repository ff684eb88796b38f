"""Chain identification from logged conversations, primed histories, act typing and drift placement.

A conversation is a run of agent conv_id modulo 4. Assistant turns are routed by hash of their text; the full
protocol counts all of them, the primed one those after the first user-assistant-user prefix.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..operators import harness, trajectory
from ..sources.io import table
from .common import r6


def turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """run_id, agent, turn_no (from the first turn that is not a system turn), role, text, rho, act."""
    c = table(spark, sf_dir, "conversations").filter("role <> 'system'")
    n = F.row_number().over(Window.partitionBy("conv_id").orderBy("turn"))
    code = F.conv(F.substring(F.md5("text"), 1, 7), 16, 10).cast("long") % 5
    rho = F.when(F.col("role") == "assistant", F.when(code == 0, "L1").when(code == 1, "L2").when(code == 2, "Other"))
    act = F.when(F.col("role") != "assistant", "SAY").when(rho.isNull(), "SQL").otherwise("ASK")
    agent = F.concat(F.lit("agent"), (F.col("conv_id") % 4).cast("string"))
    return c.select(F.col("conv_id").alias("run_id"), agent.alias("agent"), n.alias("turn_no"), "role", "text", rho.alias("rho"), act.alias("act"))


def _runs(spark: SparkSession, sf_dir: str, primed: bool) -> DataFrame:
    t = turns(spark, sf_dir)
    t = t.filter("turn_no > 3") if primed else t
    return trajectory.fold(t.withColumn("sql", F.when(F.col("act") == "SQL", F.col("text"))).withColumn("drift_turn", F.lit(None).cast("int")), ["run_id", "agent"])


def conversation_rates(spark: SparkSession, sf_dir: str) -> DataFrame:
    full = _runs(spark, sf_dir, False)
    primed = _runs(spark, sf_dir, True).select("run_id", F.array_contains("rho", "L2").alias("l2_p"))
    both = full.join(primed, "run_id", "left")
    l1, l2 = F.array_contains("rho", "L1"), F.array_contains("rho", "L2")
    return both.groupBy("agent").agg(
        F.avg(F.col("asked").cast("int")).alias("ar"), F.avg(l1.cast("int")).alias("l1_ir"), F.avg(F.coalesce("l2_p", F.lit(False)).cast("int")).alias("l2_ir_p"), F.avg((l1 & l2).cast("int")).alias("jir")
    )


def chain_identification(spark: SparkSession, sf_dir: str) -> DataFrame:
    return conversation_rates(spark, sf_dir).select("agent", *[r6(F.col(c)).alias(c) for c in ("l1_ir", "l2_ir_p", "jir")])


def ask_vs_jir(spark: SparkSession, sf_dir: str) -> DataFrame:
    return conversation_rates(spark, sf_dir).select("agent", r6(F.col("ar")).alias("ar"), r6(F.col("jir")).alias("jir"))


def primed_history(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The opening three turns of each conversation as the history of a primed run."""
    t = turns(spark, sf_dir).filter("turn_no <= 3")
    first = t.groupBy("run_id").agg(*[F.max(F.when(F.col("turn_no") == k, F.col("text"))).alias(n) for k, n in ((1, "question"), (2, "l1_question"), (3, "l1_answer"))], F.count("*").alias("n"))
    samples = first.filter("n = 3").select(F.col("run_id").alias("anchor_id"), F.lit("C").alias("sample_type"), "question", "l1_question", "l1_answer")
    return harness.prime(samples).select(F.col("anchor_id").alias("conv_id"), F.col("turn_no").alias("position"), "role", "text")


def drift_injected(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each run with an utterance placed right after its first SQL turn."""
    t = turns(spark, sf_dir).select("run_id", "turn_no", "role", "act", "text")
    said = t.select("run_id").distinct().withColumn("utterance", F.concat(F.lit("drift of "), F.col("run_id").cast("string")))
    return harness.inject_drift(t, said).select("run_id", "turn_no", "role", "act", F.md5("text").alias("text_md5"))


_T = """
WITH t AS (SELECT conv_id AS run_id, 'agent' || (conv_id % 4) AS agent, row_number() OVER (PARTITION BY conv_id ORDER BY turn) AS turn_no, role, text,
  CASE WHEN role = 'assistant' THEN CAST('0x' || substr(md5(text), 1, 7) AS BIGINT) % 5 END AS code FROM conversations WHERE role <> 'system'),
r AS (SELECT run_id, agent, coalesce(bool_or(code IN (0, 1, 2)), false) AS asked, coalesce(bool_or(code = 0), false) AS l1, coalesce(bool_or(code = 1), false) AS l2, coalesce(bool_or(code = 1 AND turn_no > 3), false) AS l2p FROM t GROUP BY run_id, agent)
"""
QUERIES = {f.__name__: f for f in (chain_identification, ask_vs_jir, primed_history, drift_injected)}
ORACLES = {
    "chain_identification": _T + "SELECT agent, round(avg(CAST(l1 AS INT)), 6) AS l1_ir, round(avg(CAST(l2p AS INT)), 6) AS l2_ir_p, round(avg(CAST(l1 AND l2 AS INT)), 6) AS jir FROM r GROUP BY agent",
    "ask_vs_jir": _T + "SELECT agent, round(avg(CAST(asked AS INT)), 6) AS ar, round(avg(CAST(l1 AND l2 AS INT)), 6) AS jir FROM r GROUP BY agent",
    "primed_history": _T + "SELECT run_id AS conv_id, CAST(turn_no - 1 AS INT) AS position, CASE turn_no WHEN 2 THEN 'assistant' ELSE 'user' END AS role, text FROM t WHERE turn_no <= 3 AND run_id IN (SELECT run_id FROM t WHERE turn_no = 3)",
    "drift_injected": _T
    + """, f AS (SELECT run_id, min(turn_no) AS first_sql FROM t WHERE code > 2 GROUP BY run_id)
    SELECT t.run_id, CAST(turn_no + CASE WHEN turn_no > first_sql THEN 1 ELSE 0 END AS INT) AS turn_no, role, CASE WHEN role <> 'assistant' THEN 'SAY' WHEN code > 2 THEN 'SQL' ELSE 'ASK' END AS act, md5(text) AS text_md5 FROM t LEFT JOIN f ON t.run_id = f.run_id
    UNION ALL SELECT run_id, CAST(first_sql + 1 AS INT), 'user', 'DRIFT', md5('drift of ' || run_id) FROM f""",
}
