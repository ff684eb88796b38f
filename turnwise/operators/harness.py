"""Runs of scripted agents against the routed user simulator, and act typing and drift injection for turn logs.

A run is a function of its own row, so the grid of samples and agents is mapped without any exchange; turns come
out in order. Columns of samples: see SAMPLE_COLUMNS.
"""

from __future__ import annotations

import re
import sys

import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import simulator
from ..sources.schemas import TURN
from . import agents

for _name in (__name__, agents.__name__):
    cloudpickle.register_pickle_by_value(sys.modules[_name])

MAX_TURNS = 8
SAMPLE_COLUMNS = "anchor_id sample_type subtype question l1_question l1_answer l2_question l2_answer drift_utterance gold_pre gold_post other_pre other_post".split()
_WORD = re.compile("[a-z0-9]+")


def act(text: Column) -> Column:
    """ASK or SQL by the look of an agent's text."""
    return F.when(F.rlike(F.trim(F.lower(text)), F.lit(r"^(with|select)\b")), "SQL").otherwise("ASK")


def prime(samples: DataFrame) -> DataFrame:
    """The three turns with which a primed run begins; only samples with a chain have a layer to prime."""
    def turn(n: int, role: str, what: str, text: str) -> Column:
        return F.struct(F.lit(n).alias("turn_no"), F.lit(role).alias("role"), F.lit(what).alias("act"), F.col(text).alias("text"))

    rows = F.array(turn(0, "user", "SAY", "question"), turn(1, "assistant", "ASK", "l1_question"), turn(2, "user", "SAY", "l1_answer"))
    return samples.filter(F.col("sample_type").isin("C", "J")).select("anchor_id", "sample_type", F.inline(rows))


def inject_drift(turns: DataFrame, drifts: DataFrame) -> DataFrame:
    """turns (run_id, turn_no, role, act, text) with the run's utterance right after its first SQL; later turns move down by one."""
    first = turns.groupBy("run_id").agg(F.min(F.when(F.col("act") == "SQL", F.col("turn_no"))).alias("at")).filter("at IS NOT NULL")
    told = first.join(drifts.select("run_id", "utterance"), "run_id")
    moved = turns.join(told.select("run_id", "at"), "run_id", "left").withColumn("turn_no", F.when(F.col("turn_no") > F.col("at"), F.col("turn_no") + 1).otherwise(F.col("turn_no"))).drop("at")
    said = told.select("run_id", (F.col("at") + 1).cast("int").alias("turn_no"), F.lit("user").alias("role"), F.lit("DRIFT").alias("act"), F.col("utterance").alias("text"))
    return moved.unionByName(said, allowMissingColumns=True)


def _similar(a: str, b: str) -> float:
    x, y = set(_WORD.findall(a.lower())), set(_WORD.findall(b.lower()))
    return len(x & y) / len(x | y) if x | y else 0.0


def route_text(said: str, l1: str, l2: str, l1_done: bool) -> str:
    """The router of functions.simulator, on plain strings."""
    s1, s2 = _similar(said, l1), _similar(said, l2) if l1_done else 0.0
    return simulator.OTHER if s1 < simulator.THRESHOLD and s2 < simulator.THRESHOLD else simulator.L1 if s1 >= s2 else simulator.L2


def play(row: dict, agent: str, behave, protocol: str, max_turns: int) -> list[tuple]:
    """Turns of one run: (run_id, turn_no, role, act, text, sql, rho)."""
    run = f"{row['anchor_id']}|{row['sample_type']}|{agent}|{protocol}"
    state = agents.State(run, row["sample_type"], row["l1_question"], row["l2_question"], row["gold_pre"], row["gold_post"], row["other_pre"], row["other_post"])
    turns: list[tuple] = []

    def say(role: str, what: str, text: str, sql: str | None = None, rho: str | None = None) -> None:
        turns.append((run, len(turns), role, what, text, sql, rho))

    say("user", "SAY", row["question"])
    l1_done = protocol == "p"
    if l1_done:
        say("assistant", "ASK", row["l1_question"])
        say("user", "SAY", row["l1_answer"])
        state.asks, state.replies = 1, [row["l1_answer"]]
    for _ in range(max_turns):
        what, text = behave(state)
        if what == "ASK":
            rho = route_text(text, row["l1_question"], row["l2_question"], l1_done)
            say("assistant", "ASK", text, None, rho)
            answer = {"L1": row["l1_answer"], "L2": row["l2_answer"]}.get(rho, simulator.REFUSAL)
            l1_done = l1_done or rho == "L1"
            state.asks += 1
            state.replies.append(answer)
            say("user", "SAY", answer)
            continue
        say("assistant", "SQL", text, text)
        state.last_sql = text
        if row["sample_type"] == "C" or state.drifted:
            break
        state.drifted = True
        say("user", "DRIFT", row["drift_utterance"])
    return turns


def run(samples: DataFrame, names: list[str], protocols: tuple[str, ...] = ("f", "p"), max_turns: int = MAX_TURNS, behaviours: dict | None = None) -> DataFrame:
    """Turns of every sample, agent and protocol. The ask that a primed history holds has no routing label."""
    behaviours = behaviours or agents.SCRIPTED
    spark = samples.sparkSession
    grid = spark.createDataFrame([(n, p) for n in names for p in protocols], "agent string, protocol string")  # a handful of rows
    rows = samples.select(*SAMPLE_COLUMNS).crossJoin(F.broadcast(grid)).filter((F.col("protocol") == "f") | F.col("sample_type").isin("C", "J"))

    def walk(batches):
        for pdf in batches:
            turns = [t for row in pdf.to_dict("records") for t in play(row, row["agent"], behaviours[row["agent"]], row["protocol"], max_turns)]
            yield pd.DataFrame({n: pd.Series([t[i] for t in turns], dtype=object if n != "turn_no" else "int32") for i, n in enumerate(TURN.names)})

    return rows.mapInPandas(walk, TURN)
