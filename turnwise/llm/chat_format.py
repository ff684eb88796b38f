"""Chat formatting by prefix-target expansion.

Every assistant turn becomes an example of its own: all preceding turns are context, the reply alone is
trainable. Turns after the last reply go into one more example without a trainable span, so that a
conversation can be read back whole from its last example. Only native functions.

A turn is written  [INST]role LF text[/INST]</s>  . A control string inside a text gets one backslash after
its first character, one more if it already has some, so that unescaping is exact for every text.

Defined cases: null text or role count as empty; turns sort by turn (nulls first), then role, then text;
repeated rows are turns of their own; an empty table gives no example; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

OPEN, CLOSE, END = "[INST]", "[/INST]", "</s>"
_CONTROL = r"([<\[])(\\*)(/?s>|/?INST\])"
_STOP = r"\[/INST\]</s>"
_HEAD = r"^\[INST\]"


def escape(text: Column) -> Column:
    return F.regexp_replace(text, _CONTROL, r"$1\\$2$3")


def unescape(text: Column) -> Column:
    return F.regexp_replace(text, r"([<\[])\\(\\*)(/?s>|/?INST\])", r"$1$2$3")


def _escape_role(role: Column) -> Column:
    """A role ends at the first line feed, so its own line feeds are written as a backslash and n."""
    return escape(F.replace(F.replace(role, F.lit("\\"), F.lit("\\\\")), F.lit("\n"), F.lit("\\n")))


def _unescape_role(role: Column) -> Column:
    parts = F.split(unescape(role), r"\\\\", -1)
    return F.array_join(F.transform(parts, lambda p: F.replace(p, F.lit("\\n"), F.lit("\n"))), "\\")


def examples(turns: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """conv_id, example, formatted, loss_start (0-based character), loss_length (0: nothing trainable)."""
    rows = turns.select(
        F.col(conv).alias("conv_id"), F.struct(F.col(turn).alias("t"), F.coalesce(F.col(role), F.lit("")).alias("r"), F.coalesce(F.col(text), F.lit("")).alias("x")).alias("e")
    )
    ordered = rows.groupBy("conv_id").agg(F.sort_array(F.collect_list("e")).alias("e"))
    written = ordered.select(
        "conv_id",
        F.transform("e", lambda e: e["r"] == "assistant").alias("reply"),
        F.transform("e", lambda e: F.concat(F.lit(OPEN), _escape_role(e["r"]), F.lit("\n"))).alias("head"),
        F.transform("e", lambda e: escape(e["x"])).alias("body"),
    )
    whole = written.withColumn("turn_text", F.transform("body", lambda b, i: F.concat(F.get("head", i), b, F.lit(CLOSE + END))))
    last = F.size("body") - 1
    ends = F.filter(F.sequence(F.lit(0), last), lambda i: F.get("reply", i) | (i == last))
    targets = whole.select("conv_id", "reply", "head", "body", "turn_text", F.posexplode(ends).alias("example", "at"))
    before = F.array_join(F.slice("turn_text", F.lit(1), F.col("at")), "")
    start = F.length(before) + F.length(F.get("head", F.col("at")))
    trained = F.get("reply", F.col("at"))
    return targets.select(
        "conv_id",
        F.col("example").cast("int").alias("example"),
        F.concat(before, F.get("turn_text", F.col("at"))).alias("formatted"),
        F.when(trained, start).otherwise(F.lit(0)).cast("long").alias("loss_start"),
        F.when(trained, F.length(F.get("body", F.col("at")))).otherwise(F.lit(0)).cast("long").alias("loss_length"),
        trained.alias("trained"),
    )


def read_back(formatted: Column) -> Column:
    """array<struct<role, text>> of a formatted conversation."""
    parts = F.split(formatted, _STOP, -1)
    bodies = F.transform(F.slice(parts, F.lit(1), F.size(parts) - 1), lambda p: F.regexp_replace(p, _HEAD, ""))

    def turn(b: Column) -> Column:
        at = F.position(F.lit("\n"), b)
        return F.struct(_unescape_role(F.substr(b, F.lit(1), at - 1)).alias("role"), unescape(F.substr(b, at + 1)).alias("text"))

    return F.transform(bodies, turn)


def digests(made: DataFrame) -> DataFrame:
    """Per conversation what can be read back from its examples."""
    loss = F.struct("example", F.when(F.col("trained"), unescape(F.substr("formatted", (F.col("loss_start") + 1).cast("int"), F.col("loss_length").cast("int")))).alias("x"))
    per = made.groupBy("conv_id").agg(
        F.max_by("formatted", "example").alias("whole"), F.sort_array(F.collect_list(loss)).alias("loss"), F.sum(F.length("formatted")).cast("long").alias("formatted_chars")
    )
    read = per.select("conv_id", read_back(F.col("whole")).alias("turns"), F.array_join(F.transform("loss", lambda e: e["x"]), "").alias("loss"), "formatted_chars")
    joined = F.array_join(F.transform("turns", lambda t: F.concat(t["role"], F.lit("\n"), t["text"], F.lit("\n"))), "")
    return read.select(
        "conv_id", F.size("turns").cast("long").alias("n_turns"), F.sha2(joined, 256).alias("turns_sha256"), F.length("loss").cast("long").alias("loss_chars"), F.sha2("loss", 256).alias("loss_sha256"), "formatted_chars"
    )
