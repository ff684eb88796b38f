"""Explicit schemas of the engine's tables."""

from pyspark.sql import types as T


def _s(*fields: tuple[str, T.DataType]) -> T.StructType:
    return T.StructType([T.StructField(n, t) for n, t in fields])


STRING, LONG, INT, BOOL, DOUBLE = T.StringType(), T.LongType(), T.IntegerType(), T.BooleanType(), T.DoubleType()
STRINGS = T.ArrayType(STRING)

COMMITMENT = _s(("kind", STRING), ("scope", STRING), ("skeleton", STRING), ("literals", STRINGS))
COMMITMENTS = T.ArrayType(COMMITMENT)
EXTRACTED = _s(("items", COMMITMENTS), ("error", STRING))

LAYER = _s(("question", STRING), ("chosen", STRING), ("alternative", STRING))
ANCHOR = _s(("anchor_id", STRING), ("db_id", STRING), ("family", STRING), ("sql", STRING), ("tier", STRING), ("split", STRING), ("evidence", STRING))
CHAIN = _s(("anchor_id", STRING), ("question", STRING), ("l1", LAYER), ("l2", LAYER), ("depends", STRING), ("verdict", STRING))
DRIFT = _s(("anchor_id", STRING), ("subtype", STRING), ("utterance", STRING), ("sql_pre", STRING), ("sql_post", STRING))
SAMPLE = _s(
    ("sample_id", STRING), ("anchor_id", STRING), ("sample_type", STRING), ("subtype", STRING), ("verdict", STRING), ("tier", STRING), ("question", STRING), ("targets", STRINGS)
)
TURN = _s(("run_id", STRING), ("turn_no", INT), ("role", STRING), ("act", STRING), ("text", STRING), ("sql", STRING), ("rho", STRING))
TRAJECTORY = _s(
    ("run_id", STRING), ("agent", STRING), ("anchor_id", STRING), ("sample_type", STRING), ("subtype", STRING), ("protocol", STRING), ("n_targets", INT),
    ("asked", BOOL), ("rho", STRINGS), ("ex", T.ArrayType(INT)), ("rec", BOOL),
)
ANNOTATION = _s(("sample_id", STRING), ("item", STRING), ("annotator", STRING), ("applicable", BOOL), ("pass", BOOL))
METRIC = _s(("agent", STRING), ("sample_type", STRING), ("subtype", STRING), ("protocol", STRING), ("metric", STRING), ("num", LONG), ("den", LONG), ("value", DOUBLE))
EVENT_PROPS = _s(("k", INT))
