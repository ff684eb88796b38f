"""Drift status, subtypes and the single-literal test on abstract commitment sets."""

import itertools

import pytest
from pyspark.sql import functions as F

from turnwise.functions import drift
from turnwise.operators import commitments
from turnwise.sources.schemas import COMMITMENTS


def f(skeleton, *literals):
    return ("FILTER", "", skeleton, list(literals))


def o(skeleton, kind="PROJECT", *literals):
    return (kind, "", skeleton, list(literals))


A1, A2, A3, B2, B4, C3 = f("a = ?", "1"), f("a = ?", "2"), f("a = ?", "3"), f("b = ?", "2"), f("b = ?", "4"), f("c = ?", "3")
X, Y = o("x"), o("y")
CASES = [
    ("F01", [A1, X], [A1, X], "not_drift"),
    ("F02", [A1, X], [A1, B2, X], "not_drift"),
    ("F03", [A1, X], [A1, X, Y], "not_drift"),
    ("F04", [A1, B2, X], [A3, B2, X], "value"),
    ("F05", [f("a IN (?, ?)", "1", "2"), X], [f("a IN (?, ?)", "1", "3"), X], "value"),
    ("F05b", [f("a IN (?, ?)", "1", "5"), X], [f("a IN (?, ?)", "5", "9"), X], "value"),
    ("F05c", [f("a IN (?, ?)", "1", "2"), X], [f("a IN (?)", "1"), X], "reject"),
    ("F06", [f("a BETWEEN ? AND ?", "1", "5"), X], [f("a BETWEEN ? AND ?", "2", "6"), X], "reject"),
    ("F07", [A1, X], [f("a > ?", "1"), X], "reject"),
    ("F08", [A1, B2, X], [A3, B4, X], "reject"),
    ("F09", [A1, B2, X], [A1, X], "constraint"),
    ("F10", [A1, B2, X], [X], "constraint"),
    ("F11", [A1, B2, X], [C3, X], "reject"),
    ("F12", [A1, X], [A1, Y], "projection"),
    ("F13", [A1, X, o("?", "LIMIT", "5")], [A1, X, o("?", "LIMIT", "10")], "projection"),
    ("F14", [A1, X, o("x ASC", "ORDER")], [A1, X, o("x DESC", "ORDER")], "projection"),
    ("F15", [A1, X, Y], [A1, X], "projection"),
    ("F16", [A1, X], [A2, Y], "reject"),
    ("F17", [A1, B2, X], [A1, Y], "reject"),
    ("F18", [X], [A1, X], "not_drift"),
]


def frame(spark, rows):
    return spark.createDataFrame(rows, f"id string, pre {COMMITMENTS.simpleString()}, post {COMMITMENTS.simpleString()}, want string")


def test_all_cases(spark):
    got = frame(spark, CASES).select("id", "want", drift.classify(F.col("pre"), F.col("post")).alias("got")).collect()
    assert [(r.id, r.got) for r in got if r.got != r.want] == []


def test_having_side_and_null(spark):
    having = ("HAVING", "", "sum(x) > ?", ["5"])
    df = frame(spark, [("F19", [A1, X, having], [A1, X], "")])
    assert df.select(drift.classify(F.col("pre"), F.col("post"))).first()[0] == "projection"
    assert df.select(drift.classify(F.col("pre"), F.col("post"), having_as_filter=True)).first()[0] == "constraint"
    nothing = frame(spark, [("F20", [A1], None, "")])
    assert nothing.select(drift.classify(F.col("pre"), F.col("post"))).first()[0] is None


def test_against_plain_sets(spark):
    """Every pair of small sets against a direct reading of the definitions."""
    pool = [A1, A2, B2, X, Y]
    sets = [list(c) for n in range(4) for c in itertools.combinations(pool, n)]
    rows = [(str(i), a, b, "") for i, (a, b) in enumerate(itertools.product(sets, sets))]
    got = {r.id: r.got for r in frame(spark, rows).select("id", drift.classify(F.col("pre"), F.col("post")).alias("got")).collect()}

    def plain(a, b):
        s, t = {str(x) for x in a}, {str(x) for x in b}
        w = lambda z: [x for x in z if x[0] == "FILTER"]
        ws, wt = {str(x) for x in w(a)}, {str(x) for x in w(b)}
        if s <= t:
            return "not_drift"
        if s - ws == t - wt:
            lost, gained = [x for x in w(a) if str(x) not in wt], [x for x in w(b) if str(x) not in ws]
            if len(lost) == len(gained) == 1 and lost[0][2] == gained[0][2]:
                return "value"
            if wt < ws:
                return "constraint"
        return "projection" if ws == wt else "reject"

    assert all(got[i] == plain(a, b) for i, a, b, _ in rows)


def test_delta_lost_admissible(spark):
    df = frame(spark, [("1", [A1, B2, X], [A1, Y], "")])
    d = df.select(drift.delta(F.col("pre"), F.col("post")).alias("d"), drift.admissible(F.col("pre")).alias("a")).first()
    assert len(d.d.lost) == 2 and len(d.d.gained) == 1 and len(d.d.kept) == 1
    assert d.a == ["value", "constraint", "projection"]
    long = lambda c: commitments.explode_long(df.select("id", c), "id", c)
    assert drift.lost(long("pre"), long("post"), "id").count() == 2


def test_extract_and_udtf(spark):
    rows = [("select a from t where b = 1", "select a from t where b = 2"), ("select a from t where b = 1", "select from"), ("select a from t where b = 1", None)]
    df = commitments.extract_distinct(spark.createDataFrame(rows, "pre string, post string"), ["pre", "post"])
    got = {r.post: (drift_of, r.post_error) for r, drift_of in ((r, r.c) for r in df.select("*", drift.classify(F.col("pre_items"), F.col("post_items")).alias("c")).collect())}
    assert got["select a from t where b = 2"] == ("value", None)
    assert got["select from"][1].startswith("SqlError") and got[None][1] == "null"
    commitments.register(spark)
    assert spark.sql("select count(*) from (values ('select a, b from t where c = 1')) v(q), lateral commitments_of(v.q)").first()[0] == 3
    assert spark.sql("select size(commitment_set('select a from t'))").first()[0] == 1


def test_targeted_recognition(spark):
    wiped = frame(spark, [("w", [A1, B2, X], [X], ""), ("g", [A1, B2, X], [A1, X], "")])
    gold_pre, gold_post = (F.lit(None) for _ in range(2))
    gold = wiped.filter("id = 'g'").select(F.col("pre").alias("gp"), F.col("post").alias("gq"))
    got = {r.id: r.t for r in wiped.crossJoin(gold).select("id", drift.targeted_recognition(F.col("pre"), F.col("post"), F.col("gp"), F.col("gq")).alias("t")).collect()}
    assert got == {"w": False, "g": True}


@pytest.mark.parametrize("name", ["drift_subtype", "drift_lost_long"])
def test_plans_have_no_python_and_prune(spark, small, name):
    from turnwise.plans import drift_log

    plan = drift_log.QUERIES[name](spark, small)._jdf.queryExecution().toString()
    assert "Python" not in plan and "CartesianProduct" not in plan and "l_tax" not in plan.split("Physical Plan")[1]
