"""Panels, sampling, execution match, trajectories, measures, analyses and the harness on small literal frames."""

import pytest
from pyspark.sql import functions as F

from turnwise.functions import chain, evidence, simulator
from turnwise.operators import agents, analysis, construct, execmatch, harness, metrics, panel, sampling, trajectory, validate
from turnwise.plans import cases, published
from turnwise.sources import io
from turnwise.sources.schemas import TRAJECTORY


def votes(spark, matrix):
    return spark.createDataFrame([(i, str(c)) for i, row in enumerate(matrix) for c in row], "s int, v string")


def kappa(spark, matrix):
    return panel.fleiss_kappa(votes(spark, matrix), "s", "v").first()["kappa"]


def test_kappa(spark):
    assert kappa(spark, [[1, 1, 1], [0, 0, 0]]) == pytest.approx(1)
    assert kappa(spark, [[1, 1, 1], [1, 1, 1]]) is None
    assert kappa(spark, [[1, 0], [0, 1]]) < 0
    counts = [(0, 0, 0, 0, 14), (0, 2, 6, 4, 2), (0, 0, 3, 5, 6), (0, 3, 9, 2, 0), (2, 2, 8, 1, 1), (7, 7, 0, 0, 0), (3, 2, 6, 3, 0), (2, 5, 3, 2, 2), (6, 5, 2, 1, 0), (0, 2, 2, 3, 7)]
    assert kappa(spark, [[k for k, n in enumerate(row) for _ in range(n)] for row in counts]) == pytest.approx(0.2099, abs=1e-4)


def test_panel_rules(spark):
    rows = [(s, k, k < yes) for s, yes in (("all", 5), ("three", 3), ("two", 2)) for k in range(5)]
    v = spark.createDataFrame(rows, "sample_id string, annotator int, ok boolean")
    a = panel.acceptance(v).first()
    assert (a.n, a.majority, a.strict) == (3, pytest.approx(2 / 3), pytest.approx(1 / 3))
    got = {r.sample_id: r.accepted for r in panel.consensus(v, "sample_id", F.col("ok"), "majority").collect()}
    assert got == {"all": True, "three": True, "two": False}
    items = spark.createDataFrame([("s", 1, "a", True, True), ("s", 1, "b", False, False), ("s", 2, "a", True, False)], "sample_id string, annotator int, item string, applicable boolean, pass boolean")
    assert {r.annotator: r.ok for r in panel.item_verdict(items).collect()} == {1: True, 2: False}
    assert "verdict" not in io.blind(spark.createDataFrame([(1, "x")], "a int, verdict string")).columns


def test_stratified(spark):
    df = spark.createDataFrame([(i, "ab"[i % 10 == 0]) for i in range(1000)], "id int, g string")
    assert {r.g: r["count"] for r in sampling.stratified(df, ["g"], "id", per_stratum=30).groupBy("g").count().collect()} == {"a": 30, "b": 30}
    assert {r.g: r["count"] for r in sampling.stratified(df, ["g"], "id", n_total=55).groupBy("g").count().collect()} in ({"a": 50, "b": 5}, {"a": 49, "b": 6})
    first = sampling.stratified(df, ["g"], "id", per_stratum=5).select("id").collect()
    assert sorted(first) == sorted(sampling.stratified(df.repartition(7), ["g"], "id", per_stratum=5).select("id").collect())


def test_counterfactual(spark):
    rows = [("whether returns count in money", "years as customer", "eliminated"), ("month range of ship date", "order date", "transformed"), ("ascending listing", "ascending listing order", "invariant")]
    df = spark.createDataFrame(rows, "l2 string, other string, want string")
    got = df.select("want", chain.counterfactual(chain.terms(F.col("l2")), chain.terms(F.col("other"))).alias("got")).collect()
    assert all(r.want == r.got for r in got)


def test_evidence_and_router(spark):
    df = spark.createDataFrame([("Spend means money. Column x holds spend. Other note.",)], "t string")
    kept = df.select(evidence.redact(F.col("t"), F.array(F.lit("pend")), F.array(F.lit("Column"))).alias("k")).first().k
    assert kept == "Column x holds spend. Other note."
    said = lambda s: chain.terms(F.lit(s))
    one = spark.range(1).select(
        simulator.route(said("late or discount"), said("late or discount reading"), said("line or order"), F.lit(False)).alias("a"), simulator.route(said("line or order"), said("late or discount"), said("line or order"), F.lit(False)).alias("b"),
        simulator.route(said("line or order"), said("late reading"), said("line or order"), F.lit(True)).alias("c"), simulator.reply(F.lit("Other"), F.lit("x"), F.lit("y")).alias("d"),
    ).first()
    assert (one.a, one.b, one.c, one.d) == ("L1", "Other", "L2", simulator.REFUSAL)


def test_exec_match(spark):
    base = spark.createDataFrame([(1, "a", 1.0), (2, None, 2.0), (2, None, 2.0)], "i int, s string, d double")
    noisy = spark.createDataFrame([(2, None, 2.0 + 1e-12), (1, "a", 1.0), (2, None, 2.0)], "x int, y string, z double")
    assert execmatch.exact(base, noisy) and execmatch.same_fingerprint(base, noisy)
    assert not execmatch.exact(base, base.distinct()) and execmatch.exact(base, base.distinct(), bag=False)
    assert not execmatch.exact(base, base.drop("d")) and not execmatch.exact(base, base.select("s", "i", "d"))
    assert execmatch.exact(base.filter("false"), noisy.filter("false"))


def test_exec_match_is_exact_on_numbers(spark):
    one = lambda kind, *values: spark.createDataFrame([(v,) for v in values], f"x {kind}")
    from decimal import Decimal

    big = 2**53
    for same in (execmatch.exact, execmatch.same_fingerprint):
        assert not same(one("long", big), one("long", big + 1)) and same(one("long", 5), one("int", 5)) and same(one("long", 100), one("double", 100.0))
        assert not same(one("decimal(38,0)", Decimal(10**30)), one("decimal(38,0)", Decimal(10**30 + 1))) and same(one("decimal(10,2)", Decimal("1.50")), one("decimal(12,4)", Decimal("1.5000")))
        assert same(one("double", 1.5, -0.0), one("decimal(10,2)", Decimal("1.50"), Decimal("0.00"))) and not same(one("double", 1.5), one("double", 1.50001)) and same(one("double", 1.0 + 1e-12), one("long", 1))


def test_executable_by_family(spark):
    spark.range(5).createOrReplaceTempView("numbers")
    anchors = spark.createDataFrame([("a", f"select id from numbers where id > {k}") for k in range(50)] + [("b", "select nope from numbers")], "family string, sql string")
    assert construct.executable(anchors, spark, limit=1, family="family").count() == 50


def test_gate_and_batch(spark):
    spark.range(5).createOrReplaceTempView("numbers")
    got = {r.pair_id: (r.ex, r.error_class) for r in execmatch.batch(
        spark, [("same", "select id from numbers", "select id from numbers where id >= 0"), ("bad", "select nope from numbers", "select id from numbers"), ("hidden", "select id from other", "select id from numbers"), ("command", "drop view numbers", "select id from numbers")], {"numbers"}
    ).collect()}
    assert got["same"] == (1, None) and got["bad"][0] == 0 and got["hidden"] == (0, "SqlError") and got["command"] == (0, "SqlError")
    anchors = spark.createDataFrame([("ok", "select id from numbers"), ("no", "select x from numbers")], "id string, sql string")
    assert [r.id for r in construct.executable(anchors, spark).collect()] == ["ok"]


RUNS = [  # id, type, protocol, n, asked, rho, ex, rec
    ("T01", "C", "f", 1, False, [], [1], None), ("T02", "C", "f", 1, True, ["L1"], [0], None), ("T03", "C", "f", 1, True, ["L1", "L2"], [1], None), ("T04", "C", "p", 1, True, ["L2"], [1], None),
    ("T05", "C", "f", 1, True, ["Other"], [0], None), ("T06", "D", "f", 2, False, [], [1, 1], True), ("T07", "D", "f", 2, False, [], [0, 1], True), ("T08", "D", "f", 2, False, [], [1, 0], True),
    ("T09", "D", "f", 2, False, [], [1, 1], False), ("T10", "J", "f", 2, True, ["L1"], [0, 0], True), ("T11", "D", "f", 2, False, [], [1], None),
]


def test_measures(spark):
    t = spark.createDataFrame([(i, "a", i, ty, "value", p, n, q, rho, ex, rec) for i, ty, p, n, q, rho, ex, rec in RUNS], TRAJECTORY)
    got = {(r.sample_type, r.metric): (r.num, r.den) for r in metrics.all_metrics(t, ["sample_type"]).collect()}
    assert got["C", "dea"] == (2, 4) and got["C", "ar"] == (3, 4) and got["C", "l1_ir"] == (2, 4) and got["C", "l2_ir_p"] == (1, 1) and got["C", "jir"] == (1, 4)
    assert got["D", "dea"] == (2, 5) and got["D", "drr"] == (3, 5) and got["D", "dra"] == (2, 5) and got["D", "ar"] == (0, 5)
    assert got["J", "dea"] == (0, 1) and got["J", "drr"] == (1, 1) and got["J", "dra"] == (0, 1)
    assert metrics.dra(t.filter("sample_type = 'C'"), ["agent"]).first().value is None
    assert t.filter("run_id = 'T10'").select(analysis.inherited_error(F.col("rec"), F.col("ex"))).first()[0]
    b = analysis.bootstrap_difference(t.withColumn("anchor_id", F.lit("k")), "dea", replicates=20).count()
    assert b <= 1
    w = spark.range(1).select(analysis.wilson(F.lit(5), F.lit(10)).alias("w")).first().w
    assert w.low == pytest.approx(0.2366, abs=1e-3) and w.high == pytest.approx(0.7634, abs=1e-3)


def test_fold_takes_last_before_and_after(spark):
    rows = [("r", 1, "ASK", "L1", None), ("r", 2, "SQL", None, "q1"), ("r", 3, "SQL", None, "q2"), ("r", 4, "DRIFT", None, None), ("r", 5, "SQL", None, "q3"), ("r", 6, "SQL", None, "q4")]
    turns = spark.createDataFrame(rows, "run_id string, turn_no int, act string, rho string, sql string")
    r = trajectory.fold(trajectory.with_drift_turn(turns)).first()
    assert (r.sql_pre, r.sql_post, r.asked, r.rho, r.n_drift) == ("q2", "q4", True, ["L1"], 1)
    assert trajectory.fold(trajectory.with_drift_turn(turns), first_sql=True).first().sql_pre == "q1"
    twice = turns.unionByName(turns.filter("act = 'DRIFT'"))
    assert validate.single_drift(twice).count() == 1 and validate.single_drift(turns).count() == 0


def test_pair_checks(spark):
    from turnwise.operators import commitments

    rows = [
        ("ok", "select a from t where b = 1", "select a from t where b = 2", "value"), ("parse", "select a from t", "select", "value"), ("monotone", "select a from t", "select a, b from t", "value"),
        ("subtype", "select a from t where b = 1", "select a from t", "value"),
    ]
    df = commitments.extract_distinct(spark.createDataFrame(rows, "id string, pre string, post string, subtype string"), ["pre", "post"])
    got = {r.id: r.dropped_at for r in validate.check_pairs(df).collect()}
    assert got == {"ok": None, "parse": "parse", "monotone": "monotone", "subtype": "subtype"}


def test_scripted_agents(spark, small):
    got = {(r.agent, r.sample_type, r.metric): r.value for r in cases.scripted_metrics(spark, small).collect()}
    g = lambda agent, ty, m: got[agent, ty, m]
    assert [g("gold", "C", m) for m in ("ar", "l1_ir", "l2_ir_p", "jir", "dea")] == [1, 1, 1, 1, 1] and g("gold", "D", "ar") == 0
    assert [g("gold", ty, m) for ty in "DJ" for m in ("drr", "dra", "dea")] == [1] * 6
    assert g("silent", "C", "ar") == 0 and [g("silent", ty, "dea") for ty in "CDJ"] == [0, 1, 0] and g("silent", "D", "dra") == 1 and g("silent", "J", "dra") == 0
    assert g("ask_everything", "C", "ar") == 1 and g("ask_everything", "C", "l1_ir") == 0
    assert g("ask_l1_only", "C", "l1_ir") == 1 and g("ask_l1_only", "C", "jir") == 0 and g("ask_l1_only", "C", "l2_ir_p") == 0
    assert g("accumulate", "D", "drr") == 0 and g("accumulate", "D", "dea") == 0 and g("ignore_drift", "D", "drr") == 0
    assert g("wipe_filters", "D", "drr") == 1 and g("wipe_filters", "D", "dra") == 0
    assert g("wrong_target", "D", "drr") == 1 and g("wrong_target", "D", "dra") == 0
    assert g("inherit_chain_error", "J", "drr") == 1 and g("inherit_chain_error", "J", "dea") == 0
    assert all(g("broken_sql", ty, "dea") == 0 for ty in "CDJ") and g("broken_sql", "D", "drr") == 0
    assert set(agents.SCRIPTED) >= {a for a, _, _ in got}


def test_replay_is_independent(spark):
    rows = [(f"a{i}", t, "value", "q", "first one", "x", "second two", "y", "d", "SELECT 1", "SELECT 2", "SELECT 3", "SELECT 4") for i in range(400) for t in "CDJ"]
    s = spark.createDataFrame(rows, ", ".join(f"{c} string" for c in harness.SAMPLE_COLUMNS))
    t = harness.run(s, ["r"], ("f",), behaviours={"r": agents.replay(0.6, 0.7)})
    f = trajectory.fold(trajectory.with_drift_turn(t))
    parts = F.split("run_id", r"\|")
    wide = f.select(F.get(parts, F.lit(0)).alias("a"), F.get(parts, F.lit(1)).alias("t"), ((F.col("sql_pre") == "SELECT 1") & F.coalesce(F.col("sql_post") == "SELECT 2", F.get(parts, F.lit(1)) == "C")).cast("int").alias("ok"))
    p = wide.groupBy().pivot("t", ["C", "D", "J"]).agg(F.avg("ok")).first()
    assert p.C == pytest.approx(0.6, abs=0.08) and p.D == pytest.approx(0.7, abs=0.08) and p.J == pytest.approx(p.C * p.D, abs=0.06)


def test_published_figures(spark, small):
    assert all(r.ok for r in published.published_audit(spark, small).collect())
