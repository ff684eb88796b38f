"""Deterministic agents over all anchors: accuracy, recognition, resolution and their contrasts.

An anchor's query gives, per return flag, the count and price sum of the lines of matching orders. Drift: the
next year (value), no status filter (constraint), the count alone (projection). Agents emit the gold query, the
alternative reading (no priority filter), a query without any filter, or repeat themselves, by hash of agent
and anchor with the agent's rates. All results of the family come from one cube, so one scan serves every agent.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import drift
from ..operators import analysis, execmatch, metrics
from . import anchors as pool
from .common import luck, luck_sql, r6

#: agent, then rates in ten-thousandths: ask on C/J, ask on D, first layer, second layer, chain read right, drift noticed, drift resolved.
AGENTS = [
    ("gold", 10000, 0, 10000, 10000, 10000, 10000, 10000),
    ("silent", 0, 0, 0, 0, 3000, 9800, 6000),
    ("steady", 4000, 500, 6000, 3000, 3500, 9900, 5500),
    ("eager", 9000, 3000, 5000, 2000, 3300, 9700, 5000),
    ("stubborn", 2000, 100, 4000, 1000, 2500, 1000, 4000),
]
_RATES = ["ask", "ask_d", "l1", "l2", "chain", "note", "solve"]
ANY = "*"
VARIANTS = ("pre", "alt", "post", "altpost", "wipe")


def cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every group that the family needs, dropped filters as a star: one scan, one exchange."""
    f = pool.facts(spark, sf_dir).withColumn("year", F.col("year").cast("string"))
    base = f.groupBy(*pool.PARAMETERS, "l_returnflag").agg(F.count("*").alias("n"), F.sum("cents").alias("cents"))
    kept = [["segment", "priority", "status", "year"], ["segment", "status", "year"], ["segment", "priority", "year"], ["segment", "year"], []]
    sets = base.groupingSets([[*k, "l_returnflag"] for k in kept], *pool.PARAMETERS, "l_returnflag").agg(F.sum("n").alias("n"), F.sum("cents").alias("cents"))
    return sets.select(*[F.coalesce(p, F.lit(ANY)).alias(p) for p in pool.PARAMETERS], "l_returnflag", "n", "cents")


def bindings(anchors: DataFrame) -> DataFrame:
    """anchor_key, variant, the four parameters of that variant, and whether the sum is shown."""
    sub, year = F.col("subtype"), F.col("year").cast("string")
    after = F.when(sub == drift.VALUE, (F.col("year") + 1).cast("string")).otherwise(year)
    status = F.when(sub == drift.CONSTRAINT, F.lit(ANY)).otherwise(F.col("status"))
    shown = sub != drift.PROJECTION
    star = F.lit(ANY)
    rows = [
        ("pre", F.col("segment"), F.col("priority"), F.col("status"), year, F.lit(True)), ("alt", F.col("segment"), star, F.col("status"), year, F.lit(True)),
        ("post", F.col("segment"), F.col("priority"), status, after, shown), ("altpost", F.col("segment"), star, status, after, shown), ("wipe", star, star, star, star, F.lit(True)),
    ]
    made = F.array(*[F.struct(F.lit(v).alias("variant"), a.alias("segment"), b.alias("priority"), c.alias("status"), d.alias("year"), e.alias("shown")) for v, a, b, c, d, e in rows])
    return anchors.select("anchor_key", "subtype", F.inline(made))


def results(spark: SparkSession, sf_dir: str) -> DataFrame:
    """anchor_key, subtype, and for each variant the fingerprint of its result (fp_<variant>)."""
    b = bindings(pool.anchors(spark, sf_dir)).withColumn("q", F.concat_ws("#", "anchor_key", "variant"))
    c = cube(spark, sf_dir)
    rows = b.join(c, pool.PARAMETERS, "left").withColumn("cents", F.when(F.col("shown"), F.col("cents")))
    prints = execmatch.fingerprint_columns(["c0", "c1", "c2"])
    cells = rows.filter("l_returnflag IS NOT NULL").select("anchor_key", "variant", F.col("l_returnflag").alias("c0"), F.col("n").cast("string").alias("c1"), F.col("cents").cast("string").alias("c2"))
    found = cells.groupBy("anchor_key", "variant").agg(*prints).select("anchor_key", "variant", F.concat_ws(":", "n", F.col("hash_sum").cast("string"), "hash_xor").alias("fp"))
    whole = b.join(found, ["anchor_key", "variant"], "left").withColumn("fp", F.concat(F.when(F.col("shown"), "3 columns ").otherwise("2 columns "), F.coalesce("fp", F.lit("empty"))))
    return whole.groupBy("anchor_key", "subtype").pivot("variant", list(VARIANTS)).agg(F.first("fp")).select("anchor_key", "subtype", *[F.col(v).alias(f"fp_{v}") for v in VARIANTS])


def _pick(code: Column, prefix: str) -> Column:
    out = F.lit(None).cast("string")
    for v in VARIANTS:
        out = F.when(code == v, F.col(f"{prefix}{v}")).otherwise(out)
    return out


def _set(code: Column) -> Column:
    """Commitments of a variant, from the anchor's own parameters."""
    seg, pri, sta, year = (F.element_at(F.split("anchor_key", "/"), i) for i in (1, 2, 3, 4))
    later = code.isin("post", "altpost")
    filters = [
        F.when(code != "wipe", drift.item("FILTER", "segment = ?", seg)),
        F.when(code.isin("pre", "post"), drift.item("FILTER", "priority = ?", pri)),
        F.when((code != "wipe") & ~(later & (F.col("subtype") == drift.CONSTRAINT)), drift.item("FILTER", "status = ?", sta)),
        F.when(code != "wipe", drift.item("FILTER", "year = ?", F.when(later & (F.col("subtype") == drift.VALUE), (year.cast("int") + 1).cast("string")).otherwise(year))),
    ]
    outputs = [drift.item("PROJECT", "l_returnflag"), drift.item("GROUP", "l_returnflag"), drift.item("PROJECT", "count(*)"), F.when(~(later & (F.col("subtype") == drift.PROJECTION)), drift.item("PROJECT", "sum(l_extendedprice)"))]
    return F.array_sort(F.array_compact(F.array(*filters, *outputs)))


def trajectories(spark: SparkSession, sf_dir: str) -> DataFrame:
    """run_id, agent, anchor_id, sample_type, subtype, protocol, n_targets, asked, rho, ex, rec of every run."""
    agents = spark.createDataFrame(AGENTS, ", ".join(["agent string", *[f"p_{r} int" for r in _RATES]]))
    grid = results(spark, sf_dir).crossJoin(F.broadcast(agents))
    types = F.explode(F.array(*[F.struct(F.lit(t).alias("sample_type"), F.lit(p).alias("protocol")) for t, p in (("C", "f"), ("D", "f"), ("J", "f"), ("C", "p"), ("J", "p"))]))
    g = grid.withColumn("e", types).select("*", "e.*").drop("e")
    lucky = lambda salt, rate=None: luck(salt, F.col("agent"), F.col("anchor_key")) < F.col(f"p_{rate or salt}")
    chained = F.col("sample_type") != "D"
    asked = F.when(chained, lucky("ask")).otherwise(lucky("ask", "ask_d"))
    l1 = chained & asked & lucky("l1")
    l2 = F.when(F.col("protocol") == "p", lucky("l2")).otherwise(l1 & lucky("l2"))
    g = g.withColumn("asked", asked).withColumn("hit1", l1 & (F.col("protocol") == "f")).withColumn("hit2", chained & l2)
    right = ~chained | lucky("chain")
    note, solve = lucky("note"), lucky("solve")
    pre = F.when(right, "pre").otherwise("alt")
    post = F.when(~note, pre).when(~solve, "wipe").otherwise(F.when(right, "post").otherwise("altpost"))
    g = g.withColumn("pre", pre).withColumn("post", F.when(F.col("sample_type") != "C", post))
    ex_pre = (_pick(F.col("pre"), "fp_") == F.col("fp_pre")).cast("int")
    ex_post = (_pick(F.col("post"), "fp_") == F.col("fp_post")).cast("int")
    return g.select(
        F.concat_ws("|", "anchor_key", "sample_type", "agent", "protocol").alias("run_id"), "agent", F.col("anchor_key").alias("anchor_id"), "sample_type", "subtype", "protocol",
        F.when(F.col("sample_type") == "C", 1).otherwise(2).alias("n_targets"), "asked",
        F.array_compact(F.array(F.when(F.col("hit1"), "L1"), F.when(F.col("hit2"), "L2"), F.when(F.col("asked") & ~F.col("hit1") & ~F.col("hit2"), "Other"))).alias("rho"),
        F.when(F.col("sample_type") == "C", F.array(ex_pre)).otherwise(F.array(ex_pre, ex_post)).alias("ex"),
        F.when(F.col("sample_type") != "C", drift.is_drift(_set(F.col("pre")), _set(F.col("post")))).alias("rec"),
    )


def ex_family(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether the anchor's result survives its own drift (a sound anchor's does not)."""
    return results(spark, sf_dir).select("anchor_key", F.col("subtype").alias("drift"), (F.col("fp_pre") == F.col("fp_post")).cast("int").alias("ex"))


def dea_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    return analysis.accuracy_table(trajectories(spark, sf_dir)).withColumn("dea", F.round("dea", 6))


def _dea(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.dea(trajectories(spark, sf_dir), ["agent", "sample_type"]).withColumn("dea", r6(F.col("value"))).select("agent", "sample_type", "dea")


def dea_marks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return analysis.rank_marks(_dea(spark, sf_dir))


def dea_spread(spark: SparkSession, sf_dir: str) -> DataFrame:
    return analysis.spread(_dea(spark, sf_dir)).withColumn("spread", F.round("spread", 6))


def dea_ordering(spark: SparkSession, sf_dir: str) -> DataFrame:
    return analysis.ordering(trajectories(spark, sf_dir)).select("agent", "ordered")


def ask_rate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.ar(trajectories(spark, sf_dir), ["agent", "sample_type"]).select("agent", "sample_type", "num", "den", r6(F.col("value")).alias("ar"))


def ask_selectivity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return analysis.ask_selectivity(trajectories(spark, sf_dir)).select("agent", *[r6(F.col(c)).alias(c) for c in ("ar_chain", "ar_drift", "difference")])


def layer_contrast(spark: SparkSession, sf_dir: str) -> DataFrame:
    return analysis.layer_contrast(trajectories(spark, sf_dir)).select("agent", *[r6(F.col(c)).alias(c) for c in ("l1_ir", "l2_ir_p", "jir")])


def drift_recognition(spark: SparkSession, sf_dir: str) -> DataFrame:
    return analysis.recognition(trajectories(spark, sf_dir)).select("agent", "sample_type", r6(F.col("drr")).alias("drr"), r6(F.col("dra")).alias("dra"))


def recognition_gap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return analysis.gap(trajectories(spark, sf_dir)).withColumn("gap", r6(F.col("gap")))


def dra_by_subtype(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = analysis.subtype_profile(trajectories(spark, sf_dir))
    return p.select("subtype", "agent", r6(F.col("dra")).alias("dra"), r6(F.col("subtype_mean")).alias("subtype_mean"), "is_max")


def joint_transition(spark: SparkSession, sf_dir: str) -> DataFrame:
    return analysis.transition(trajectories(spark, sf_dir)).select("agent", *[r6(F.col(f"d_{n}")).alias(f"d_{n}") for n in ("drr", "dra", "dea")])


def joint_excess(spark: SparkSession, sf_dir: str) -> DataFrame:
    return analysis.joint_excess(trajectories(spark, sf_dir)).select("agent", *[r6(F.col(c)).alias(c) for c in ("product", "joint", "excess")])


def failure_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = analysis.failure_overlap(trajectories(spark, sf_dir))
    return o.select("agent", *[F.col(c).cast("long").alias(c) for c in ("both_fail", "only_chain", "only_drift", "neither")], r6(F.col("lift")).alias("lift"), r6(F.col("jaccard")).alias("jaccard"))


def plain_execution(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Baseline: the final query's match alone."""
    return metrics.plain_ex(trajectories(spark, sf_dir), ["agent", "sample_type"]).select("agent", "sample_type", "num", "den", r6(F.col("value")).alias("plain_ex"))


def per_turn_ambiguity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Baseline: each layer alone."""
    w = metrics.per_turn_ambiguity(trajectories(spark, sf_dir), ["agent"])
    return w.select("agent", "per_turn_l1_num", "per_turn_l1_den", "per_turn_l2_num", "per_turn_l2_den")


def pre_post_match(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The components of the case study: pre and post match and the inherited error, counted."""
    t = trajectories(spark, sf_dir).filter("protocol = 'f' AND sample_type <> 'C'")
    return t.groupBy("agent", "sample_type").agg(
        F.count_if(F.get("ex", F.lit(0)) == 1).alias("pre_ex"), F.count_if(F.get("ex", F.lit(1)) == 1).alias("post_ex"), F.count_if(analysis.inherited_error(F.col("rec"), F.col("ex"))).alias("inherited")
    )


def threshold_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    m = metrics.all_metrics(trajectories(spark, sf_dir), ["agent"]).filter(F.col("metric").isin("jir", "drr", "dea")).select("agent", "metric", "value")
    levels = spark.createDataFrame([("jir", 0.05), ("drr", 0.949), ("dea", 0.46)], "metric string, level double")
    return analysis.threshold_counts(m, levels).select("metric", "level", "n_below", "argmin", "argmax")


def size_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    classes = spark.createDataFrame([("gold", "large"), ("steady", "large"), ("silent", "small"), ("eager", "small"), ("stubborn", "small")], "agent string, size_class string")
    c = analysis.class_contrast(_dea(spark, sf_dir), classes)
    return c.select("sample_type", *[r6(F.col(x)).alias(x) for x in ("large", "small", "difference")])


def subtype_extremes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For how many agents each subtype is the easiest, and the hardest."""
    e = analysis.extremes(analysis.subtype_profile(trajectories(spark, sf_dir)))
    return e.select("subtype", F.col("easiest_for").cast("long").alias("easiest_for"), F.col("hardest_for").cast("long").alias("hardest_for"))


def ask_correlation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return analysis.ask_correlation(trajectories(spark, sf_dir)).select(r6(F.col("correlation")).alias("correlation"))


def dea_intervals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy with its 95 % score interval."""
    m = metrics.dea(trajectories(spark, sf_dir), ["agent", "sample_type"]).withColumn("w", analysis.wilson(F.col("num"), F.col("den")))
    return m.select("agent", "sample_type", r6(F.col("w.low")).alias("low"), r6(F.col("w.high")).alias("high"))


def failure_phi(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = analysis.failure_overlap(trajectories(spark, sf_dir))
    return o.select("agent", r6(F.col("phi")).alias("phi"))


_VALUES = ", ".join(f"({', '.join([repr(a[0]), *map(str, a[1:])])})" for a in AGENTS)


def _l(salt: str, rate: str) -> str:
    return f"{luck_sql(repr(salt), 'agent', 'anchor_key')} < p_{rate}"


_B = f"""{pool._A},
fine AS (SELECT segment, priority, status, year, l_returnflag AS flag, count(*) AS n, sum(cents) AS cents FROM f GROUP BY segment, priority, status, year, l_returnflag),
b AS (SELECT anchor_key, subtype, 'pre' AS v, segment, priority, status, year, true AS shown FROM a
  UNION ALL SELECT anchor_key, subtype, 'alt', segment, NULL, status, year, true FROM a
  UNION ALL SELECT anchor_key, subtype, 'post', segment, priority, CASE WHEN subtype <> 'constraint' THEN status END, year + CASE WHEN subtype = 'value' THEN 1 ELSE 0 END, subtype <> 'projection' FROM a
  UNION ALL SELECT anchor_key, subtype, 'altpost', segment, NULL, CASE WHEN subtype <> 'constraint' THEN status END, year + CASE WHEN subtype = 'value' THEN 1 ELSE 0 END, subtype <> 'projection' FROM a
  UNION ALL SELECT anchor_key, subtype, 'wipe', NULL, NULL, NULL, NULL, true FROM a),
g AS (SELECT b.anchor_key, b.subtype, b.v, b.shown, fine.flag, sum(fine.n) AS n, sum(fine.cents) AS cents FROM b LEFT JOIN fine
  ON (b.segment IS NULL OR b.segment = fine.segment) AND (b.priority IS NULL OR b.priority = fine.priority) AND (b.status IS NULL OR b.status = fine.status) AND (b.year IS NULL OR b.year = fine.year)
  GROUP BY b.anchor_key, b.subtype, b.v, b.shown, fine.flag),
r0 AS (SELECT anchor_key, subtype, v, CASE WHEN shown THEN '3' ELSE '2' END || coalesce(string_agg(flag || n || CASE WHEN shown THEN ':' || cents ELSE '' END, ',' ORDER BY flag), '') AS txt FROM g GROUP BY anchor_key, subtype, v, shown),
r AS (SELECT anchor_key, subtype, {', '.join(f"max(CASE WHEN v = '{v}' THEN txt END) AS {v}" for v in VARIANTS)} FROM r0 GROUP BY anchor_key, subtype),
agents AS (SELECT * FROM (VALUES {_VALUES}) AS t(agent, {', '.join('p_' + r for r in _RATES)})),
u AS (SELECT agent, anchor_key, subtype, pre, alt, post, altpost, wipe, {_l('ask', 'ask')} AS ask_c, {_l('ask', 'ask_d')} AS ask_d, {_l('l1', 'l1')} AS l1, {_l('l2', 'l2')} AS l2, {_l('chain', 'chain')} AS chain, {_l('note', 'note')} AS note, {_l('solve', 'solve')} AS solve FROM r, agents),
w AS (SELECT *, t.ty AS sample_type, t.pr AS protocol FROM u, (VALUES ('C', 'f'), ('D', 'f'), ('J', 'f'), ('C', 'p'), ('J', 'p')) AS t(ty, pr)),
x AS (SELECT *, CASE WHEN sample_type = 'D' THEN ask_d ELSE ask_c END AS asked, sample_type <> 'D' AND protocol = 'f' AND ask_c AND l1 AS hit1,
  sample_type <> 'D' AND CASE WHEN protocol = 'p' THEN l2 ELSE ask_c AND l1 AND l2 END AS hit2, sample_type = 'D' OR chain AS good FROM w),
t AS (SELECT agent, anchor_key, subtype, sample_type, protocol, asked, hit1, hit2, sample_type <> 'C' AND note AS rec,
  CASE WHEN good THEN pre ELSE alt END = pre AS ex1,
  sample_type <> 'C' AND CASE WHEN NOT note THEN CASE WHEN good THEN pre ELSE alt END WHEN NOT solve THEN wipe WHEN good THEN post ELSE altpost END = post AS ex2 FROM x),
z AS (SELECT *, ex1 AND (sample_type = 'C' OR ex2) AS ok FROM t WHERE protocol = 'f'),
d AS (SELECT agent, sample_type, round(avg(CAST(ok AS INT)), 6) AS dea FROM z GROUP BY agent, sample_type)
"""


def _avg(c: str, where: str | None = None) -> str:
    return f"avg(CASE WHEN {where} THEN CAST({c} AS INT) END)" if where else f"avg(CAST({c} AS INT))"


_PAIR = "(SELECT agent, anchor_key, " + ", ".join(f"max(CASE WHEN sample_type = '{k}' THEN CAST({e} AS INT) END) AS {n}_{k}" for k in "CDJ" for n, e in (("drr", "rec"), ("dra", "(rec AND ex2)"), ("dea", "ok"))) + " FROM z GROUP BY agent, anchor_key) y"

QUERIES = {
    f.__name__: f
    for f in (
        ex_family, dea_table, dea_marks, dea_spread, dea_ordering, ask_rate, ask_selectivity, layer_contrast, drift_recognition, recognition_gap, dra_by_subtype, joint_transition,
        joint_excess, failure_overlap, plain_execution, per_turn_ambiguity, pre_post_match, threshold_counts, size_classes, subtype_extremes, ask_correlation, dea_intervals, failure_phi,
    )
}
ORACLES = {
    "ex_family": _B + "SELECT anchor_key, subtype AS drift, CAST(pre = post AS INT) AS ex FROM r",
    "dea_table": _B + "SELECT agent, sample_type, subtype, count_if(ok) AS num, count(*) AS den, round(avg(CAST(ok AS INT)), 6) AS dea FROM z GROUP BY GROUPING SETS ((agent, sample_type, subtype), (agent, sample_type))",
    "dea_marks": _B + "SELECT agent, sample_type, dea, r AS rank_dense, CASE r WHEN 1 THEN 'best' WHEN 2 THEN 'second' ELSE '' END AS mark FROM (SELECT *, dense_rank() OVER (PARTITION BY sample_type ORDER BY dea DESC) AS r FROM d) y",
    "dea_spread": _B + "SELECT sample_type, max(dea) AS best, min(dea) AS worst, round(max(dea) - min(dea), 6) AS spread FROM d GROUP BY sample_type",
    "dea_ordering": _B + f"SELECT agent, {_avg('ok', 'sample_type = ' + repr('D'))} > {_avg('ok', 'sample_type = ' + repr('C'))} AND {_avg('ok', 'sample_type = ' + repr('C'))} > {_avg('ok', 'sample_type = ' + repr('J'))} AS ordered FROM z GROUP BY agent",
    "ask_rate": _B + f"SELECT agent, sample_type, count_if(asked) AS num, count(*) AS den, round({_avg('asked')}, 6) AS ar FROM z GROUP BY agent, sample_type",
    "ask_selectivity": _B + f"SELECT agent, round(c, 6) AS ar_chain, round(d, 6) AS ar_drift, round(c - d, 6) AS difference FROM (SELECT agent, {_avg('asked', 'sample_type = ' + repr('C'))} AS c, {_avg('asked', 'sample_type = ' + repr('D'))} AS d FROM z GROUP BY agent) y",
    "layer_contrast": _B + "SELECT agent, round(avg(CASE WHEN protocol = 'f' THEN CAST(hit1 AS INT) END), 6) AS l1_ir, round(avg(CASE WHEN protocol = 'p' THEN CAST(hit2 AS INT) END), 6) AS l2_ir_p, round(avg(CASE WHEN protocol = 'f' THEN CAST(hit1 AND hit2 AS INT) END), 6) AS jir FROM t WHERE sample_type = 'C' GROUP BY agent",
    "drift_recognition": _B + f"SELECT agent, sample_type, round({_avg('rec')}, 6) AS drr, round({_avg('(rec AND ex2)')}, 6) AS dra FROM z WHERE sample_type <> 'C' GROUP BY agent, sample_type",
    "recognition_gap": _B + f"SELECT agent, sample_type, round({_avg('rec')} - {_avg('(rec AND ex2)')}, 6) AS gap FROM z WHERE sample_type <> 'C' GROUP BY agent, sample_type",
    "dra_by_subtype": _B + f"SELECT subtype, agent, round(v, 6) AS dra, round(avg(v) OVER (PARTITION BY subtype), 6) AS subtype_mean, v = max(v) OVER (PARTITION BY subtype) AS is_max FROM (SELECT subtype, agent, {_avg('(rec AND ex2)')} AS v FROM z WHERE sample_type = 'D' GROUP BY subtype, agent) y",
    "joint_transition": _B + "SELECT agent, " + ", ".join(f"round(avg({n}_J) - avg({n}_D), 6) AS d_{n}" for n in ("drr", "dra", "dea")) + f" FROM {_PAIR} GROUP BY agent",
    "joint_excess": _B + f"SELECT agent, round(avg(dea_C) * avg(dea_D), 6) AS product, round(avg(dea_J), 6) AS joint, round(avg(dea_J) - avg(dea_C) * avg(dea_D), 6) AS excess FROM {_PAIR} GROUP BY agent",
    "failure_overlap": _B + f"""SELECT agent, a AS both_fail, b AS only_chain, c AS only_drift, n - a - b - c AS neither, round(CAST(a AS DOUBLE) * n / nullif((a + b) * (a + c), 0), 6) AS lift, round(CAST(a AS DOUBLE) / nullif(a + b + c, 0), 6) AS jaccard
    FROM (SELECT agent, count(*) AS n, count_if(dea_C = 0 AND dea_D = 0) AS a, count_if(dea_C = 0 AND dea_D = 1) AS b, count_if(dea_C = 1 AND dea_D = 0) AS c FROM {_PAIR} GROUP BY agent) q""",
    "plain_execution": _B + "SELECT agent, sample_type, count_if(CASE WHEN sample_type = 'C' THEN ex1 ELSE ex2 END) AS num, count(*) AS den, round(avg(CAST(CASE WHEN sample_type = 'C' THEN ex1 ELSE ex2 END AS INT)), 6) AS plain_ex FROM z GROUP BY agent, sample_type",
    "per_turn_ambiguity": _B + "SELECT agent, count_if(hit1) AS per_turn_l1_num, count(*) AS per_turn_l1_den, count_if(hit2) AS per_turn_l2_num, count(*) AS per_turn_l2_den FROM z WHERE sample_type <> 'D' GROUP BY agent",
    "pre_post_match": _B + "SELECT agent, sample_type, count_if(ex1) AS pre_ex, count_if(ex2) AS post_ex, count_if(NOT ex1 AND rec AND NOT ex2) AS inherited FROM z WHERE sample_type <> 'C' GROUP BY agent, sample_type",
    "threshold_counts": _B + """SELECT metric, level, count_if(value < level) AS n_below, min_by(agent, rank_lo) AS argmin, min_by(agent, rank_hi) AS argmax FROM (
      SELECT *, row_number() OVER (PARTITION BY metric ORDER BY value, agent) AS rank_lo, row_number() OVER (PARTITION BY metric ORDER BY value DESC, agent DESC) AS rank_hi FROM (
        SELECT agent, 'jir' AS metric, 0.05::DOUBLE AS level, avg(CASE WHEN sample_type <> 'D' THEN CAST(hit1 AND hit2 AS INT) END) AS value FROM z GROUP BY agent
        UNION ALL SELECT agent, 'drr', 0.949::DOUBLE, avg(CASE WHEN sample_type <> 'C' THEN CAST(rec AS INT) END) FROM z GROUP BY agent
        UNION ALL SELECT agent, 'dea', 0.46::DOUBLE, avg(CAST(ok AS INT)) FROM z GROUP BY agent) y) q GROUP BY metric, level""",
    "subtype_extremes": _B + f"""SELECT subtype, CAST(sum(e) AS BIGINT) AS easiest_for, CAST(sum(h) AS BIGINT) AS hardest_for FROM (
      SELECT subtype, CAST(row_number() OVER (PARTITION BY agent ORDER BY v DESC, subtype DESC) = 1 AS INT) AS e, CAST(row_number() OVER (PARTITION BY agent ORDER BY v, subtype) = 1 AS INT) AS h
      FROM (SELECT subtype, agent, {_avg('(rec AND ex2)')} AS v FROM z WHERE sample_type = 'D' GROUP BY subtype, agent) y) q GROUP BY subtype HAVING sum(e) + sum(h) > 0""",
    "ask_correlation": _B + f"SELECT round(corr(ar, jir), 6) AS correlation FROM (SELECT agent, {_avg('asked')} AS ar, {_avg('(hit1 AND hit2)')} AS jir FROM z WHERE sample_type = 'C' GROUP BY agent) y",
    "dea_intervals": _B + """SELECT agent, sample_type, round((p + 1.96 * 1.96 / (2 * n) - 1.96 * sqrt(p * (1 - p) / n + 1.96 * 1.96 / (4 * n * n))) / (1 + 1.96 * 1.96 / n), 6) AS low,
      round((p + 1.96 * 1.96 / (2 * n) + 1.96 * sqrt(p * (1 - p) / n + 1.96 * 1.96 / (4 * n * n))) / (1 + 1.96 * 1.96 / n), 6) AS high
      FROM (SELECT agent, sample_type, CAST(count(*) AS DOUBLE) AS n, avg(CAST(ok AS DOUBLE)) AS p FROM z GROUP BY agent, sample_type) y""",
    "failure_phi": _B + f"SELECT agent, round(CASE WHEN isnan(c) THEN NULL ELSE c END, 6) AS phi FROM (SELECT agent, CASE WHEN stddev_pop(dea_C) = 0 OR stddev_pop(dea_D) = 0 THEN NULL ELSE corr(1 - dea_C, 1 - dea_D) END AS c FROM {_PAIR} GROUP BY agent) q",
    "size_classes": _B + "SELECT sample_type, round(l, 6) AS large, round(s, 6) AS small, round(l - s, 6) AS difference FROM (SELECT sample_type, avg(CASE WHEN agent IN ('gold', 'steady') THEN dea END) AS l, avg(CASE WHEN agent NOT IN ('gold', 'steady') THEN dea END) AS s FROM d GROUP BY sample_type) y",
}
