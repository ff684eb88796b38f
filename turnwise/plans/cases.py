"""Case study analog: disappointing orders in a range of years, and runs of the scripted agents on it.

First layer: late shipping or heavy discount; second: judged on the whole order or on a single line. The gold
reads heavy discount on the whole order (mean line discount over 0.07); the chain error takes any line over 0.07.
The drift withdraws the range of years.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import drift
from ..operators import agents, analysis, commitments, execmatch, harness, metrics, trajectory
from ..sources.io import table
from .common import r6

YEARS = (1996, 1997)
GOLD = "SELECT o_orderkey FROM case_orders WHERE mean_discount > 0.07 AND o_year BETWEEN 1996 AND 1997"
GOLD_POST = "SELECT o_orderkey FROM case_orders WHERE mean_discount > 0.07"
ERROR = "SELECT o_orderkey FROM case_orders WHERE max_discount > 0.07 AND o_year BETWEEN 1996 AND 1997"
ERROR_POST = "SELECT o_orderkey FROM case_orders WHERE max_discount > 0.07"


def case_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    """o_orderkey, o_year, mean_discount (of whole percents, so that the sum is exact), max_discount."""
    percent = F.round(F.col("l_discount") * 100).cast("long")
    per = table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.sum(percent).alias("s"), F.count("*").alias("n"), F.max(percent).alias("m"))
    orders = table(spark, sf_dir, "orders").select("o_orderkey", F.year("o_orderdate").alias("o_year"))
    return per.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).select("o_orderkey", "o_year", (F.col("s") / (F.col("n") * 100)).alias("mean_discount"), (F.col("m") / 100).alias("max_discount"))


def case_gold_pre(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = case_orders(spark, sf_dir)
    return c.filter((F.col("mean_discount") > 0.07) & F.col("o_year").between(*YEARS)).select(F.col("o_orderkey").alias("order_key"))


def case_gold_post(spark: SparkSession, sf_dir: str) -> DataFrame:
    return case_orders(spark, sf_dir).filter("mean_discount > 0.07").select(F.col("o_orderkey").alias("order_key"))


def samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = [
        ("case", t, drift.CONSTRAINT, "Which orders were disappointing in 1996 and 1997?", "Does disappointing mean late shipping or heavy discount?", "Heavy discount.",
         "Is the discount taken over whole orders, or may one single line decide?", "Over whole orders.", "Forget the years, I want all of them.", GOLD, GOLD_POST, ERROR, ERROR_POST)
        for t in ("C", "D", "J")
    ]
    return spark.createDataFrame(rows, ", ".join(f"{c} string" for c in harness.SAMPLE_COLUMNS))


def scored_runs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Trajectories of all scripted agents: turns are played, folded, their queries run once each and compared with the gold."""
    case_orders(spark, sf_dir).createOrReplaceTempView("case_orders")
    turns = harness.run(samples(spark, sf_dir), list(agents.SCRIPTED))
    folded = trajectory.fold(trajectory.with_drift_turn(turns))
    parts = F.split("run_id", r"\|")
    runs = folded.select("run_id", F.get(parts, F.lit(1)).alias("sample_type"), F.get(parts, F.lit(2)).alias("agent"), F.get(parts, F.lit(3)).alias("protocol"), "asked", "rho", "sql_pre", "sql_post")
    texts = runs.select(F.explode(F.array("sql_pre", "sql_post")).alias("q")).dropna().distinct()
    queries = sorted(r[0] for r in texts.collect())  # bounded by agents x samples x 2, as the samples are three
    ex = execmatch.batch(spark, [(f"{q}#{name}", q, g) for q in queries for name, g in (("pre", GOLD), ("post", GOLD_POST))], {"case_orders"})
    ex = ex.select(F.split("pair_id", "#").alias("p"), "ex").select(F.get("p", F.lit(0)).alias("q"), F.get("p", F.lit(1)).alias("side"), "ex")
    side = lambda s: ex.filter(F.col("side") == s).select(F.col("q").alias(f"sql_{s}"), F.col("ex").alias(f"ex_{s}"))
    joined = runs.join(side("pre"), "sql_pre", "left").join(side("post"), "sql_post", "left")
    sets = commitments.extract_distinct(joined, ["sql_pre", "sql_post"])
    chained = F.col("sample_type") == "C"
    known = F.col("sql_pre_error").isNull() & F.col("sql_post_error").isNull()
    return sets.select(
        "run_id", "agent", F.lit("case").alias("anchor_id"), "sample_type", F.lit(drift.CONSTRAINT).alias("subtype"), "protocol", F.when(chained, 1).otherwise(2).alias("n_targets"), "asked", "rho",
        F.when(chained, F.array(F.coalesce("ex_pre", F.lit(0)))).otherwise(F.array(F.coalesce("ex_pre", F.lit(0)), F.coalesce("ex_post", F.lit(0)))).alias("ex"),
        F.when(~chained, F.coalesce(known & drift.is_drift(F.col("sql_pre_items"), F.col("sql_post_items")), F.lit(False))).alias("rec"),
    )


def scripted_metrics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every measure of every scripted agent on the case's three samples."""
    m = metrics.all_metrics(scored_runs(spark, sf_dir), ["agent", "sample_type"]).filter("den > 0")
    return m.select("agent", "sample_type", "metric", "num", "den", r6(F.col("value")).alias("value"))


MEASURES = ("dea", "ar", "l1_ir", "l2_ir_p", "jir", "drr", "dra")


def scripted_closed_form(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The seven measures of the harness's runs, for comparison with what each agent's behaviour implies."""
    return scripted_metrics(spark, sf_dir).filter(F.col("metric").isin(*MEASURES))


def case_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages of the Joint run that inherits its chain error: first layer met, second missed, drift noticed, both queries wrong."""
    t = scored_runs(spark, sf_dir).filter("agent = 'inherit_chain_error' AND sample_type = 'J' AND protocol = 'f'")
    flags = [("first_layer", F.array_contains("rho", "L1")), ("second_layer", F.array_contains("rho", "L2")), ("pre_ex", F.get("ex", F.lit(0)) == 1), ("recognised", F.col("rec")), ("post_ex", F.get("ex", F.lit(1)) == 1), ("inherited_error", analysis.inherited_error(F.col("rec"), F.col("ex")))]
    return t.select(F.inline(F.array(*[F.struct(F.lit(n).alias("step"), f.cast("int").alias("flag")) for n, f in flags])))


def ex_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exact match, as multisets and as sets, of pairs of results of known relation."""
    lines = table(spark, sf_dir, "lineitem").select("l_returnflag", "l_linestatus", "l_quantity")
    some = lines.filter("l_quantity > 45")
    pairs = {
        "same": (some, some.orderBy("l_quantity")), "renamed": (some, some.toDF("a", "b", "c")), "swapped": (some, some.select("l_linestatus", "l_returnflag", "l_quantity")),
        "duplicated": (some.distinct(), some), "fewer_columns": (some, some.drop("l_quantity")), "both_empty": (some.filter("false"), some.filter("l_quantity > 1000")),
        "noise": (some, some.withColumn("l_quantity", F.col("l_quantity") + F.lit(1e-12))), "filtered": (some, some.filter("l_quantity > 46")),
        "large_integers": (some.withColumn("k", F.lit(9007199254740992)), some.withColumn("k", F.lit(9007199254740993))), "decimals": (some, some.withColumn("l_quantity", F.col("l_quantity").cast("decimal(12,3)"))),
    }
    rows = [(n, int(execmatch.exact(a, b)), int(execmatch.exact(a, b, bag=False)), int(execmatch.same_fingerprint(a, b))) for n, (a, b) in pairs.items()]
    return spark.createDataFrame(rows, "pair string, ex_bag int, ex_set int, ex_fingerprint int")


def _closed_form() -> str:
    """Every measure of every scripted agent on one sample of each type, from what the agent is known to do."""
    asks = {"gold": (1, 1, 1), "ask_both": (1, 1, 1), "ask_l1_only": (1, 1, 0), "inherit_chain_error": (1, 1, 0), "ask_everything": (1, 0, 0)}  # chained types: asked, first layer, second layer
    pre = {"gold": "CDJ", "ask_both": "CDJ", "accumulate": "CDJ", "ignore_drift": "CDJ", "wipe_filters": "CDJ", "wrong_target": "CDJ", "broken_sql": ""}  # types with the right first query; the others: D alone
    post = {"gold": "DJ", "ask_both": "DJ", "accumulate": "", "ignore_drift": "", "wipe_filters": "", "wrong_target": "", "broken_sql": ""}  # and the right last one; the others: D alone
    rec = {"accumulate": "", "ignore_drift": "", "broken_sql": ""}  # notices the withdrawal; the others: both
    rows = []
    for a in agents.SCRIPTED:
        asked, one, two = asks.get(a, (0, 0, 0))
        for ty in "CDJ":
            first, last, seen = ty in pre.get(a, "D"), ty in post.get(a, "D"), ty in rec.get(a, "DJ")
            rows.append((a, ty, "dea", int(first and (ty == "C" or last))))
            rows.append((a, ty, "ar", asked if ty != "D" or a == "ask_everything" else 0))
            rows += [(a, ty, "l1_ir", one), (a, ty, "l2_ir_p", two), (a, ty, "jir", int(one and two))] if ty != "D" else []
            rows += [(a, ty, "drr", int(seen)), (a, ty, "dra", int(seen and last))] if ty != "C" else []
    values = ", ".join(f"('{a}', '{ty}', '{m}', {n})" for a, ty, m, n in rows)
    return f"SELECT agent, sample_type, metric, CAST(n AS BIGINT) AS num, CAST(1 AS BIGINT) AS den, CAST(n AS DOUBLE) AS value FROM (VALUES {values}) AS t(agent, sample_type, metric, n)"


_G = """
WITH g AS (SELECT o_orderkey, year(o_orderdate) AS y, sum(CAST(round(l_discount * 100) AS BIGINT)) AS s, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderkey, year(o_orderdate))
"""
QUERIES = {f.__name__: f for f in (case_gold_pre, case_gold_post, case_trace, scripted_metrics, scripted_closed_form, ex_exact)}
ORACLES = {
    "case_gold_pre": _G + "SELECT o_orderkey AS order_key FROM g WHERE s > 7 * n AND y BETWEEN 1996 AND 1997",
    "case_gold_post": _G + "SELECT o_orderkey AS order_key FROM g WHERE s > 7 * n",
    "scripted_closed_form": _closed_form(),
    "case_trace": "SELECT * FROM (VALUES ('first_layer', 1), ('second_layer', 0), ('pre_ex', 0), ('recognised', 1), ('post_ex', 0), ('inherited_error', 1)) AS t(step, flag)",
    "ex_exact": """WITH src AS (SELECT l_returnflag AS a, l_linestatus AS b, l_quantity AS c FROM lineitem WHERE l_quantity > 45),
      one AS (SELECT a, b, c, 0::BIGINT AS k FROM src), d AS (SELECT DISTINCT a, b, c, k FROM one), o AS (SELECT b AS a, a AS b, c, k FROM one), f AS (SELECT * FROM one WHERE c > 46),
      l AS (SELECT a, b, c, 9007199254740992::BIGINT AS k FROM src), m AS (SELECT a, b, c, 9007199254740993::BIGINT AS k FROM src),
      n(pair, bag_out, bag_in, set_out, set_in) AS ("""
    + " UNION ALL ".join(
        f"SELECT '{n}', (SELECT count(*) FROM (SELECT * FROM {x} EXCEPT ALL SELECT * FROM {y}) p), (SELECT count(*) FROM (SELECT * FROM {y} EXCEPT ALL SELECT * FROM {x}) p), (SELECT count(*) FROM (SELECT * FROM {x} EXCEPT SELECT * FROM {y}) p), (SELECT count(*) FROM (SELECT * FROM {y} EXCEPT SELECT * FROM {x}) p)"
        for n, x, y in (("same", "one", "one"), ("renamed", "one", "one"), ("swapped", "one", "o"), ("duplicated", "d", "one"), ("noise", "one", "one"), ("filtered", "one", "f"), ("large_integers", "l", "m"), ("decimals", "one", "one"))
    )
    + """) SELECT pair, CAST(bag_out + bag_in = 0 AS INT) AS ex_bag, CAST(set_out + set_in = 0 AS INT) AS ex_set, CAST(bag_out + bag_in = 0 AS INT) AS ex_fingerprint FROM n
      UNION ALL SELECT 'fewer_columns', 0, 0, 0 UNION ALL SELECT 'both_empty', 1, 1, 1""",
}
