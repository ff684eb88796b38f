"""The construction pipeline on SQL anchors: every stage checks the texts, their results or the data.

Candidates are the anchors of the catalogue as SQL text, and two families that have to be dropped: one that names a
column that does not exist, one without enough structure. A candidate passes when its text runs, has enough structure
and supports a drift; when both judges let its chain pass (the second layer is the words of a part's name, the other
reading supplies those of the next part; one judge looks at all words, the other at the noun); when its drift pair
parses, differs in result, withdraws something, is of the assigned subtype and leaves the rest alone; and when both
cross-checks (scope of the change, and the shape of the query in strict mode) agree. Tiers come from the score.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import chain, complexity, drift
from ..operators import commitments, construct, panel, sampling, validate
from ..sources.io import cut, register
from . import agents_grid, anchors, panels, sql_anchors
from .common import luck, luck_sql

STAGES = ("executable", "structure", "drift_supported", "chain_judges", "pair_checks", "cross_validation")
#: Parts that chains are drawn from: as many as the smallest catalogue has.
PARTS = 199
CUTS = (10, 11)
_BROKEN = "SELECT c_custkey, c_region FROM customer WHERE c_mktsegment = '{segment}' AND c_acctbal > 100"
_FLAT = "SELECT o_orderkey FROM orders WHERE o_orderstatus = '{status}'"


def candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """anchor_key, family, sql, and sql_<kind> of the later texts where the family has some."""
    pool = anchors.facts(spark, sf_dir).select(*anchors.PARAMETERS).distinct()
    _, text, later = sql_anchors.TEMPLATES["flags"]
    kinds = [drift.VALUE, drift.CONSTRAINT, drift.PROJECTION]
    named = pool.select(anchors.key_of().alias("anchor_key"), F.lit("flags").alias("family"), sql_anchors.bound(text).alias("sql"), *[sql_anchors.bound(later[k]).alias(f"sql_{k}") for k in kinds])
    none = [F.lit(None).cast("string").alias(f"sql_{k}") for k in kinds]
    blank = pool.withColumns({"priority": F.lit(""), "year": F.lit(0)})
    broken = blank.withColumn("status", F.lit("")).distinct().select(F.concat(F.lit("broken/"), "segment").alias("anchor_key"), F.lit("broken").alias("family"), sql_anchors.bound(_BROKEN).alias("sql"), *none)
    flat = blank.withColumn("segment", F.lit("")).distinct().select(F.concat(F.lit("flat/"), "status").alias("anchor_key"), F.lit("flat").alias("family"), sql_anchors.bound(_FLAT).alias("sql"), *none)
    return named.unionByName(broken).unionByName(flat)


def chain_votes(spark: SparkSession, sf_dir: str, keys: DataFrame) -> DataFrame:
    """anchor_key, judge, verdict: the chain of a part drawn by hash, seen by two judges."""
    drawn = keys.select("anchor_key", (F.lit(1) + luck("part", F.col("anchor_key")) % PARTS).alias("part_key"))
    seen = panels.layer_terms(spark, sf_dir).join(drawn, "part_key")
    noun = F.slice("needs", F.size("needs"), F.lit(1))
    verdicts = {"words": chain.counterfactual(F.col("needs"), F.col("supplies")), "noun": chain.counterfactual(noun, F.col("supplies"))}
    return seen.select("anchor_key", F.inline(F.array(*[F.struct(F.lit(j).alias("judge"), v.alias("verdict")) for j, v in verdicts.items()])))


def judged(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every candidate with a flag for each stage, the assigned subtype, both texts, the verdict and the tier."""
    register(spark, sf_dir)  # what the texts name
    # Cut, as several branches read it: one row a combination of parameters, however many facts there are. Rows that are
    # only cached would keep their plan inside every plan that reads them, and descriptions of that fill the driver.
    read = cut(commitments.extract_distinct(candidates(spark, sf_dir), ["sql"]))
    runs = construct.executable_families(read, spark).withColumn("executable", F.lit(True))
    read = read.join(F.broadcast(runs), "family", "left").withColumn("structure", construct.complex_enough(F.col("sql_items"))).withColumn("drift_supported", construct.supports_drift(F.col("sql_items")))
    ready = read.filter("executable AND structure AND drift_supported")
    assigned = construct.assign_subtype(ready, "sql_items", "anchor_key")
    post = F.lit(None).cast("string")
    for kind in (drift.VALUE, drift.CONSTRAINT, drift.PROJECTION):
        post = F.when(F.col("subtype") == kind, F.col(f"sql_{kind}")).otherwise(post)
    pairs = commitments.extract_distinct(cut(assigned.select("anchor_key", "subtype", F.col("sql").alias("pre"), post.alias("post"))), ["pre", "post"])
    results = agents_grid.results(spark, sf_dir).select("anchor_key", "fp_pre", "fp_post")
    checked = validate.check_pairs(pairs.join(results, "anchor_key", "left"), F.col("fp_pre") != F.col("fp_post"))
    strict = cut(commitments.extract_distinct(cut(checked.select("anchor_key", "pre", "post", "subtype", "pre_items", "post_items", "dropped_at").withColumnsRenamed({"pre_items": "a", "post_items": "b"})), ["pre", "post"], strict=True))
    shape = lambda c: F.filter(c, lambda x: x["kind"] == "SHAPE")
    votes = strict.select("anchor_key", F.explode(F.array(validate.preserved(F.col("a"), F.col("b"), F.col("subtype")), drift.same_set(shape(F.col("pre_items")), shape(F.col("post_items"))))).alias("good"))
    crossed = panel.consensus(votes, "anchor_key", F.col("good")).select("anchor_key", F.col("accepted").alias("cross_validation"))
    chains = cut(chain_votes(spark, sf_dir, ready))
    agreed = panel.consensus(chains, "anchor_key", chain.qualifies(F.col("verdict"))).select("anchor_key", F.col("accepted").alias("chain_judges"))
    verdict = chains.filter("judge = 'words'").select("anchor_key", "verdict")
    pairs_ok = strict.select("anchor_key", "subtype", "post", F.col("dropped_at").isNull().alias("pair_checks"))
    out = read.select("anchor_key", "family", F.col("sql").alias("pre"), F.col("sql_items").alias("items"), "executable", "structure", "drift_supported")
    for part in (pairs_ok, crossed, agreed, verdict):
        out = out.join(part, "anchor_key", "left")
    return cut(out.withColumn("tier", complexity.tier(complexity.score(F.col("items"), F.col("verdict"), F.col("subtype")), CUTS)))


def pipeline_funnel(spark: SparkSession, sf_dir: str) -> DataFrame:
    f = construct.funnel(judged(spark, sf_dir), {name: F.col(name) for name in STAGES})
    return f.select("stage", "entered", "kept", F.round("rate", 6).alias("rate"), F.round("cumulative", 6).alias("cumulative"))


def survivors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged(spark, sf_dir).filter(" AND ".join(STAGES))


def samples(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Triplets of the survivors: their chain and drift branches joined again, then expanded."""
    s = survivors(spark, sf_dir)
    chains, drifts = s.select("anchor_key", "verdict", "tier"), s.select("anchor_key", "subtype", "pre", "post")
    return construct.assemble(chains, drifts, "anchor_key")


def triplets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return samples(spark, sf_dir).select("anchor_key", "sample_type", F.col("n_targets").cast("int").alias("n_targets"), F.length("pre").alias("pre_chars"), F.length("post").alias("post_chars"))


def triplet_violations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return validate.triplets(samples(spark, sf_dir))


def triplet_violations_planted(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One kind of damage by the year of the anchor: a lost sample, or the anchor's own text as the joint one's later query."""
    s = samples(spark, sf_dir).withColumn("year", F.element_at(F.split("anchor_key", "/"), -1).cast("int"))
    joint = F.col("sample_type") == "J"
    s = s.filter(~((F.col("year") == 1996) & joint)).withColumn("post", F.when((F.col("year") == 1997) & joint, F.col("pre")).otherwise(F.col("post")))
    return validate.triplets(s)


def dataset_shares(spark: SparkSession, sf_dir: str) -> DataFrame:
    return construct.shares(survivors(spark, sf_dir), ["subtype", "verdict", "tier"]).withColumn("share", F.round("share", 6))


def audit_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Triplets for a human audit, balanced over subtype, verdict and tier: how many of each stratum and type."""
    s = samples(spark, sf_dir).withColumnRenamed("anchor_key", "anchor_id")
    picked = sampling.audit_triplets(s, ["subtype", "verdict", "tier"], 100)
    return picked.groupBy("sample_type", "subtype", "verdict", "tier").agg(F.count("*").alias("n"))


_J = f"""{agents_grid._B},
p AS (SELECT p_partkey, list_distinct(string_split(p_name, ' ')) AS needs, string_split(p_name, ' ')[-1] AS noun, string_split(lead(p_name) OVER (ORDER BY p_partkey), ' ') AS nxt FROM part),
v AS (SELECT p_partkey, CASE len(list_intersect(needs, nxt)) WHEN 0 THEN 'eliminated' WHEN len(needs) THEN 'invariant' ELSE 'transformed' END AS verdict, NOT list_contains(nxt, noun) AS noun FROM p WHERE nxt IS NOT NULL),
j AS (SELECT a.anchor_key, a.year, a.subtype, a.segment, a.priority, a.status, v.verdict, v.verdict <> 'invariant' AND v.noun AS s4, r.pre <> r.post AS s5,
    9 + CASE v.verdict WHEN 'eliminated' THEN 1 WHEN 'transformed' THEN 2 ELSE 0 END + CASE WHEN a.subtype = 'value' THEN 0 ELSE 1 END AS score
  FROM a JOIN r ON a.anchor_key = r.anchor_key LEFT JOIN v ON v.p_partkey = 1 + {luck_sql("'part'", 'a.anchor_key')} % {PARTS}),
k AS (SELECT *, CASE WHEN score <= 10 THEN 'basic' WHEN score <= 11 THEN 'intermediate' ELSE 'advanced' END AS tier FROM j WHERE s4 AND s5),
n AS (SELECT count(*) AS flags, count_if(s4) AS chained, count_if(s4 AND s5) AS whole, (SELECT count(DISTINCT segment) FROM a) AS broken, (SELECT count(DISTINCT status) FROM a) AS flat FROM j)
"""
_COUNTS = ["flags + broken + flat", "flags + flat", "flags", "flags", "chained", "whole", "whole"]
#: Lengths of the texts, from the lengths of the parameters.
_PLAIN = {k: len(t.replace("{segment}", "").replace("{priority}", "").replace("{status}", "").replace("{year}", "").replace("{next}", "")) for k, t in {"pre": sql_anchors.TEMPLATES["flags"][1], **sql_anchors.TEMPLATES["flags"][2]}.items()}
_OWN = "length(segment) + length(priority) + 4"
QUERIES = {f.__name__: f for f in (pipeline_funnel, triplets, triplet_violations, triplet_violations_planted, dataset_shares, audit_sample)}
ORACLES = {
    "pipeline_funnel": _J
    + " UNION ALL ".join(
        f"SELECT '{s}' AS stage, {_COUNTS[i]} AS entered, {_COUNTS[i + 1]} AS kept, round(({_COUNTS[i + 1]}) * 1.0 / ({_COUNTS[i]}), 6) AS rate, round(({_COUNTS[i + 1]}) * 1.0 / ({_COUNTS[0]}), 6) AS cumulative FROM n" for i, s in enumerate(STAGES)
    ),
    "triplets": _J
    + f"""SELECT anchor_key, t AS sample_type, CASE WHEN t = 'C' THEN 1 ELSE 2 END AS n_targets, {_PLAIN['pre']} + {_OWN} + length(status) AS pre_chars,
      CASE subtype WHEN 'value' THEN {_PLAIN['value']} + length(status) WHEN 'constraint' THEN {_PLAIN['constraint']} ELSE {_PLAIN['projection']} + length(status) END + {_OWN} AS post_chars FROM k, (SELECT unnest(['C', 'D', 'J']) AS t) y""",
    "triplet_violations": _J + "SELECT anchor_key, 'types' AS reason FROM k WHERE false",
    "triplet_violations_planted": _J + "SELECT anchor_key, CASE WHEN year = 1996 THEN 'types' ELSE 'post' END AS reason FROM k WHERE year IN (1996, 1997)",
    "dataset_shares": _J
    + " UNION ALL ".join(f"SELECT '{c}' AS dimension, {c} AS level, count(*) AS n, round(count(*) * 1.0 / (SELECT count(*) FROM k), 6) AS share FROM k GROUP BY {c}" for c in ("subtype", "verdict", "tier")),
    "audit_sample": _J
    + """SELECT t AS sample_type, subtype, verdict, tier, least(n, CAST(base AS BIGINT) + CASE WHEN row_number() OVER (PARTITION BY t ORDER BY exact - base DESC, subtype, verdict, tier) <= 100 - sum(base) OVER (PARTITION BY t) THEN 1 ELSE 0 END) AS n
    FROM (SELECT subtype, verdict, tier, n, 100.0 * n / sum(n) OVER () AS exact, floor(100.0 * n / sum(n) OVER ()) AS base FROM (SELECT subtype, verdict, tier, count(*) AS n FROM k GROUP BY subtype, verdict, tier) x) y, (SELECT unnest(['C', 'D', 'J']) AS t) z""",
}
