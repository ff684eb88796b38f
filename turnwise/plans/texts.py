"""Router check on benchmark passages, evidence rewriting, page titles as utterances, vectors as a semantic router."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import chain, evidence, simulator
from ..operators import harness, panel
from ..sources.io import table
from .common import luck, luck_sql, r6

#: A passage counts as asked about when the document has this share of its terms.
COVERAGE = 0.8
#: Reference vectors that may be broadcast; beyond that they are an error, as each vector is compared with each of them.
MOST_LABELS = 10_000


def _items(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("passage"))


def _opening(words: F.Column) -> F.Column:
    return F.array_join(F.slice(words, F.lit(1), F.lit(5)), " ")


def router_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Documents that hold a passage whole: even items are the first layer's question, odd ones the second's.

    A passage's five inner words at its start are joined with the documents' runs of five words, an equi-join that scales
    with the texts; only pairs that meet are searched for the passage. Passages of fewer than seven words, whose first and last
    word may be parts of longer ones in a document, are compared by the words that are whole, or with every document if none is.
    """
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    items = _items(spark, sf_dir).withColumn("inner", F.slice(F.split("passage", r"\s+"), F.lit(2), F.greatest(F.size(F.split("passage", r"\s+")) - 2, F.lit(0))))
    layer = F.when(F.col("item_id") % 2 == 0, simulator.L1).otherwise(simulator.L2)
    long = items.filter(F.size("inner") >= 5).select("item_id", "passage", _opening(F.col("inner")).alias("run"))
    words = docs.withColumn("w", F.split("text", r"\s+")).filter(F.size("w") >= 5)
    runs = words.select("doc_id", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - 4), lambda i: F.array_join(F.slice("w", i, F.lit(5)), " ")))).alias("run"))
    met = runs.join(long.select("run").distinct(), "run", "left_semi").join(long.select("run", "item_id"), "run").select("doc_id", "item_id").distinct()
    held = met.join(long.select("item_id", "passage"), "item_id").join(docs, "doc_id").filter(F.contains("text", F.col("passage")))
    short = items.filter(F.size("inner") < 5).select("item_id", "passage")
    if not short.isEmpty():
        held = held.select("doc_id", "item_id").unionByName(docs.join(short, F.contains("text", F.col("passage"))).select("doc_id", "item_id"))
    return held.select("doc_id", "item_id", layer.alias("rho"))


def best_items(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, item, s: the item of which a document covers the largest share of terms, for shares of COVERAGE and more.

    A document that covers that share of an item's n terms has one of any n - ceil(COVERAGE n) + 1 of them: the rarest
    among the items are joined first, and only pairs that meet there are counted on all terms.
    """
    docs = table(spark, sf_dir, "documents").select("doc_id", chain.terms(F.col("text")).alias("said"))
    items = _items(spark, sf_dir).select("item_id", chain.terms(F.col("passage")).alias("asked")).withColumn("n", F.size("asked"))
    terms = items.select("item_id", "n", F.explode("asked").alias("term"))
    common = terms.groupBy("term").agg(F.count("*").alias("items"))
    rank = F.row_number().over(Window.partitionBy("item_id").orderBy("items", "term"))
    rare = terms.join(common, "term").withColumn("rank", rank).filter(F.col("rank") <= F.col("n") - F.ceil(F.col("n") * COVERAGE - 1e-9) + 1).select("item_id", "term")
    said = docs.select("doc_id", F.explode("said").alias("term"))
    met = said.join(rare, "term").select("doc_id", "item_id").distinct()
    scored = met.join(items, "item_id").join(docs, "doc_id").select("doc_id", "item_id", simulator.coverage(F.col("asked"), F.col("said")).alias("s")).filter(F.col("s") >= COVERAGE)
    return scored.groupBy("doc_id").agg(F.max_by("item_id", F.struct("s", -F.col("item_id"))).alias("item"), F.max("s").alias("s"))


def routed_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, truth, routed: the token router (coverage of the passage's terms) against the passages that documents really hold."""
    layer = F.when(F.col("item") % 2 == 0, simulator.L1).otherwise(simulator.L2)
    best = best_items(spark, sf_dir).select("doc_id", layer.alias("routed"))
    truth = router_labels(spark, sf_dir).groupBy("doc_id").agg(F.min("rho").alias("truth"))
    both = table(spark, sf_dir, "documents").select("doc_id").join(best, "doc_id", "left").join(truth, "doc_id", "left")
    return both.select("doc_id", *[F.coalesce(c, F.lit(simulator.OTHER)).alias(c) for c in ("truth", "routed")])


def router_confusion(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simulator.validate(routed_documents(spark, sf_dir))


def router_kappa(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Agreement of router and truth as two raters."""
    votes = routed_documents(spark, sf_dir).select("doc_id", F.explode(F.array("truth", "routed")).alias("v"))
    return panel.fleiss_kappa(votes, "doc_id", "v").select("n", r6(F.col("kappa")).alias("kappa"))


def router_panel(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Five raters of the router's labels: the truth, and in a few documents, drawn by hash of rater and document, another layer."""
    rater = F.explode(F.sequence(F.lit(1), F.lit(5)))
    votes = routed_documents(spark, sf_dir).select("doc_id", "truth", rater.alias("rater"))
    other = F.when(F.col("truth") == simulator.L1, simulator.L2).otherwise(simulator.L1)
    said = F.when(luck("rater", F.col("rater"), F.col("doc_id")) < 500, other).otherwise(F.col("truth"))
    return panel.fleiss_kappa(votes.select("doc_id", said.alias("v")), "doc_id", "v").select("n", r6(F.col("kappa")).alias("kappa"))


def routed_turns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The router and responder over dialogue turns: the first and second user turns are the layers' questions, each assistant turn is
    routed with the second layer open from the second assistant turn on; labels, replies and acts counted."""
    turns = table(spark, sf_dir, "conversations").filter("role <> 'system'")
    n = F.row_number().over(Window.partitionBy("conv_id", "role").orderBy("turn"))
    numbered = turns.withColumn("n", n)
    asked = numbered.filter("role = 'user' AND n <= 2").groupBy("conv_id").agg(*[F.max(F.when(F.col("n") == k, F.col("text"))).alias(f"q{k}") for k in (1, 2)])
    said = numbered.filter("role = 'assistant'").join(asked, "conv_id")
    rho = simulator.route(chain.terms(F.col("text")), chain.terms(F.col("q1")), chain.terms(F.col("q2")), F.col("n") > 1, threshold=0.1)
    rows = said.select(rho.alias("rho"), harness.act(F.col("text")).alias("act"), F.col("q1"), F.col("q2"))
    answer = simulator.reply(F.col("rho"), F.col("q1"), F.col("q2"))
    return rows.withColumn("chars", F.length(answer)).groupBy("rho", "act").agg(F.count("*").alias("n"), F.sum("chars").alias("reply_chars"))


def evidence_redact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clauses that hold the first term of a benchmark passage of the document's parity are dropped, unless they hold a digit."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", (F.col("doc_id") % 2).alias("parity"))
    terms = _items(spark, sf_dir).groupBy((F.col("item_id") % 2).alias("parity")).agg(F.array_sort(F.collect_set(F.element_at(F.split("passage", " "), 2))).alias("giveaway"))
    digits = F.array(*[F.lit(str(i)) for i in range(10)])
    joined = docs.join(F.broadcast(terms), "parity")
    text = F.replace("text", F.lit("\n"), F.lit(" "))
    kept = evidence.redact(text, F.col("giveaway"), digits, breaks=r"\. ")
    all_clauses = F.size(evidence.clauses(text, r"\. "))
    return joined.select("doc_id", F.length(kept).cast("long").alias("kept_chars"), all_clauses.cast("long").alias("clauses"))


def page_utterances(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("html", "(?i)<title>([^<]*)</title>", 1).alias("title"))


def vector_router(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nearest reference vector (the first vector of each label) by cosine, for every vector."""
    e = table(spark, sf_dir, "embeddings")
    firsts = e.groupBy("label").agg(F.min("vec_id").alias("vec_id"))
    if firsts.limit(MOST_LABELS + 1).count() > MOST_LABELS:
        raise ValueError("too many labels to compare every vector with")
    refs = firsts.join(e.select("vec_id", F.col("embedding").alias("ref")), "vec_id").select(F.col("vec_id").alias("ref_id"), "ref")
    near = e.select("vec_id", "embedding").crossJoin(F.broadcast(refs)).select("vec_id", "ref_id", simulator.cosine(F.col("embedding"), F.col("ref")).alias("c"))
    return near.groupBy("vec_id").agg(F.max_by("ref_id", F.struct("c", -F.col("ref_id"))).alias("nearest"), F.round(F.max("c"), 4).alias("cosine"))


QUERIES = {f.__name__: f for f in (router_labels, router_confusion, router_kappa, router_panel, routed_turns, evidence_redact, page_utterances, vector_router)}
_W = """
WITH d AS (SELECT doc_id, text, list_distinct(list_filter(string_split_regex(lower(text), '[^a-z0-9]+'), lambda w: w <> '')) AS said FROM documents),
b AS (SELECT item_id, text, list_distinct(list_filter(string_split_regex(lower(text), '[^a-z0-9]+'), lambda w: w <> '')) AS asked FROM benchmark),
s AS (SELECT doc_id, item_id, CASE WHEN len(asked) = 0 THEN 0.0 ELSE len(list_intersect(asked, said)) * 1.0::DOUBLE / len(asked) END AS s FROM d, b),
r AS (SELECT doc_id, CASE WHEN s < 0.8 THEN 'Other' WHEN item_id % 2 = 0 THEN 'L1' ELSE 'L2' END AS routed FROM (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY s DESC, item_id) AS k FROM s) x WHERE k = 1),
t AS (SELECT doc_id, min(CASE WHEN item_id % 2 = 0 THEN 'L1' ELSE 'L2' END) AS truth FROM d JOIN b ON contains(d.text, b.text) GROUP BY doc_id),
c AS (SELECT coalesce(truth, 'Other') AS truth, routed FROM r LEFT JOIN t ON r.doc_id = t.doc_id)
"""
ORACLES = {
    "router_confusion": _W + "SELECT truth, routed, count(*) AS n FROM c GROUP BY truth, routed",
    "router_kappa": _W + """, q AS (SELECT sum(y * y) AS pe FROM (SELECT count(*) * 1.0::DOUBLE / (SELECT 2 * count(*) FROM c) AS y FROM (SELECT truth AS v FROM c UNION ALL SELECT routed FROM c) u GROUP BY v) z)
    SELECT count(*) AS n, round((avg(CAST(truth = routed AS INT)) - max(pe)) / (1 - max(pe)), 6) AS kappa FROM c, q""",
    "router_panel": _W + f""", v AS (SELECT doc_id, CASE WHEN {luck_sql("'rater'", 'CAST(k AS VARCHAR)', 'CAST(doc_id AS VARCHAR)')} < 500 THEN CASE WHEN truth = 'L1' THEN 'L2' ELSE 'L1' END ELSE truth END AS v
      FROM (SELECT d.doc_id, coalesce(truth, 'Other') AS truth FROM documents d LEFT JOIN t ON d.doc_id = t.doc_id) x, (SELECT unnest(range(1, 6)) AS k) y),
    m AS (SELECT doc_id, v, count(*) AS c FROM v GROUP BY doc_id, v), o AS (SELECT avg(p) AS p, count(*) AS n FROM (SELECT doc_id, sum(c * (c - 1)) / 20.0::DOUBLE AS p FROM m GROUP BY doc_id) z),
    e AS (SELECT sum(q * q) AS pe FROM (SELECT sum(c) * 1.0::DOUBLE / (SELECT sum(c) FROM m) AS q FROM m GROUP BY v) z)
    SELECT n, round((p - pe) / (1 - pe), 6) AS kappa FROM o, e""",
    "routed_turns": r"""WITH c AS (SELECT conv_id, role, turn, text, row_number() OVER (PARTITION BY conv_id, role ORDER BY turn) AS n FROM conversations WHERE role <> 'system'),
    w AS (SELECT *, list_distinct(list_filter(string_split_regex(lower(coalesce(text, '')), '[^a-z0-9]+'), lambda x: x <> '')) AS terms FROM c),
    q AS (SELECT a.conv_id, a.text AS t1, a.terms AS q1, b.text AS t2, coalesce(b.terms, []) AS q2 FROM w a LEFT JOIN (SELECT * FROM w WHERE role = 'user' AND n = 2) b ON a.conv_id = b.conv_id WHERE a.role = 'user' AND a.n = 1),
    s AS (SELECT w.text, w.n, t1, t2, len(list_intersect(terms, q1)) * 1.0::DOUBLE / nullif(len(list_distinct(list_concat(terms, q1))), 0) AS s1,
      CASE WHEN w.n > 1 THEN len(list_intersect(terms, q2)) * 1.0::DOUBLE / nullif(len(list_distinct(list_concat(terms, q2))), 0) ELSE 0 END AS s2 FROM w JOIN q ON w.conv_id = q.conv_id WHERE w.role = 'assistant'),
    r AS (SELECT *, CASE WHEN coalesce(s1, 0) < 0.1 AND coalesce(s2, 0) < 0.1 THEN 'Other' WHEN coalesce(s1, 0) >= coalesce(s2, 0) THEN 'L1' ELSE 'L2' END AS rho FROM s)
    SELECT rho, CASE WHEN regexp_matches(trim(lower(text)), '^(with|select)\b') THEN 'SQL' ELSE 'ASK' END AS act, count(*) AS n,
      CAST(sum(length(CASE rho WHEN 'L1' THEN t1 WHEN 'L2' THEN t2 ELSE 'Please decide that yourself.' END)) AS BIGINT) AS reply_chars FROM r GROUP BY 1, 2""",
    "vector_router": """WITH f AS (SELECT min(vec_id) AS ref_id FROM embeddings GROUP BY label), r AS (SELECT ref_id, embedding::DOUBLE[] AS ref FROM f JOIN embeddings ON vec_id = ref_id),
    n AS (SELECT vec_id, ref_id, list_cosine_similarity(embedding::DOUBLE[], ref) AS c FROM embeddings, r)
    SELECT vec_id, ref_id AS nearest, round(c, 4) AS cosine FROM (SELECT *, row_number() OVER (PARTITION BY vec_id ORDER BY c DESC, ref_id) AS k FROM n) x WHERE k = 1""",
    "router_labels": "SELECT doc_id, item_id, CASE WHEN item_id % 2 = 0 THEN 'L1' ELSE 'L2' END AS rho FROM documents d JOIN benchmark b ON contains(d.text, b.text)",
    "evidence_redact": r"""
WITH g AS (SELECT item_id % 2 AS parity, list(DISTINCT string_split(text, ' ')[2]) AS giveaway FROM benchmark GROUP BY item_id % 2),
c AS (SELECT doc_id, giveaway, unnest(string_split_regex(replace(text, chr(10), ' '), '\. ')) AS clause FROM documents JOIN g ON doc_id % 2 = parity)
SELECT doc_id, CAST(coalesce(sum(length(clause)) FILTER (keep), 0) + greatest(count_if(keep) - 1, 0) AS BIGINT) AS kept_chars, count(*) AS clauses
FROM (SELECT doc_id, clause, regexp_matches(clause, '[0-9]') OR len(list_filter(giveaway, lambda w: contains(clause, w))) = 0 AS keep FROM c) x GROUP BY doc_id
""",
    "page_utterances": "SELECT page_id, regexp_extract(html, '(?i)<title>([^<]*)</title>', 1) AS title FROM pages",
}
