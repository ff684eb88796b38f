"""Anchor queries as SQL text: eight templates over the given tables, bound to the combinations that the data hold.

Each family has an anchor text and one later text for each kind of change: one literal replaced (value), one
predicate withdrawn (constraint), an output changed (projection), two changes at once (mixed), something added
(addition). The parameters of a binding come from the anchor catalogue; texts go through the parser, and what it
reads is compared with SQL that is computed from the bindings.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import complexity, drift
from ..operators import commitments

KINDS = ("value", "constraint", "projection", "mixed", "addition")
#: What a change of each kind is to be read as.
READ_AS = {"value": drift.VALUE, "constraint": drift.CONSTRAINT, "projection": drift.PROJECTION, "mixed": drift.REJECT, "addition": drift.NOT_DRIFT}

_JOINED = "lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey"
_CELL = "c_mktsegment = '{segment}' AND o_orderpriority = '{priority}' AND o_orderstatus = '{status}'"
_FLAGS = "SELECT l_returnflag, COUNT(*) AS n, SUM(l_extendedprice) AS total FROM " + _JOINED

#: family: parameters, anchor text, later text by kind. {next} is {year} + 1.
TEMPLATES: dict[str, tuple[tuple[str, ...], str, dict[str, str]]] = {
    "flags": (
        ("segment", "priority", "status", "year"),
        _FLAGS + " WHERE " + _CELL + " AND YEAR(o_orderdate) = {year} GROUP BY l_returnflag",
        {
            "value": _FLAGS + " WHERE " + _CELL + " AND YEAR(o_orderdate) = {next} GROUP BY l_returnflag",
            "constraint": _FLAGS + " WHERE c_mktsegment = '{segment}' AND o_orderpriority = '{priority}' AND YEAR(o_orderdate) = {year} GROUP BY l_returnflag",
            "projection": "SELECT l_returnflag, COUNT(*) AS n FROM " + _JOINED + " WHERE " + _CELL + " AND YEAR(o_orderdate) = {year} GROUP BY l_returnflag",
            "mixed": "SELECT l_returnflag, COUNT(*) AS n FROM " + _JOINED + " WHERE " + _CELL + " AND YEAR(o_orderdate) = {next} GROUP BY l_returnflag",
            "addition": _FLAGS + " WHERE " + _CELL + " AND YEAR(o_orderdate) = {year} AND l_quantity > 10 GROUP BY l_returnflag",
        },
    ),
    "member": (
        ("segment", "status"),
        "SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = '{segment}' AND c_acctbal > 500) AND o_orderstatus = '{status}'",
        {
            "value": "SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = '{segment}' AND c_acctbal > 900) AND o_orderstatus = '{status}'",
            "constraint": "SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = '{segment}') AND o_orderstatus = '{status}'",
            "projection": "SELECT o_orderkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = '{segment}' AND c_acctbal > 500) AND o_orderstatus = '{status}'",
            "mixed": "SELECT o_orderkey FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = '{segment}') AND o_orderstatus = '{status}'",
            "addition": "SELECT o_orderkey, o_totalprice FROM orders WHERE o_custkey IN (SELECT c_custkey FROM customer WHERE c_mktsegment = '{segment}' AND c_acctbal > 500 AND c_nationkey < 20) AND o_orderstatus = '{status}'",
        },
    ),
    "present": (
        ("segment", "priority", "status"),
        "SELECT c_custkey FROM customer WHERE c_mktsegment = '{segment}' AND EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '{priority}' AND o_orderstatus = '{status}')",
        {
            "value": "SELECT c_custkey FROM customer WHERE c_mktsegment = '{segment}' AND EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = 'none' AND o_orderstatus = '{status}')",
            "constraint": "SELECT c_custkey FROM customer WHERE c_mktsegment = '{segment}'  AND EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '{priority}')",
            "projection": "SELECT c_name FROM customer WHERE c_mktsegment = '{segment}' AND EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '{priority}' AND o_orderstatus = '{status}')",
            "mixed": "SELECT c_custkey FROM customer WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = 'none' AND o_orderstatus = '{status}')",
            "addition": "SELECT c_custkey, c_name FROM customer WHERE c_mktsegment = '{segment}' AND EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey AND o_orderpriority = '{priority}' AND o_orderstatus = '{status}')",
        },
    ),
    "yearly": (
        ("segment", "status", "year"),
        "WITH yearly AS (SELECT o_custkey, SUM(o_totalprice) AS spent FROM orders WHERE YEAR(o_orderdate) = {year} AND o_orderstatus = '{status}' GROUP BY o_custkey) "
        "SELECT c_nationkey, AVG(spent) FROM yearly JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment IN ('{segment}', 'OTHER') GROUP BY c_nationkey",
        {
            "value": "WITH yearly AS (SELECT o_custkey, SUM(o_totalprice) AS spent FROM orders WHERE YEAR(o_orderdate) = {next} AND o_orderstatus = '{status}' GROUP BY o_custkey) "
            "SELECT c_nationkey, AVG(spent) FROM yearly JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment IN ('{segment}', 'OTHER') GROUP BY c_nationkey",
            "constraint": "WITH yearly AS (SELECT o_custkey, SUM(o_totalprice) AS spent FROM orders WHERE YEAR(o_orderdate) = {year} GROUP BY o_custkey) "
            "SELECT c_nationkey, AVG(spent) FROM yearly JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment IN ('OTHER', '{segment}') GROUP BY c_nationkey",
            "projection": "WITH yearly AS (SELECT o_custkey, SUM(o_totalprice) AS spent FROM orders WHERE YEAR(o_orderdate) = {year} AND o_orderstatus = '{status}' GROUP BY o_custkey) "
            "SELECT c_nationkey, MAX(spent) FROM yearly JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment IN ('{segment}', 'OTHER') GROUP BY c_nationkey",
            "mixed": "WITH yearly AS (SELECT o_custkey, SUM(o_totalprice) AS spent FROM orders WHERE YEAR(o_orderdate) = {next} AND o_orderstatus = '{status}' GROUP BY o_custkey) "
            "SELECT c_nationkey, AVG(spent) FROM yearly JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment IN ('{segment}', 'ANOTHER') GROUP BY c_nationkey",
            "addition": "WITH yearly AS (SELECT o_custkey, SUM(o_totalprice) AS spent FROM orders WHERE YEAR(o_orderdate) = {year} AND o_orderstatus = '{status}' GROUP BY o_custkey) "
            "SELECT c_nationkey, AVG(spent) FROM yearly JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment IN ('{segment}', 'OTHER') GROUP BY c_nationkey LIMIT 5",
        },
    ),
    "ranked": (
        ("segment", "priority"),
        "SELECT c_nationkey, COUNT(*) FROM customer c JOIN orders o ON o.o_custkey = c.c_custkey AND o.o_orderpriority = '{priority}' WHERE c.c_mktsegment = '{segment}' AND o.o_totalprice BETWEEN 1000 AND 200000 "
        "GROUP BY 1 HAVING COUNT(*) > 2 ORDER BY 2 DESC LIMIT 3 OFFSET 1",
        {
            "value": "SELECT c_nationkey, COUNT(*) FROM customer c JOIN orders o ON o.o_custkey = c.c_custkey AND o.o_orderpriority = '{priority}' WHERE c.c_mktsegment = '{segment}' AND o.o_totalprice BETWEEN 1000 AND 150000 "
            "GROUP BY 1 HAVING COUNT(*) > 2 ORDER BY 2 DESC LIMIT 3 OFFSET 1",
            "constraint": "SELECT c_nationkey, COUNT(*) FROM customer c JOIN orders o ON o.o_custkey = c.c_custkey WHERE c.c_mktsegment = '{segment}' AND o.o_totalprice BETWEEN 1000 AND 200000 "
            "GROUP BY 1 HAVING COUNT(*) > 2 ORDER BY 2 DESC LIMIT 3 OFFSET 1",
            "projection": "SELECT c_nationkey, COUNT(*) FROM customer c JOIN orders o ON o.o_custkey = c.c_custkey AND o.o_orderpriority = '{priority}' WHERE c.c_mktsegment = '{segment}' AND o.o_totalprice BETWEEN 1000 AND 200000 "
            "GROUP BY 1 ORDER BY 2 ASC LIMIT 5",
            "mixed": "SELECT c_nationkey, COUNT(*) FROM customer c JOIN orders o ON o.o_custkey = c.c_custkey AND o.o_orderpriority = '{priority}' WHERE c.c_mktsegment = '{segment}' AND o.o_totalprice BETWEEN 2000 AND 150000 "
            "GROUP BY 1 HAVING COUNT(*) > 2 ORDER BY 2 DESC LIMIT 3 OFFSET 1",
            "addition": "SELECT c_nationkey, COUNT(*), MIN(o.o_totalprice) FROM customer c JOIN orders o ON o.o_custkey = c.c_custkey AND o.o_orderpriority = '{priority}' WHERE c.c_mktsegment = '{segment}' "
            "AND o.o_totalprice BETWEEN 1000 AND 200000 GROUP BY 1 HAVING COUNT(*) > 2 ORDER BY 2 DESC LIMIT 3 OFFSET 1",
        },
    ),
    "above": (
        ("priority", "status"),
        "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT AVG(o_totalprice) FROM orders WHERE o_orderpriority = '{priority}') AND o_orderstatus = '{status}'",
        {
            "value": "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT AVG(o_totalprice) FROM orders WHERE o_orderpriority = 'none') AND o_orderstatus = '{status}'",
            "constraint": "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT AVG(o_totalprice) FROM orders) AND o_orderstatus = '{status}'",
            "projection": "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT MIN(o_totalprice) FROM orders WHERE o_orderpriority = '{priority}') AND o_orderstatus = '{status}'",
            "mixed": "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT AVG(o_totalprice) FROM orders WHERE o_orderpriority <> '{priority}') AND o_orderstatus = '{status}'",
            "addition": "SELECT o_orderkey FROM orders WHERE o_totalprice > (SELECT AVG(o_totalprice) FROM orders WHERE o_orderpriority = '{priority}' AND o_totalprice > 0) AND o_orderstatus = '{status}'",
        },
    ),
    "either": (
        ("segment", "year"),
        "SELECT c_custkey FROM customer WHERE c_mktsegment = '{segment}' AND c_acctbal < 0 UNION SELECT o_custkey FROM orders WHERE YEAR(o_orderdate) = {year} AND o_totalprice >= 300000",
        {
            "value": "SELECT c_custkey FROM customer WHERE c_mktsegment = '{segment}' AND c_acctbal < 0 UNION SELECT o_custkey FROM orders WHERE YEAR(o_orderdate) = {next} AND o_totalprice >= 300000",
            "constraint": "SELECT c_custkey FROM customer WHERE c_mktsegment = '{segment}' AND c_acctbal < 0 UNION SELECT o_custkey FROM orders WHERE {year} = YEAR(o_orderdate)",
            "projection": "SELECT c_nationkey FROM customer WHERE c_mktsegment = '{segment}' AND 0 > c_acctbal UNION SELECT o_custkey FROM orders WHERE YEAR(o_orderdate) = {year} AND o_totalprice >= 300000",
            "mixed": "SELECT c_custkey FROM customer WHERE c_mktsegment = '{segment}' AND c_acctbal < 100 UNION SELECT o_custkey FROM orders WHERE YEAR(o_orderdate) = {next} AND o_totalprice >= 300000",
            "addition": "SELECT c_custkey FROM customer WHERE c_mktsegment = '{segment}' AND c_acctbal < 0 UNION SELECT o_custkey FROM orders WHERE YEAR(o_orderdate) = {year} AND o_totalprice >= 300000 ORDER BY 1",
        },
    ),
    "derived": (
        ("status", "year"),
        "SELECT x.o_orderpriority, MAX(x.spent) FROM (SELECT o_orderpriority, o_custkey, SUM(o_totalprice) AS spent FROM orders WHERE o_orderstatus = '{status}' AND YEAR(o_orderdate) = {year} GROUP BY o_orderpriority, o_custkey) x "
        "WHERE x.spent > 1000 GROUP BY x.o_orderpriority",
        {
            "value": "SELECT x.o_orderpriority, MAX(x.spent) FROM (SELECT o_orderpriority, o_custkey, SUM(o_totalprice) AS spent FROM orders WHERE o_orderstatus = '{status}' AND YEAR(o_orderdate) = {year} GROUP BY o_orderpriority, o_custkey) x "
            "WHERE x.spent > 5000 GROUP BY x.o_orderpriority",
            "constraint": "SELECT x.o_orderpriority, MAX(x.spent) FROM (SELECT o_orderpriority, o_custkey, SUM(o_totalprice) AS spent FROM orders WHERE YEAR(o_orderdate) = {year} GROUP BY o_orderpriority, o_custkey) x "
            "WHERE x.spent > 1000 GROUP BY x.o_orderpriority",
            "projection": "SELECT x.o_orderpriority, MAX(x.spent) FROM (SELECT o_orderpriority, o_custkey, AVG(o_totalprice) AS spent FROM orders WHERE o_orderstatus = '{status}' AND YEAR(o_orderdate) = {year} GROUP BY o_orderpriority, o_custkey) x "
            "WHERE x.spent > 1000 GROUP BY x.o_orderpriority",
            "mixed": "SELECT MAX(x.spent) FROM (SELECT o_orderpriority, o_custkey, SUM(o_totalprice) AS spent FROM orders WHERE o_orderstatus = '{status}' AND YEAR(o_orderdate) = {year} GROUP BY o_orderpriority, o_custkey) x WHERE x.spent > 2000",
            "addition": "SELECT x.o_orderpriority, MAX(x.spent), COUNT(*) FROM (SELECT o_orderpriority, o_custkey, SUM(o_totalprice) AS spent FROM orders WHERE o_orderstatus = '{status}' AND YEAR(o_orderdate) = {year} GROUP BY o_orderpriority, "
            "o_custkey) x WHERE x.spent > 1000 GROUP BY x.o_orderpriority",
        },
    ),
}


def bound(template: str) -> Column:
    """A template's text with the parameter columns put in."""
    text = F.lit(template)
    for name in ("segment", "priority", "status", "year"):
        text = F.replace(text, F.lit("{" + name + "}"), F.col(name).cast("string"))
    return F.replace(text, F.lit("{next}"), (F.col("year") + 1).cast("string"))


def texts_of(pool: DataFrame, family: str) -> DataFrame:
    """family, anchor_key, sql, and sql_<kind> for each binding of one family; pool: the catalogue's parameters."""
    names, anchor, later = TEMPLATES[family]
    rows = pool.select(*names).distinct()
    for absent in ("segment", "priority", "status", "year"):
        if absent not in names:
            rows = rows.withColumn(absent, F.lit(0 if absent == "year" else ""))
    key = F.concat_ws("/", F.lit(family), *[F.col(n).cast("string") for n in names])
    return rows.select(F.lit(family).alias("family"), key.alias("anchor_key"), bound(anchor).alias("sql"), *[bound(later[k]).alias(f"sql_{k}") for k in KINDS])


def sql_anchors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """family, anchor_key, sql, and sql_<kind>: every family over every binding."""
    from .anchors import PARAMETERS, facts

    pool = facts(spark, sf_dir).select(*PARAMETERS).distinct()
    out = texts_of(pool, "flags")
    for family in list(TEMPLATES)[1:]:
        out = out.unionByName(texts_of(pool, family))
    return out


def read_anchors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """family, anchor_key, items, error of the anchor texts."""
    read = commitments.extract_distinct(sql_anchors(spark, sf_dir).select("family", "anchor_key", "sql"), ["sql"])
    return read.select("family", "anchor_key", F.col("sql_items").alias("items"), F.col("sql_error").alias("error"))


def sql_anchor_catalogue(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Anchors of each family, and how many of them the parser reads."""
    return read_anchors(spark, sf_dir).groupBy("family").agg(F.count("*").alias("n"), F.count_if(F.col("error").isNull()).alias("n_read"))


def commitment_long(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every commitment of every anchor text, one row each."""
    long = commitments.explode_long(read_anchors(spark, sf_dir), "anchor_key")
    return long.select("anchor_key", "kind", "scope", "skeleton", F.array_join("literals", ",").alias("literals"))


def sql_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """family, anchor_key, change, pre and post with their items and errors."""
    wide = sql_anchors(spark, sf_dir)
    changes = F.explode(F.array(*[F.struct(F.lit(k).alias("change"), F.col(f"sql_{k}").alias("post")) for k in KINDS]))
    pairs = wide.select("family", "anchor_key", F.col("sql").alias("pre"), changes.alias("c")).select("family", "anchor_key", "pre", "c.change", "c.post")
    return commitments.extract_distinct(pairs, ["pre", "post"])


def sql_drift_subtype(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Subtype read from the texts, by family and by the change that was made."""
    p = sql_pairs(spark, sf_dir)
    return p.groupBy("family", "change", drift.classify(F.col("pre_items"), F.col("post_items")).alias("subtype")).agg(F.count("*").alias("n"))


def sql_admissible(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The kinds of drift that each anchor text can support, and how many anchors there are of each such set."""
    options = F.array_join(drift.admissible(F.col("items")), "|")
    return read_anchors(spark, sf_dir).groupBy("family", options.alias("options")).agg(F.count("*").alias("n"))


def sql_anchor_tiers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Structural score and tier of the anchor texts."""
    score = complexity.score(F.col("items"))
    return read_anchors(spark, sf_dir).select("family", score.alias("score"), complexity.tier(score, (9, 11)).alias("tier")).groupBy("family", "score", "tier").agg(F.count("*").alias("n"))


#: What each family's anchor text commits to, written by hand: kind, scope, skeleton, literals (a parameter's name, or =value).
EXPECTED: dict[str, list[tuple[str, str, str, tuple[str, ...]]]] = {
    "flags": [
        ("FILTER", "", "c_mktsegment = ?", ("segment",)), ("FILTER", "", "o_orderpriority = ?", ("priority",)), ("FILTER", "", "o_orderstatus = ?", ("status",)), ("FILTER", "", "year(o_orderdate) = ?", ("year",)),
        ("GROUP", "", "l_returnflag", ()), ("PROJECT", "", "count(*)", ()), ("PROJECT", "", "l_returnflag", ()), ("PROJECT", "", "sum(l_extendedprice)", ()),
    ],
    "member": [
        ("FILTER", "", "orders.o_custkey IN (sub:1)", ()), ("FILTER", "", "orders.o_orderstatus = ?", ("status",)), ("FILTER", "sub:1", "customer.c_acctbal > ?", ("=500",)),
        ("FILTER", "sub:1", "customer.c_mktsegment = ?", ("segment",)), ("PROJECT", "", "orders.o_orderkey", ()), ("PROJECT", "", "orders.o_totalprice", ()), ("PROJECT", "sub:1", "customer.c_custkey", ()),
    ],
    "present": [
        ("FILTER", "", "EXISTS (sub:1)", ()), ("FILTER", "", "customer.c_mktsegment = ?", ("segment",)), ("FILTER", "sub:1", "orders.c_custkey = orders.o_custkey", ()),
        ("FILTER", "sub:1", "orders.o_orderpriority = ?", ("priority",)), ("FILTER", "sub:1", "orders.o_orderstatus = ?", ("status",)), ("PROJECT", "", "customer.c_custkey", ()), ("PROJECT", "sub:1", "?", ("=1",)),
    ],
    "yearly": [
        ("FILTER", "", "c_mktsegment IN (?, ?)", ("segment", "=OTHER")), ("FILTER", "cte:yearly", "orders.o_orderstatus = ?", ("status",)), ("FILTER", "cte:yearly", "year(orders.o_orderdate) = ?", ("year",)),
        ("GROUP", "", "c_nationkey", ()), ("GROUP", "cte:yearly", "orders.o_custkey", ()), ("PROJECT", "", "avg(spent)", ()), ("PROJECT", "", "c_nationkey", ()),
        ("PROJECT", "cte:yearly", "orders.o_custkey", ()), ("PROJECT", "cte:yearly", "sum(orders.o_totalprice)", ()),
    ],
    "ranked": [
        ("FILTER", "", "customer.c_mktsegment = ?", ("segment",)), ("FILTER", "", "orders.o_orderpriority = ?", ("priority",)), ("FILTER", "", "orders.o_totalprice BETWEEN ? AND ?", ("=1000", "=200000")),
        ("GROUP", "", "c_nationkey", ()), ("HAVING", "", "count(*) > ?", ("=2",)), ("LIMIT", "", "?", ("=3",)), ("OFFSET", "", "?", ("=1",)), ("ORDER", "", "count(*) DESC", ()),
        ("PROJECT", "", "c_nationkey", ()), ("PROJECT", "", "count(*)", ()),
    ],
    "above": [
        ("FILTER", "", "orders.o_orderstatus = ?", ("status",)), ("FILTER", "", "(sub:1) < orders.o_totalprice", ()), ("FILTER", "sub:1", "orders.o_orderpriority = ?", ("priority",)),
        ("PROJECT", "", "orders.o_orderkey", ()), ("PROJECT", "sub:1", "avg(orders.o_totalprice)", ()),
    ],
    "either": [
        ("FILTER", "arm:0", "customer.c_acctbal < ?", ("=0",)), ("FILTER", "arm:0", "customer.c_mktsegment = ?", ("segment",)), ("FILTER", "arm:1", "orders.o_totalprice >= ?", ("=300000",)),
        ("FILTER", "arm:1", "year(orders.o_orderdate) = ?", ("year",)), ("PROJECT", "arm:0", "customer.c_custkey", ()), ("PROJECT", "arm:1", "orders.o_custkey", ()),
    ],
    "derived": [
        ("FILTER", "", "x.spent > ?", ("=1000",)), ("FILTER", "from:1", "orders.o_orderstatus = ?", ("status",)), ("FILTER", "from:1", "year(orders.o_orderdate) = ?", ("year",)),
        ("GROUP", "", "x.o_orderpriority", ()), ("GROUP", "from:1", "orders.o_custkey", ()), ("GROUP", "from:1", "orders.o_orderpriority", ()), ("PROJECT", "", "max(x.spent)", ()),
        ("PROJECT", "", "x.o_orderpriority", ()), ("PROJECT", "from:1", "orders.o_custkey", ()), ("PROJECT", "from:1", "orders.o_orderpriority", ()), ("PROJECT", "from:1", "sum(orders.o_totalprice)", ()),
    ],
}

_POOL = """
WITH f AS (SELECT DISTINCT c_mktsegment AS segment, o_orderpriority AS priority, o_orderstatus AS status, CAST(year(o_orderdate) AS INT) AS year
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey)
"""


def _bindings_sql() -> str:
    """family, anchor_key and the parameters of each binding."""
    parts = []
    for family, (names, _, _) in TEMPLATES.items():
        columns = ", ".join(n if n in names else f"NULL AS {n}" for n in ("segment", "priority", "status", "year"))
        key = "concat_ws('/', " + ", ".join([f"'{family}'", *[f"CAST({n} AS VARCHAR)" for n in names]]) + ")"
        parts.append(f"SELECT DISTINCT '{family}' AS family, {key} AS anchor_key, {columns} FROM f")
    return _POOL + ", b AS (" + " UNION ALL ".join(parts) + ")"


def _items_sql() -> str:
    """family, kind, scope, skeleton, and the literals with the names of parameters in braces."""
    rows = []
    for family, items in EXPECTED.items():
        for kind, scope, skeleton, literals in items:
            rows.append(f"('{family}', '{kind}', '{scope}', '{skeleton}', '{','.join(x[1:] if x[0] == '=' else '{' + x + '}' for x in literals)}')")
    return "(VALUES " + ", ".join(rows) + ") AS e(family, kind, scope, skeleton, literals)"


def _options_sql() -> str:
    """Families by their sets of admissible kinds, from the expected items."""
    return f"""SELECT family, concat_ws('|', CASE WHEN bool_or(kind = 'FILTER' AND literals <> '') THEN 'value' END, CASE WHEN bool_or(kind = 'FILTER') THEN 'constraint' END,
      CASE WHEN bool_or(kind <> 'FILTER') THEN 'projection' END) AS options FROM {_items_sql()} GROUP BY family"""


_POINTS = "CASE kind WHEN 'GROUP' THEN 2 WHEN 'HAVING' THEN 2 ELSE 1 END"
QUERIES = {f.__name__: f for f in (sql_anchor_catalogue, commitment_long, sql_drift_subtype, sql_admissible, sql_anchor_tiers)}
ORACLES = {
    "sql_anchor_catalogue": _bindings_sql() + "SELECT family, count(*) AS n, count(*) AS n_read FROM b GROUP BY family",
    "commitment_long": _bindings_sql()
    + f"""SELECT anchor_key, kind, scope, skeleton, replace(replace(replace(replace(literals, '{{segment}}', coalesce(segment, '')), '{{priority}}', coalesce(priority, '')), '{{status}}', coalesce(status, '')),
      '{{year}}', coalesce(CAST(year AS VARCHAR), '')) AS literals FROM b JOIN {_items_sql()} ON b.family = e.family""",
    "sql_drift_subtype": _bindings_sql()
    + "SELECT family, change, subtype, count(*) AS n FROM b, (VALUES " + ", ".join(f"('{k}', '{v}')" for k, v in READ_AS.items()) + ") AS t(change, subtype) GROUP BY family, change, subtype",
    "sql_admissible": _bindings_sql() + f"SELECT b.family, o.options, count(*) AS n FROM b JOIN ({_options_sql()}) o ON b.family = o.family GROUP BY b.family, o.options",
    "sql_anchor_tiers": _bindings_sql()
    + f""", s AS (SELECT family, CAST(sum({_POINTS}) + 2 * count(DISTINCT nullif(scope, '')) AS INT) AS score FROM {_items_sql()} GROUP BY family)
    SELECT b.family, s.score, CASE WHEN s.score <= 9 THEN 'basic' WHEN s.score <= 11 THEN 'intermediate' ELSE 'advanced' END AS tier, count(*) AS n FROM b JOIN s ON b.family = s.family GROUP BY b.family, s.score""",
}
