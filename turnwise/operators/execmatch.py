"""Execution match: whether two results are equal as collections, whatever the order of rows.

Cells are compared by their text, null equal to null; column names do not count, their order does. Integers and
decimals are compared exactly, whatever their types, in one spelling without trailing zeros; floating-point numbers
are rounded to DIGITS places, and those that are whole numbers a double holds exactly are spelled like integers.
"""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark.sql import Column, DataFrame, Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sqltext import SqlError, parse
from ..sqltext.parser import lex

DIGITS = 6


def canonical(df: DataFrame) -> DataFrame:
    """The rows as columns c0, c1, ... of comparable text."""
    out = []
    for i, f in enumerate(df.schema.fields):
        c = F.col(f"`{f.name}`")
        out.append(spelled(c, f.dataType).alias(f"c{i}"))
    return df.toDF(*[f.name for f in df.schema.fields]).select(*out)


def plain(text: Column) -> Column:
    """A decimal's text without trailing zeros."""
    return F.when(F.contains(text, F.lit(".")), F.regexp_replace(text, r"\.?0+$", "")).otherwise(text)


def spelled(c: Column, kind: T.DataType) -> Column:
    """The one text of a cell: 1, 1.0 and DECIMAL 1.00 are the same, 2**53 and 2**53 + 1 are not."""
    if isinstance(kind, T.BooleanType):
        return c.cast("int").cast("string")
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        rounded = F.round(c.cast("double"), DIGITS) + F.lit(0.0)  # no negative zero
        inside = F.abs(rounded) < F.lit(1e15)
        return F.when(inside, plain(rounded.cast(f"decimal(38,{DIGITS})").cast("string"))).otherwise(rounded.cast("string"))
    if isinstance(kind, T.DecimalType):
        return plain(c.cast("string"))
    return c.cast("string")


def exact(a: DataFrame, b: DataFrame, bag: bool = True) -> bool:
    """Equal as multisets (bag) or as sets: one signed count over all columns, one exchange."""
    if len(a.columns) != len(b.columns):
        return False
    a, b = canonical(a), canonical(b)
    if not a.columns:
        return True
    both = a.withColumn("_s", F.lit(1)).unionByName(b.withColumn("_s", F.lit(-1)))
    grouped = both.groupBy(*a.columns).agg(F.sum("_s").alias("s"), F.min("_s").alias("lo"), F.max("_s").alias("hi"))
    return grouped.filter(F.col("s") != 0 if bag else F.col("lo") == F.col("hi")).isEmpty()


def fingerprint_columns(columns: list[str]) -> list[Column]:
    """Mergeable aggregates: count, sum and xor of row hashes."""
    h = F.xxhash64(*[F.coalesce(F.concat(F.lit("="), F.col(c)), F.lit("null")) for c in columns])
    return [F.count("*").alias("n"), F.sum(h.cast("decimal(20,0)")).alias("hash_sum"), F.coalesce(F.bit_xor(h), F.lit(0)).alias("hash_xor")]


def fingerprint(a: DataFrame) -> Row:
    c = canonical(a)
    return c.agg(*fingerprint_columns(c.columns)).first()


def same_fingerprint(a: DataFrame, b: DataFrame) -> bool:
    return len(a.columns) == len(b.columns) and fingerprint(a) == fingerprint(b)


def gate(query: str, allowed: set[str] | None = None) -> None:
    """Untrusted SQL must be one readable SELECT over the allowed tables; raises SqlError otherwise."""
    tree = parse(query)
    if any(v.lower() in ("reflect", "java_method", "transform") for k, v in lex(query) if k == "word"):
        raise SqlError("call not allowed")
    if allowed is not None:
        unknown = tables_of(tree) - allowed
        if unknown:
            raise SqlError(f"table not allowed: {', '.join(sorted(unknown))}")


def tables_of(node) -> set[str]:
    """Table names read anywhere in a tree, without the names of its own common table expressions."""
    found: set[str] = set()
    own: set[str] = set()

    def walk(x) -> None:
        if isinstance(x, dict):
            own.update(name for name, _ in x.get("ctes", ()))
            for (kind, what, _), _, _ in x.get("from", ()):
                if kind == "table":
                    found.add(what)
            for v in x.values():
                walk(v)
        elif isinstance(x, (tuple, list)):
            for v in x:
                walk(v)

    walk(node)
    return found - own


def batch(spark: SparkSession, pairs: list[tuple[str, str, str]], allowed: set[str] | None = None, threads: int = 8) -> DataFrame:
    """pair_id, ex, error_class for (pair_id, agent SQL, gold SQL): each distinct text is run once, as a fingerprint, which
    is one row however large the result. The list of pairs lives on the driver: for more queries than a driver holds, see family()."""

    def run(query: str):
        try:
            gate(query, allowed)
            df = spark.sql(query)
            return (len(df.columns), *fingerprint(df)), None
        except Exception as e:  # noqa: BLE001  any failure of an agent's query is a mismatch with a class
            return None, type(e).__name__

    texts = sorted({q for _, a, g in pairs for q in (a, g)})
    with ThreadPoolExecutor(threads) as pool:
        got = dict(zip(texts, pool.map(run, texts), strict=True))
    rows = [(i, int(got[a][0] is not None and got[a][0] == got[g][0]), got[a][1] or (f"gold {got[g][1]}" if got[g][1] else None)) for i, a, g in pairs]
    return spark.createDataFrame(rows, "pair_id string, ex int, error_class string")


def family(bindings: DataFrame, cube: DataFrame, keys: list[str], anchor: str, cells: list[str]) -> DataFrame:
    """Results of a whole family of queries in one scan: bindings (anchor, literal columns) meet a cube that is
    grouped by the literals' columns and the queries' own groups; one fingerprint an anchor."""
    rows = bindings.join(cube, keys, "left").filter(reduce(lambda x, y: x | y, [F.col(c).isNotNull() for c in cells]))
    return rows.select(anchor, *[F.col(c).cast("string").alias(c) for c in cells]).groupBy(anchor).agg(*fingerprint_columns(cells))
