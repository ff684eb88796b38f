"""Commitment sets of SQL text columns: each distinct text is parsed once, in Arrow batches."""

from __future__ import annotations

import sys

import pandas as pd
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.schemas import COMMITMENT, EXTRACTED
from ..sqltext import commitments, commitments_of_tree, parser

for _module in (parser, commitments_of_tree, sys.modules[commitments.__module__.rpartition(".")[0]], sys.modules[__name__]):
    cloudpickle.register_pickle_by_value(_module)  # executors need no copy of this package on their path


def one(sql: str | None, level: str = "full", strict: bool = False, schema: dict | None = None) -> tuple[list, str | None]:
    if sql is None:
        return [], "null"
    try:
        return [(k, s, t, list(ls)) for k, s, t, ls in commitments(sql, level, strict, schema)], None
    except (ValueError, RecursionError, ArithmeticError) as e:
        return [], f"{type(e).__name__}: {e}"[:200]


def extract(sql: Column | str, level: str = "full", strict: bool = False, schema: dict | None = None) -> Column:
    """struct<items: array<commitment>, error: string> of each text; unreadable texts have no items and an error."""

    def run(texts):
        rows = [one(t, level, strict, schema) for t in texts]
        return pd.DataFrame({"items": pd.Series([[dict(zip(COMMITMENT.names, i, strict=True)) for i in r[0]] for r in rows], dtype=object), "error": pd.Series([r[1] for r in rows], dtype=object)})

    run.__annotations__ = {"texts": pd.Series, "return": pd.DataFrame}
    return F.pandas_udf(run, EXTRACTED)(sql)


def extract_distinct(df: DataFrame, columns: list[str], **how) -> DataFrame:
    """df with, for each SQL column c, columns c_items and c_error; each distinct text is parsed once and joined back."""
    texts = df.select(F.explode(F.array(*columns)).alias("_sql")).dropna().distinct()
    parsed = texts.withColumn("_p", extract("_sql", **how)).select("_sql", "_p.items", "_p.error")
    for c in columns:
        df = df.join(parsed.toDF(c, f"{c}_items", f"{c}_error"), c, "left").withColumn(f"{c}_error", F.when(F.col(c).isNull(), "null").otherwise(F.col(f"{c}_error")))
    return df


def explode_long(df: DataFrame, key: str, items: str = "items") -> DataFrame:
    """One row per commitment: key, kind, scope, skeleton, literals."""
    return df.select(key, F.explode(items).alias("_i")).select(key, "_i.*")


class CommitmentsOf:
    """Table function: commitments as rows, for use with LATERAL."""

    def eval(self, sql: str):
        for k, s, t, ls in one(sql)[0]:
            yield k, s, t, ls


def register(spark: SparkSession) -> None:
    """SQL surface: commitments_of(sql) as a table function, commitment_set(sql) as a function."""
    kind = T.StructType([T.StructField(f.name, f.dataType) for f in COMMITMENT.fields])
    spark.udtf.register("commitments_of", F.udtf(CommitmentsOf, returnType=kind))

    def run(texts):
        return pd.Series([[dict(zip(COMMITMENT.names, i, strict=True)) for i in one(t)[0]] for t in texts], dtype=object)

    run.__annotations__ = {"texts": pd.Series, "return": pd.Series}
    spark.udf.register("commitment_set", F.pandas_udf(run, T.ArrayType(COMMITMENT)))
