"""Construction of paired samples. A dropped candidate keeps its row, flagged with the stage that dropped it."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..functions import complexity, drift

TYPES = ("C", "D", "J")


def expand(anchors: DataFrame) -> DataFrame:
    """One Chain-only, one Drift-only and one Joint row per anchor; only drift types have two targets."""
    return anchors.withColumn("sample_type", F.explode(F.array(*[F.lit(t) for t in TYPES]))).withColumn("n_targets", F.when(F.col("sample_type") == "C", 1).otherwise(2))


def executable_families(anchors: DataFrame, spark: SparkSession, family: str = "family", sql: str = "sql", threads: int = 8) -> DataFrame:
    """The families whose texts the analyser accepts. A family's texts differ in literals only, so one text of each is
    probed: the driver sees as many texts as there are templates, however many anchors there are."""
    texts = [(r[0], r[1]) for r in anchors.groupBy(family).agg(F.min(sql)).collect()]
    with ThreadPoolExecutor(threads) as pool:
        ok = [(name,) for (name, _), good in zip(texts, pool.map(lambda t: _analysed(spark, t[1]), texts), strict=True) if good]
    return spark.createDataFrame(ok, f"{family} string")


def executable(anchors: DataFrame, spark: SparkSession, sql: str = "sql", limit: int = 10_000, threads: int = 8, family: str | None = None) -> DataFrame:
    """Anchors whose query the analyser accepts. Without a family column distinct texts are probed on the driver: at most
    limit of them, else an error; with one, one text of each family is, and there is no limit on anchors."""
    if family:
        return anchors.join(F.broadcast(executable_families(anchors, spark, family, sql, threads)), family, "left_semi")
    texts = [r[0] for r in anchors.select(sql).distinct().limit(limit + 1).collect()]
    if len(texts) > limit:
        raise ValueError(f"more than {limit} distinct queries; name their family")
    with ThreadPoolExecutor(threads) as pool:
        ok = [(q,) for q, good in zip(texts, pool.map(lambda q: _analysed(spark, q), texts), strict=True) if good]
    return anchors.join(F.broadcast(spark.createDataFrame(ok, f"{sql} string")), sql, "left_semi")


def _analysed(spark: SparkSession, query: str) -> bool:
    try:
        spark.sql(query).schema
        return True
    except Exception:  # noqa: BLE001  whatever the analyser says, the query does not run
        return False


def complex_enough(s: Column, floor: int = 3) -> Column:
    return complexity.score(s) >= floor


def supports_drift(s: Column) -> Column:
    return F.size(drift.admissible(s)) > 0


def assign_subtype(df: DataFrame, items: str, key: str) -> DataFrame:
    """A drift subtype for each anchor, near evenly over its admissible ones."""
    options = drift.admissible(F.col(items))
    rank = F.row_number().over(Window.partitionBy("_options").orderBy(F.md5(F.col(key).cast("string")), key)) - 1
    ranked = df.withColumn("_options", options).filter(F.size("_options") > 0)
    return ranked.withColumn("subtype", F.get("_options", rank % F.size("_options"))).drop("_options")


def assemble(chains: DataFrame, drifts: DataFrame, key: str = "anchor_id") -> DataFrame:
    """Triplets of the anchors that came through both branches."""
    return expand(chains.join(drifts, key))


def funnel(candidates: DataFrame, stages: dict[str, Column]) -> DataFrame:
    """stage, entered, kept, rate, cumulative: one pass with a conditional sum per stage; stages in their order."""
    passed, sums = F.lit(True), [F.count("*").alias("_0")]
    for i, test in enumerate(stages.values(), 1):
        passed = passed & F.coalesce(test, F.lit(False))
        sums.append(F.count_if(passed).alias(f"_{i}"))
    one = candidates.agg(*sums)
    rows = F.array(*[F.struct(F.lit(i).alias("i"), F.lit(name).alias("stage"), F.col(f"_{i - 1}").alias("entered"), F.col(f"_{i}").alias("kept"), F.col("_0").alias("all")) for i, name in enumerate(stages, 1)])
    return one.select(F.inline(rows)).select("stage", "entered", "kept", F.try_divide("kept", "entered").alias("rate"), F.try_divide("kept", "all").alias("cumulative"))


def shares(df: DataFrame, columns: list[str]) -> DataFrame:
    """dimension, level, n, share for each column: one pass, one grouping set a column."""
    long = df.select(F.explode(F.array(*[F.struct(F.lit(c).alias("dimension"), F.col(c).cast("string").alias("level")) for c in columns])).alias("e")).select("e.*")
    counts = long.groupBy("dimension", "level").agg(F.count("*").alias("n"))
    return counts.withColumn("share", F.col("n") / F.sum("n").over(Window.partitionBy("dimension")))
