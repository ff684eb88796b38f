"""Readers of tables and dialogues, and writers of the engine's results."""

from __future__ import annotations

import re
import tempfile

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import schemas

NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
VERDICT_COLUMNS = ("verdict", "votes", "judge", "subtype_matches", "dropped_at")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tables(spark: SparkSession, sf_dir: str) -> dict[str, DataFrame]:
    return {n: table(spark, sf_dir, n) for n in NAMES}


def register(spark: SparkSession, sf_dir: str) -> None:
    """The tables as temporary views, for queries given as SQL text."""
    for name, df in tables(spark, sf_dir).items():
        df.createOrReplaceTempView(name)


def shared_folder(spark: SparkSession) -> None:
    """Use the session's spark.checkpoint.dir; only in local mode, where that is unset (tests, a laptop), make a local one."""
    if not spark.conf.get("spark.checkpoint.dir", None) and spark.sparkContext._jsc.sc().getCheckpointDir().isEmpty():
        if not re.fullmatch(r"local(\[[^\]]*\])?", spark.sparkContext.master):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="turnwise-checkpoint-"))


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint: the rows are on shared storage, so a lost executor costs nothing that came before."""
    shared_folder(df.sparkSession)
    return df.checkpoint(eager=True)


def read_dialogues(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """Turns (schema TURN) from parquet, JSON lines or CSV; never inferred."""
    return spark.read.schema(schemas.TURN).format(fmt).option("header", "true").load(path)


def read_sql_texts(spark: SparkSession, path: str) -> DataFrame:
    """One statement per file: path, sql."""
    return spark.read.text(path, wholetext=True).select(F.input_file_name().alias("path"), F.col("value").alias("sql"))


def stream_turns(spark: SparkSession, path: str, fmt: str = "json") -> DataFrame:
    return spark.readStream.schema(schemas.TURN).format(fmt).load(path)


def write_metrics(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").partitionBy("protocol", "sample_type").parquet(path)


def write_turns(df: DataFrame, name: str, buckets: int = 64) -> None:
    """Turns bucketed by run, so that later folds need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, "run_id").sortBy("run_id", "turn_no").saveAsTable(name)


def write_rejected(df: DataFrame, path: str) -> None:
    df.filter(F.col("dropped_at").isNotNull()).write.mode("overwrite").partitionBy("dropped_at").parquet(path)


def blind(df: DataFrame) -> DataFrame:
    """A view for human audit: without the columns that tell the automated verdicts."""
    return df.drop(*[c for c in df.columns if c in VERDICT_COLUMNS])
