"""Helpers shared by the training-data operators."""

from __future__ import annotations

import sys
import types
import uuid

from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.io import cut, shared_folder  # noqa: F401  the operators take cut from here

#: The ASCII white space of the contracts: space, and tab to carriage return.
SPACES = r"[\x20\x09-\x0D]+"

#: A key table of at most this many rows may be broadcast (16 MB of longs); larger ones are joined by shuffle.
BROADCAST_ROWS = 1_000_000


def by_value(module_name: str) -> None:
    """Pickle a module's functions by value, so that executors need no copy of this package on their path."""
    cloudpickle.register_pickle_by_value(sys.modules[module_name])


by_value(__name__)


def process_cache(owner: str) -> dict:
    """A dictionary that lives as long as the Python worker, until another owner asks: one operator's memory at a time."""
    name = "_turnwise_worker_cache"
    if name not in sys.modules:
        sys.modules[name] = types.ModuleType(name)
        sys.modules[name].store = {}
        sys.modules[name].owner = owner
    if sys.modules[name].owner != owner:
        sys.modules[name].store = {}
        sys.modules[name].owner = owner
    return sys.modules[name].store


def trim() -> None:
    """Give freed memory back to the system: workers live on between tasks, and an executor's memory counts theirs."""
    import ctypes

    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def written(df: DataFrame) -> tuple[DataFrame, str]:
    """df as a Parquet table in the shared folder (smaller than a checkpoint), and its path, for removed()."""
    spark = df.sparkSession
    shared_folder(spark)
    base = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext._jsc.sc().getCheckpointDir().get()
    path = f"{base}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def removed(spark: SparkSession, path: str) -> None:
    """Delete a written table, on whatever file system it is."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)


def folded(text: Column) -> Column:
    """Null as empty; each run of ASCII white space as one space."""
    return F.regexp_replace(F.coalesce(text, F.lit("")), SPACES, " ")


def free_name(df: DataFrame, base: str) -> str:
    """A column name that df does not have."""
    taken = {c.lower() for c in df.columns}
    while base.lower() in taken:
        base += "_"
    return base


def is_small(df: DataFrame, rows: int = BROADCAST_ROWS) -> bool:
    """Whether a table has at most so many rows; reads no more than rows + 1 of them."""
    return df.limit(rows + 1).count() <= rows


def row_name(key: Column, text: Column) -> Column:
    """A hash by which a row is found again, with or without an id; rows that share it are copies in id and text."""
    return F.xxhash64(key, text)


def without_rows(docs: DataFrame, rows: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """docs without the rows named by rows (row, stays; each name once); of copies whose name stays, one remains.

    Text moves only when there are too many names to broadcast, or for the copies that are reduced to one.
    """
    h = free_name(docs, "_row")
    marked = docs.withColumn(h, row_name(F.col(key), F.col(text)))
    names = rows.select(F.col("row").alias(h))
    left = marked.join(F.broadcast(names) if is_small(names) else names, h, "left_anti")
    copied = rows.filter("stays").select(F.col("row").alias(h))
    if not copied.isEmpty():
        left = left.unionByName(marked.join(F.broadcast(copied) if is_small(copied) else copied, h, "left_semi").dropDuplicates([h]))
    return left.drop(h)
