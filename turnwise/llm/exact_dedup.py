"""Exact dedup by progressive refinement: length, then a prefix hash, then the full hash.

Only native DataFrame functions. The first pass keeps 16 bytes a row. Lengths that occur once leave at
once; of the rest, (length, prefix hash) pairs that occur once leave; SHA-256 of the whole text is taken
for the survivors alone. Where these pairs are too many to broadcast, a bitmap of at most BITMAP_BITS bits of
their hashes goes to the executors instead: it says of a row either that it is no survivor, or that it may be
one, which the narrow rows then settle by a join; no text moves and the result is the same. A group's
representative comes from a partial aggregate, so a group of any size sends one row per task, and the join back
is an ordinary equi-join that AQE may split when one key is hot.

Defined cases: a null text counts as empty; empty texts are equal to each other; of rows with equal text
the smallest doc_id stays (null ids last) and, of repeated ids, exactly one row; an empty table gives an
empty result; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut, folded, is_small, row_name, without_rows

PREFIX_CHARS = 256
#: 16 MB, broadcast in rows of 4 KB.
BITMAP_BITS = 1 << 27


def colliding(narrow: DataFrame) -> DataFrame:
    """(n_bytes, prefix_hash) pairs that more than one row has, found length first."""
    lengths = narrow.groupBy("n_bytes").agg(F.count("*").alias("_n")).filter("_n > 1").select("n_bytes")
    if is_small(lengths):
        lengths = F.broadcast(lengths)
    same_length = narrow.join(lengths, "n_bytes", "left_semi")
    return same_length.groupBy("n_bytes", "prefix_hash").agg(F.count("*").alias("_n")).filter("_n > 1").select("n_bytes", "prefix_hash")


def spot() -> Column:
    return F.pmod(F.xxhash64("n_bytes", "prefix_hash"), F.lit(BITMAP_BITS)) + 1


def marked(measured: DataFrame, survivors: DataFrame, few: bool) -> DataFrame:
    """measured with _maybe: false where a row's length and prefix hash are surely not among the survivors'."""
    if few:
        hit = survivors.withColumn("_maybe", F.lit(True))
        return measured.join(F.broadcast(hit), ["n_bytes", "prefix_hash"], "left").withColumn("_maybe", F.coalesce("_maybe", F.lit(False)))
    bits = survivors.groupBy(F.bitmap_bucket_number(spot()).alias("_bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(spot())).alias("_bits"))
    there = measured.withColumn("_bucket", F.bitmap_bucket_number(spot())).join(F.broadcast(bits), "_bucket", "left")
    at = F.bitmap_bit_position(spot())
    byte = F.conv(F.hex(F.substr("_bits", (F.floor(at / 8) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
    return there.withColumn("_maybe", F.coalesce(F.getbit(byte, (at % 8).cast("int")) == 1, F.lit(False)))


def resolved(docs: DataFrame, key: str, text: str, digest_all: bool) -> DataFrame:
    """_id, row (its name), keep_id, group_size, kept, text_sha256 of every row."""
    whole = folded(F.col(text))
    measured = docs.select(
        F.col(key).alias("_id"), row_name(F.col(key), F.col(text)).alias("row"), whole.alias("_t"), F.octet_length(whole).alias("n_bytes"),
        F.xxhash64(F.substring(whole, 1, PREFIX_CHARS)).alias("prefix_hash"),
    )
    survivors = cut(colliding(measured.select("n_bytes", "prefix_hash")))
    few = is_small(survivors)
    hashed = marked(measured, survivors, few).select("_id", "row", "n_bytes", "prefix_hash", F.col("_maybe").alias("_hit"), F.when(F.col("_maybe") | F.lit(digest_all), F.sha2("_t", 256)).alias("text_sha256"))
    if not few:
        sure = survivors.withColumn("_sure", F.lit(True))
        hashed = hashed.drop("_hit").join(sure, ["n_bytes", "prefix_hash"], "left").withColumn("_hit", F.coalesce("_sure", F.lit(False)))
        hashed = hashed.withColumn("text_sha256", F.when(F.col("_hit") | F.lit(digest_all), F.col("text_sha256")))
    rows = cut(hashed.select("_id", "row", "n_bytes", "_hit", "text_sha256").withColumn("_row", F.monotonically_increasing_id()))
    order = F.struct(F.col("_id").isNull().alias("none"), F.col("_id").alias("id"), F.col("_row").alias("row"))
    groups = (
        rows.filter("_hit").groupBy("n_bytes", "text_sha256").agg(F.min(order).alias("_first"), F.count("*").alias("_n")).filter("_n > 1")
        .select("n_bytes", "text_sha256", "_first", "_n", F.lit(True).alias("_dup"))
    )
    joined = rows.join(groups, ["n_bytes", "text_sha256"], "left")
    return joined.select(
        "_id",
        "row",
        F.when(F.col("_dup"), F.col("_first.id")).otherwise(F.col("_id")).alias("keep_id"),
        F.coalesce("_n", F.lit(1)).cast("long").alias("group_size"),
        F.coalesce(F.col("_first.row") == F.col("_row"), F.lit(True)).alias("kept"),
        "text_sha256",
    )


def progressive_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text", digest_all: bool = False) -> DataFrame:
    """One row per input row: key, keep_id, group_size, kept, text_sha256 (null where length and prefix hash occur once, unless digest_all)."""
    found = resolved(docs, key, text, digest_all)
    return found.select(F.col("_id").alias(key), "keep_id", "group_size", "kept", "text_sha256")


def keep_first(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """docs with one row of each group of equal texts; all columns as they were."""
    names = resolved(docs, key, text, False).groupBy("row").agg(F.max("kept").alias("stays"), F.count("*").alias("n"))
    return without_rows(docs, cut(names.filter("NOT stays OR n > 1").select("row", "stays")), key, text)
