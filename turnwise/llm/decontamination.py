"""Benchmark decontamination by size-partitioned min-hash containment search, verified exactly.

Test items fall into partitions by the size of their shingle set (doubling bounds); the partition fixes how many of
an item's smallest shingle hashes make its sketch: one more than a set of the partition's largest size may lack at
the threshold. A document that holds that share of an item's shingles misses too few of them to miss its whole
sketch, however long the document is, so the search loses nothing, where banded signatures of long documents would.
Documents are streamed through the sketches in one pass of generated code: no document signature is stored, no
text is shuffled. A second pass over the documents with a candidate counts the candidates' distinct shingles in
them. Only native functions.

Words are `[^\\x20\\x09-\\x0D]+` with A-Z in lower case; shingles have five words; an item with fewer is one
shingle, looked up at its own width. Defined cases: a null or wordless text holds and finds nothing; repeated
ids are documents of their own; items that share an id are one item, null being an id; several items may match one document; empty tables give an empty result;
columns besides the id and the text are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import BROADCAST_ROWS, SPACES, cut, is_small, row_name, without_rows

WIDTH, PERCENT = 5, 75
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
_BLANKS = " \t\n\x0b\x0c\r"


def words(text: Column) -> Column:
    """Words of a text; one empty string if it has none."""
    plain = F.translate(F.coalesce(text, F.lit("")), _UPPER, _LOWER)
    return F.split(F.btrim(plain, F.lit(_BLANKS)), SPACES)


def shingles(docs: DataFrame, width: int) -> DataFrame:
    """docs (with a column words) by every run of width words: column gram, a 64-bit hash of the run."""
    spots = docs.filter(F.size("words") >= width).withColumn("at", F.explode(F.sequence(F.lit(0), F.size("words") - width)))
    return spots.withColumn("gram", F.xxhash64(F.lit(width), *[F.get("words", F.col("at") + k) for k in range(width)])).drop("words", "at")


def item_shingles(items: DataFrame, key: str, text: str, percent: int = PERCENT) -> DataFrame:
    """item_id, width, gram, item_shingles, in_sketch: the items' distinct shingles, the smallest hashes marked, as many as the size partition says."""
    # The id in a struct, for two structs with a null inside are equal.
    cut_up = items.select(F.struct(F.col(key).alias("id")).alias("item_id"), words(F.col(text)).alias("words")).filter(~((F.size("words") == 1) & (F.get("words", F.lit(0)) == "")))
    sized = cut_up.withColumn("width", F.least(F.size("words"), F.lit(WIDTH)))
    parts = [shingles(sized.filter(F.col("width") == w), w) for w in range(1, WIDTH + 1)]
    every = parts[0]
    for p in parts[1:]:
        every = every.unionByName(p)
    every = every.distinct()
    whole = every.groupBy("item_id").agg(F.count("*").alias("item_shingles"))
    ranked = every.withColumn("rank", F.row_number().over(Window.partitionBy("item_id").orderBy("gram"))).join(whole, "item_id")
    largest = F.pow(F.lit(2), F.length(F.bin("item_shingles"))) - 1  # the partition's
    sketch = largest - F.ceil(largest * percent / 100) + 1
    return ranked.select("item_id", "width", "gram", "item_shingles", (F.col("rank") <= sketch).alias("in_sketch"))


def by_width(rows: DataFrame, index: DataFrame, small: bool, widths: list[int]) -> DataFrame:
    """Shingles of rows that are in the index, each width looked up among its own."""
    hits = None
    for w in widths:
        of_width = index.filter(F.col("width") == w).drop("width")
        found = shingles(rows, w).join(F.broadcast(of_width) if small else of_width, "gram")
        hits = found if hits is None else hits.unionByName(found)
    return hits


def candidates(rows: DataFrame, index: DataFrame, small: bool, widths: list[int]) -> DataFrame:
    """row, item_id of every document that holds a shingle of the item's sketch."""
    sketches = index.filter("in_sketch").select("width", "gram", "item_id")
    return by_width(rows.select("row", "words"), sketches, small, widths).select("row", "item_id").distinct()


def contained_rows(docs: DataFrame, items: DataFrame, key: str, text: str, item_key: str, item_text: str, percent: int) -> DataFrame:
    """doc_id, row (its name), item_id, item_shingles, common, containment of every pair at or over the threshold."""
    index = cut(item_shingles(items, item_key, item_text, percent))
    widths = sorted(r["width"] for r in index.select("width").distinct().collect()) or [WIDTH]  # at most WIDTH values
    small = is_small(index, BROADCAST_ROWS // 4)
    named = docs.select(F.col(key).alias("doc_id"), row_name(F.col(key), F.col(text)).alias("row"), F.col(text).alias("text"))
    near = cut(candidates(named.select("row", words(F.col("text")).alias("words")), index, small, widths))
    with_any = near.select("row").distinct()
    chosen = named.join(F.broadcast(with_any) if is_small(with_any) else with_any, "row", "left_semi")  # before its words are cut
    hits = by_width(chosen.select("doc_id", "row", words(F.col("text")).alias("words")), index.drop("in_sketch"), small, widths).join(near, ["row", "item_id"], "left_semi")
    per_gram = hits.select("doc_id", "row", "item_id", "item_shingles", "gram").distinct()
    pairs = per_gram.groupBy("doc_id", "row", "item_id", "item_shingles").agg(F.count("*").alias("common"))
    verified = pairs.filter(F.col("common") * 100 >= F.col("item_shingles") * percent)
    verified = verified.withColumn("item_id", F.col("item_id")["id"])
    return verified.withColumn("containment", F.col("common") / F.col("item_shingles"))


def contained(docs: DataFrame, items: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text", percent: int = PERCENT) -> DataFrame:
    """doc_id, item_id, item_shingles, common, containment of every pair at or over the threshold."""
    found = contained_rows(docs, items, key, text, item_key, item_text, percent)
    return found.select("doc_id", "item_id", "item_shingles", "common", "containment").distinct()


def clean(docs: DataFrame, items: DataFrame, key: str = "doc_id", text: str = "text", item_key: str = "item_id", item_text: str = "text", percent: int = PERCENT) -> DataFrame:
    """docs without the rows that hold a test item, whatever their ids; all columns as they were."""
    bad = contained_rows(docs, items, key, text, item_key, item_text, percent).select("row").distinct()
    return without_rows(docs, cut(bad.withColumn("stays", F.lit(False))), key, text)
