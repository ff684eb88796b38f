"""Sharding by vector bin packing over bytes, tokens and rows.

Items are placed where the dot product of their vector with the residual capacity is highest. Groups of
equal text are never sent anywhere as rows: a hash deals them to a fixed number of packets, and a group that
weighs more than a small part of a shard is cut into chunks by row, whatever its ids, so the placed items are at most PACKETS +
2 * shards * HEAVY_PARTS + chunks, whatever the input. That bounded table of vectors is placed on the driver
and broadcast back; rows move once, to be numbered inside their packet.

Law `bytes`: shard sizes near equal. A closing pass moves and swaps small items while that narrows the
spread of bytes. Defined cases: a null text has size 16 and crc 0; equal rows share a packet; repeated ids
get slots of their own; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import cut

ROW_BYTES = 16
PACKETS = 16_384
HEAVY_PARTS = 64
#: Weights of bytes, tokens and rows in the dot product.
WEIGHTS = (1.0, 0.25, 0.1)


def place(vectors: np.ndarray, shards: int, weights: tuple[float, ...] = WEIGHTS) -> np.ndarray:
    """Shard of each item (rows of vectors: bytes, tokens, rows), largest first by the highest dot product."""
    n, dims = vectors.shape
    shard = np.zeros(n, dtype=np.int64)
    if not n:
        return shard
    cap = np.maximum(vectors.sum(axis=0), 1) / shards
    unit = vectors / cap
    w = np.asarray(weights[:dims])
    residual = np.ones((shards, dims))
    order = np.lexsort((np.arange(n), -vectors[:, 0]))
    for i in order:
        v = unit[i]
        score = residual @ (w * v)
        fits = (residual >= v - 1e-12).all(axis=1)
        score = np.where(fits, score, score - 1e6 + residual[:, 0]) if fits.any() else residual[:, 0]
        k = int(np.argmax(score))
        shard[i] = k
        residual[k] -= v
    return even_out(vectors[:, 0], shard, shards)


def even_out(size: np.ndarray, shard: np.ndarray, shards: int, rounds: int = 4000) -> np.ndarray:
    """Move or swap one item between the fullest and the emptiest shard while that brings them closer."""
    total = np.bincount(shard, weights=size, minlength=shards)
    members = [list(np.flatnonzero(shard == k)) for k in range(shards)]
    for _ in range(rounds):
        hi, lo = int(np.argmax(total)), int(np.argmin(total))
        gap = total[hi] - total[lo]
        if gap <= 1 or not members[hi]:
            break
        a = np.asarray(members[hi])
        b = np.asarray(members[lo])
        moves = size[a].astype(float)
        best = int(np.argmin(np.abs(moves - gap / 2)))
        change, swap = moves[best], None
        if len(b):
            sb = np.sort(size[b])
            want = size[a] - gap / 2
            at = np.clip(np.searchsorted(sb, want), 0, len(sb) - 1)
            for near in (at, np.maximum(at - 1, 0)):
                diff = size[a] - sb[near]
                j = int(np.argmin(np.abs(diff - gap / 2)))
                if abs(diff[j] - gap / 2) < abs(change - gap / 2):
                    change, best, swap = float(diff[j]), j, int(b[np.flatnonzero(size[b] == sb[near[j]])[0]])
        if not 0 < change < gap:
            break
        i = int(a[best])
        members[hi].remove(i)
        members[lo].append(i)
        shard[i] = lo
        if swap is not None:
            members[lo].remove(swap)
            members[hi].append(swap)
            shard[swap] = hi
        total[hi] -= change
        total[lo] += change
    return shard


def assign_shards(docs: DataFrame, shards: int = 40, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, size, text_crc32, law, shard, slot, grown_shard for every row of docs."""
    spark = docs.sparkSession
    body = F.coalesce(F.col(text), F.lit(""))
    rows = cut(
        docs.select(
            F.col(key).alias("_id"),
            (F.octet_length(body) + ROW_BYTES).cast("long").alias("size"),
            F.crc32(body.cast("binary")).alias("text_crc32"),
            (F.length(body) - F.length(F.translate(body, " \n\t\r", "")) + 1).cast("long").alias("tokens"),
            F.xxhash64(body).alias("_group"),
            F.monotonically_increasing_id().alias("_row"),
        )
    )
    sums = [F.sum("size").alias("size"), F.sum("tokens").alias("tokens"), F.count("*").alias("rows")]
    total = rows.agg(*sums).first()
    part = shards * HEAVY_PARTS
    most = max((total["size"] or 0) // part, 1)
    # A group over 1/part of all bytes: there are fewer than part of them.
    heavy = rows.groupBy("_group").agg(*sums).filter((F.col("size") > most) & (F.col("rows") > 1))
    heavy = heavy.select("_group", F.least(F.col("rows"), F.ceil(F.col("size") / F.lit(most)) * 4).cast("int").alias("_chunks"))
    packet = F.pmod(F.col("_group"), F.lit(PACKETS)).cast("long")
    chunk = F.pmod(F.xxhash64("_row"), F.col("_chunks").cast("long"))
    item = F.when(F.col("_chunks").isNull(), F.struct(F.lit(None).cast("long").alias("g"), packet.alias("k"))).otherwise(F.struct(F.col("_group").alias("g"), chunk.alias("k")))
    dealt = cut(rows.join(F.broadcast(heavy), "_group", "left").select("_id", "size", "text_crc32", "tokens", item.alias("_item")))
    # Bounded: PACKETS and the chunks of the heavy groups. Not through pandas, which would make floats of the ids.
    items = dealt.groupBy("_item").agg(*sums).select("_item.g", "_item.k", "size", "tokens", "rows").collect()
    items.sort(key=lambda r: (-r["size"], r["g"] is not None, r["g"] or 0, r["k"]))
    vectors = np.array([(r["size"], r["tokens"], r["rows"]) for r in items], dtype=float).reshape(-1, 3)
    made, filled = [], [0] * shards
    for r, s in zip(items, place(vectors, shards).tolist(), strict=True):
        made.append((r["g"], r["k"], s, filled[s]))
        filled[s] += r["rows"]
    placed = spark.createDataFrame(made, "g long, k long, shard int, first long")
    spots = dealt.join(F.broadcast(placed), F.col("_item.g").eqNullSafe(F.col("g")) & (F.col("_item.k") == F.col("k")), "left")
    inside = Window.partitionBy("_item").orderBy("_id", "text_crc32", "size")
    return spots.select(
        F.col("_id").alias(key),
        "size",
        "text_crc32",
        F.lit("bytes").alias("law"),
        "shard",
        (F.col("first") + F.row_number().over(inside) - 1).alias("slot"),
        F.lit(None).cast("int").alias("grown_shard"),
    )
