"""N-gram Jaccard join by parity sketches.

Two documents link when the Jaccard similarity of their sets of five-word shingles is at least 0.75. With sizes
s and t that allows a symmetric difference of at most D = (s + t) // 7.

Size bands. A band holds the pairs with s + t up to its bound. In a band a set's shingles are dealt by hash to
K parts, and the parity (XOR) of the hashes in a part is that part of the set's sketch: one differing shingle
changes one part at most, so at most D parts differ (pigeonhole). Parts are compared as tokens (part, parity)
in their common order: a set shows its first d + 1 + m non-empty parts, d being the largest D that it can meet
in the band and m growing with d, and then a linked pair shares at least m + 1 shown tokens, m being that of the
smaller set; so a set is asked only for as many as its smallest possible partner. A pair of sets of which neither
has more than d non-empty parts is met through single shingles in the same way.

Steps: (1) one narrow row per document: size, and a hash that names the set, so that copies are one set from
here on; (2) tokens, as packed blocks dealt to buckets; those that only one set shows are gone at once, the others
know how many sets show them; (3) of the h shared tokens of a set of which a are asked for, the h - a + 1 rarest
are kept: two linked sets have at least a in common, so also one among the kept of both. A passage that many
documents hold gives each of them fewer tokens than asked for, so they leave without any pair being looked at;
(4) sets that keep a token in common are in one bundle (rounds in which names merge and their rows with them); (5) a bundle's
sets meet in one task, in the order of their sizes: pairs not yet connected whose one-bit parity sketches differ
in more than D bits are passed over, for that Hamming distance is a lower bound of the symmetric difference; the
others are verified on the shingles. A task returns one link for each set at most, whatever the number of pairs;
(6) components of the links by label propagation.

Bundles over MOST_SHINGLES do not go to one task: their sets first meet those with the same least token, in blocks,
and are connected by what is found; then the tokens whose sets are not in one component are compared across
components, by pairs of blocks. No link between different components is left out there either.

Set names and shingles are 64-bit hashes. Defined cases: without words, or null text, a set is empty and
linked with nothing; with fewer than five words the whole sequence is the one shingle; repeated rows are copies;
rows without an id are compared like others; very long texts are whole; an empty table gives an empty result;
other columns are ignored.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import by_value, cut, is_small, process_cache, removed, row_name, trim, without_rows, written

by_value(__name__)

WIDTH = 5
PERCENT = 75
#: Bound of s + t in the first band; each band's is twice the one before. Below it only equal sets link.
FIRST_SUM = 14
#: Parts of a band for each shingle of its largest difference, and shared tokens asked for beyond one.
PARTS, MORE = 2, 3
SKETCH_BITS = 2048
KEYS_PER_BUCKET = 1_000_000
#: Texts whose tokens are held at a time.
TEXTS = 1500
#: Shingles of a bundle that one task takes whole, of all the bundles of a task, and of a block of a larger bundle;
#: a set counts as LEAST_WEIGHT shingles at least.
MOST_SHINGLES, TASK_SHINGLES, BLOCK, LEAST_WEIGHT = 4_000_000, 1_000_000, 500_000, 256
_C = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F], dtype=np.uint64)
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
WORD_MEMO = 200_000


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _M1
    x = (x ^ (x >> np.uint64(27))) * _M2
    return x ^ (x >> np.uint64(31))


class Words(dict):
    """64-bit hashes of words, remembered."""

    def __missing__(self, word: bytes) -> int:
        if len(self) > WORD_MEMO:
            self.clear()
        h = self[word] = int.from_bytes(hashlib.blake2b(word, digest_size=8).digest(), "little")
        return h


def shingle_set(text: str | None, known: Words) -> np.ndarray:
    """Sorted distinct shingle hashes. bytes.lower and bytes.split do just what the contract's A-Z and white space say."""
    words = text.encode("utf-8", "replace").lower().split() if text else []
    if not words:
        return np.zeros(0, dtype=np.uint64)
    w = np.fromiter(map(known.__getitem__, words), dtype=np.uint64, count=len(words))
    if len(w) < WIDTH:
        return mix((w * _C[: len(w)]).sum(dtype=np.uint64, keepdims=True) + np.uint64(len(w)))
    n = len(w) - WIDTH + 1
    h = w[:n] * _C[0]
    for k in range(1, WIDTH):
        h += w[k : k + n] * _C[k]
    h = mix(h)
    h.sort()
    return h[np.concatenate(([True], h[1:] != h[:-1]))]


def largest_difference(s: int, bound: int) -> int:
    """d: the largest symmetric difference of a set of s shingles and one that it links with in the band of this bound."""
    return min(bound, s + s * 100 // PERCENT) * (100 - PERCENT) // (100 + PERCENT)


def bands(s: int) -> list[tuple[int, int, int, int]]:
    """(band, K, d, least d of its partners and itself) of every band in which a set of s shingles may have a partner other than its equal."""
    smallest = -(-s * PERCENT // 100)
    low, high = s + smallest, s + s * 100 // PERCENT
    out, band, bound, below = [], 0, FIRST_SUM, 6
    while below < high:
        if bound >= low:
            d = largest_difference(s, bound)
            if d > 0:
                out.append((band, PARTS * (bound // 7), d, min(d, largest_difference(max(smallest, below + 1 - s), bound))))
        band, below, bound = band + 1, bound, bound * 2
    return out


def asked(d: int) -> int:
    """Shared tokens that a linked pair has at least, when the set with the smaller d shows d + asked(d) tokens."""
    return 1 + d // MORE


def tokens(h: np.ndarray) -> list[tuple[int, int, np.ndarray]]:
    """(band, shared tokens asked for, token hashes) of a set, for each of its bands; band 255: single shingles."""
    out, s, alone = [], len(h), False
    mixed = mix(h + np.uint64(0x51ED270B))
    for band, parts, d, least in bands(s):
        part = ((h >> np.uint64(32)) * np.uint64(parts)) >> np.uint64(32)  # rises with h, so parts are runs
        first = np.flatnonzero(np.concatenate(([True], part[1:] != part[:-1])))
        want = asked(d)
        if len(first) < d + want:  # it shows all it has
            want = len(first) - d
            if want < 1:
                want, alone = 1, True
        shown = min(len(first), d + want)
        parity = np.bitwise_xor.reduceat(mixed, first)[:shown]
        out.append((band, min(want, asked(least)), mix(parity + (part[first[:shown]] * np.uint64(256) + np.uint64(band)) * _C[1])))
    if alone:
        prefix = s - -(-s * PERCENT // 100) + 1
        out.append((255, 1, mix(h[:prefix] + _C[2])))
    return out


def one_bit_sketch(h: np.ndarray) -> np.ndarray:
    """Each shingle flips one of SKETCH_BITS bits; as 64-bit words."""
    odd = np.bincount((h % np.uint64(SKETCH_BITS)).astype(np.int64), minlength=SKETCH_BITS) & 1
    return np.packbits(odd.astype(np.uint8)).view(np.uint64)


def set_name(h: np.ndarray) -> int:
    return int.from_bytes(hashlib.blake2b(h.tobytes(), digest_size=8).digest(), "little", signed=True)


def known_words() -> Words:
    return process_cache("shingles").setdefault("words", Words())


def named_sets(docs: DataFrame, key: str, text: str) -> DataFrame:
    """doc_id, row, n_shingles, name (null for the empty set)."""

    def run(batches):
        known = known_words()
        for b in batches:
            n, name = [], []
            for v in b.column(2):
                h = shingle_set(v.as_py(), known)
                n.append(len(h))
                name.append(set_name(h) if len(h) else None)
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(n, pa.int64()), pa.array(name, pa.int64())], ["doc_id", "row", "n_shingles", "name"])
        trim()

    kind = docs.schema[key].dataType.simpleString()
    narrow = docs.select(F.col(key).alias("doc_id"), row_name(F.col(key), F.col(text)).alias("row"), F.col(text).alias("text"))
    return narrow.mapInArrow(run, f"doc_id {kind}, row long, n_shingles long, name long")


def planes(a: np.ndarray) -> bytes:
    """An array's first bytes, then its second bytes and so on: the empty high ones cost nothing once compressed."""
    return np.ascontiguousarray(a.view(np.uint8).reshape(len(a), -1).T).tobytes()


def unplanes(raw: memoryview, n: int, kind: type) -> np.ndarray:
    width = np.dtype(kind).itemsize
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8, n * width).reshape(width, n).T).view(kind).ravel()


#: A token goes by its bucket and so many of its low bytes; that two share them by chance only costs a look.
LOW = 5


def pack_block(name, band, ask, count, token) -> bytes:
    """Slots (a set in a band) with the number of their tokens here, then the tokens."""
    low = np.ascontiguousarray(token.view(np.uint8).reshape(-1, 8)[:, :LOW])
    return len(name).to_bytes(4, "little") + b"".join((name.tobytes(), band.tobytes(), planes(ask), planes(count), low.tobytes()))


def unpack_block(raw) -> tuple[np.ndarray, ...]:
    """name, band, asked of each token, and the tokens' low bytes."""
    view = memoryview(raw)
    n = int.from_bytes(view[:4], "little")
    name, band = np.frombuffer(view[4:], np.int64, n), np.frombuffer(view[4 + 8 * n :], np.uint8, n)
    ask, count = unplanes(view[4 + 9 * n :], n, np.uint32), unplanes(view[4 + 13 * n :], n, np.uint32)
    low = np.frombuffer(view[4 + 17 * n :], np.uint8).reshape(-1, LOW)
    token = np.zeros((len(low), 8), dtype=np.uint8)
    token[:, :LOW] = low
    return *(np.repeat(a, count) for a in (name, band, ask)), token.view(np.uint64).ravel()


def shared_tokens(docs: DataFrame, text: str, buckets: int) -> DataFrame:
    """The tokens that at least two sets show: name, band, asked, token, shown (number of those sets)."""

    def deal(batches):
        known = known_words()
        for column in (b.column(0).slice(k, TEXTS) for b in batches for k in range(0, b.num_rows, TEXTS)):
            names, band, ask, count, every, seen = [], [], [], [], [], set()
            for v in column:
                h = shingle_set(v.as_py(), known)
                if not len(h) or (name := set_name(h)) in seen:
                    continue
                seen.add(name)
                for x, a, t in tokens(h):
                    names.append(name)
                    band.append(x)
                    ask.append(a)
                    count.append(len(t))
                    every.append(t)
            if not every:
                continue
            token = np.concatenate(every)
            bucket = (token >> np.uint64(8 * LOW)) % np.uint64(buckets)
            order = np.argsort(bucket, kind="stable")
            slot = np.repeat(np.arange(len(count), dtype=np.int32), count)[order]
            token, bucket = token[order], bucket[order]
            names, band, ask = np.array(names, dtype=np.int64), np.array(band, dtype=np.uint8), np.array(ask, dtype=np.uint32)
            edge = np.flatnonzero(np.concatenate(([True], bucket[1:] != bucket[:-1], [True])))
            keys, blocks = [], []
            for lo, hi in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
                own = slot[lo:hi]
                first = np.flatnonzero(np.concatenate(([True], own[1:] != own[:-1])))
                of = own[first]
                keys.append(int(bucket[lo]))
                blocks.append(pack_block(names[of], band[of], ask[of], np.diff(first, append=len(own)).astype(np.uint32), token[lo:hi]))
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int32()), pa.array(blocks, pa.binary())], ["bucket", "block"])
        trim()

    def meet(table: pa.Table) -> pa.Table:
        parts = [unpack_block(v.as_buffer()) for v in table.column("block")]
        name, band, ask, token = (np.concatenate([p[k] for p in parts]) for k in range(4))
        del parts
        order = np.argsort(token)
        run = token[order]
        same = run[1:] == run[:-1]
        order = order[np.concatenate((same, [False])) | np.concatenate(([False], same))]  # shown twice at least
        name, band, ask, token = (a[order] for a in (name, band, ask, token))
        order = np.lexsort((name, token))
        name, band, ask, token = (a[order] for a in (name, band, ask, token))
        new = np.concatenate(([True], (token[1:] != token[:-1]) | (name[1:] != name[:-1])))[: len(token)]  # a set once a token
        name, band, ask, token = (a[new] for a in (name, band, ask, token))
        first = np.flatnonzero(np.concatenate(([True], token[1:] != token[:-1])))[: len(token)]
        size = np.diff(first, append=len(token))
        shown = np.repeat(size, size)
        keep = shown > 1
        whole = (token[keep] | (np.uint64(table.column("bucket")[0].as_py()) << np.uint64(8 * LOW))).view(np.int64)
        return pa.table(
            [pa.array(name[keep]), pa.array(band[keep].astype(np.int32)), pa.array(ask[keep].astype(np.int32)), pa.array(whole), pa.array(shown[keep].astype(np.int32))],
            names=["name", "band", "asked", "token", "shown"],
        )

    dealt = docs.select(F.col(text).alias("text")).mapInArrow(deal, "bucket int, block binary")
    return dealt.groupBy("bucket").applyInArrow(meet, "name long, band int, asked int, token long, shown int")


def rarest(shared: DataFrame) -> DataFrame:
    """name, token: of a set's h shared tokens in a band, of which it is asked for a, the h - a + 1 rarest."""
    slot = Window.partitionBy("name", "band")  # as many rows as a set has tokens
    ranked = shared.withColumn("rank", F.row_number().over(slot.orderBy("shown", "token"))).withColumn("had", F.count("*").over(slot))
    return ranked.filter("rank <= had - asked + 1").select("name", "token")


def flattened(up: DataFrame) -> DataFrame:
    """root, to: where each label ends that is sent to a lower one, or to itself."""
    while True:
        after = cut(up.join(up.toDF("to", "far"), "to").select("root", F.col("far").alias("to"), (F.col("far") < F.col("to")).alias("moved")))
        up = after.select("root", "to")
        if after.filter("moved").isEmpty():
            return up


def bundled(kept: DataFrame) -> DataFrame:
    """name, bundle (its least name) of every set that keeps a token in common with another one.

    Rounds on the rows (set, token) themselves: a set goes to the least one with which it shares a token, the rows take
    the new names, and those of tokens that only one name holds leave. So no round has more rows than kept has.
    """
    rows, bundles = kept.select(F.col("name").alias("root"), "token"), None
    while True:
        open_ = rows.groupBy("token").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).filter("lo < hi").select("token", "lo")
        rows = cut(rows.join(open_, "token"))
        if bundles is not None and rows.isEmpty():
            return bundles
        up = flattened(cut(rows.groupBy("root").agg(F.min("lo").alias("to"))))
        if bundles is None:
            bundles = up.toDF("name", "bundle")
        else:
            bundles = cut(bundles.join(up.toDF("bundle", "to"), "bundle", "left").select("name", F.coalesce("to", "bundle").alias("bundle")))
        rows = rows.join(up, "root").select(F.col("to").alias("root"), "token").distinct()


def sets_of(docs: DataFrame, rows: DataFrame, key: str, text: str) -> DataFrame:
    """rows (row and other columns) with name and shingles (packed) of the documents that have those rows, each set once."""

    def run(batches):
        known = known_words()
        seen: set[int] = set()  # repeated rows are one set
        for b in (b.slice(k, TEXTS) for b in batches for k in range(0, b.num_rows, TEXTS)):
            names, packed, bundles = [], [], []
            for v, bundle in zip(b.column(0), b.column(1), strict=True):
                h = shingle_set(v.as_py(), known)
                if (name := set_name(h)) not in seen:
                    seen.add(name)
                    names.append(name)
                    packed.append(h.tobytes())
                    bundles.append(bundle.as_py())
            yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(packed, pa.binary()), pa.array(bundles, pa.int64())], ["name", "shingles", "bundle"])
        trim()

    held = docs.select(row_name(F.col(key), F.col(text)).alias("row"), F.col(text).alias("text"))
    chosen = held.join(F.broadcast(rows) if is_small(rows) else rows, "row").select("text", "bundle")
    return chosen.mapInArrow(run, "name long, shingles binary, bundle long")


def similar(a: int, b: int, common: int) -> bool:
    return 100 * common >= PERCENT * (a + b - common)


def forest(name: np.ndarray, sets: list[np.ndarray], root: np.ndarray, side: np.ndarray | None = None) -> list[tuple[int, int]]:
    """(a, b), a < b: for each set that links with another one, directly or through others here, a pair that says so.

    root: sets with the same one are connected already; side: only pairs of different sides are looked at.
    """
    n = np.array([len(h) for h in sets], dtype=np.int64)
    order = np.lexsort((name, n))
    name, n, sets = name[order], n[order], [sets[k] for k in order]
    bits = np.stack([one_bit_sketch(h) for h in sets])
    values, parent = np.unique(root[order], return_index=True)
    parent = parent[np.searchsorted(values, root[order])].tolist()
    known = parent.copy()
    side = side[order] if side is not None else None

    def find(x: int) -> int:
        while parent[x] != x:
            parent[x] = x = parent[parent[x]]
        return x

    ends = np.searchsorted(n, n * 100 // PERCENT, "right").tolist()
    for k, end in enumerate(ends):
        far = np.bitwise_count(bits[k + 1 : end] ^ bits[k]).sum(axis=1, dtype=np.int64)
        near = far <= (n[k + 1 : end] + n[k]) * (100 - PERCENT) // (100 + PERCENT)
        if side is not None:
            near &= side[k + 1 : end] != side[k]
        x = sets[k]
        for j in (np.flatnonzero(near) + k + 1).tolist():
            p, q = find(k), find(j)
            if p != q:
                y = sets[j]
                spot = y.searchsorted(x)
                if similar(len(x), len(y), int((y[np.minimum(spot, len(y) - 1)] == x).sum())):
                    parent[max(p, q)] = min(p, q)
    least: dict[int, int] = {}
    for k in range(len(sets)):
        p = find(k)
        least[p] = min(least.get(p, int(name[k])), int(name[k]))
    told = {(least[p], int(name[k])) for k in range(len(sets)) if (p := find(k)) != known[k] or p == k}
    return [(a, b) for a, b in told if a != b]


def joined_in_tasks(sets: DataFrame, keys: list[str]) -> DataFrame:
    """(a, b): the forests of groups of rows (name, shingles, bundle, and root and side where there are some) that have the same keys and bundle."""
    placed = "root" in sets.columns

    def run(table: pa.Table) -> pa.Table:
        bundle = table.column("bundle").to_numpy()
        order = np.lexsort((table.column("name").to_numpy(), bundle))
        name, bundle = table.column("name").to_numpy()[order], bundle[order]
        once = np.concatenate(([True], (name[1:] != name[:-1]) | (bundle[1:] != bundle[:-1])))
        order, name, bundle = order[once], name[once], bundle[once]
        raw = table.column("shingles").combine_chunks()
        root, side = (table.column(c).to_numpy()[order] if placed else None for c in ("root", "side"))
        edge = np.flatnonzero(np.concatenate(([True], bundle[1:] != bundle[:-1], [True])))
        found: list[tuple[int, int]] = []
        for lo, hi in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
            if hi - lo > 1:
                held = [np.frombuffer(raw[int(i)].as_buffer(), dtype=np.uint64) for i in order[lo:hi]]
                own = name[lo:hi] if root is None else root[lo:hi]
                found += forest(name[lo:hi], held, own, None if side is None or not side[lo:hi].any() else side[lo:hi])
        return pa.table([pa.array([p[0] for p in found], pa.int64()), pa.array([p[1] for p in found], pa.int64())], names=["a", "b"])

    return sets.groupBy(*keys).applyInArrow(run, "a long, b long")


def components(links: DataFrame) -> DataFrame:
    """name, root (the least name reachable) for every name with a link: least labels spread, with a jump to the label's label."""
    both = cut(links.select("a", "b").union(links.select("b", "a")).distinct())
    labels = cut(both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("name"), F.least("a", "m").alias("root")))
    while True:
        spread = both.join(labels.toDF("b", "r"), "b").groupBy("a").agg(F.min("r").alias("m")).toDF("name", "m")
        lower = labels.join(spread, "name").select("name", F.least("root", "m").alias("low"), "root")
        jump = labels.toDF("low", "far")
        after = cut(lower.join(jump, "low", "left").select("name", F.least("low", F.coalesce("far", "low")).alias("new"), "root"))
        moved = after.filter("new < root").limit(1).count()
        labels = after.select("name", F.col("new").alias("root"))
        if not moved:
            return labels


def links_of_large(kept: DataFrame, large: DataFrame, sets: DataFrame) -> DataFrame:
    """(a, b): links of bundles too large for one task. large: name, n; sets: name, shingles, bundle."""
    rows = kept.join(large.select("name", "n"), "name")
    shingles = sets.select("name", "shingles")
    # First the sets with the same least token, a block at a time: what is alike for the most part is connected here.
    first = rows.groupBy("name").agg(F.min("token").alias("token"), F.max("n").alias("n"))
    sizes = first.groupBy("token").agg(F.sum("n").alias("weight"))
    dealt = first.join(sizes, "token").select("token", "name", F.pmod(F.xxhash64("name"), F.ceil(F.col("weight") / BLOCK)).alias("i"))
    start = cut(joined_in_tasks(dealt.join(shingles, "name").withColumn("bundle", F.col("token")), ["token", "i"]))
    # Then whatever tokens have sets of several components, across components, by pairs of blocks.
    labels = components(start)
    rooted = rows.join(labels, "name", "left").select("token", "name", "n", F.coalesce("root", "name").alias("root"))
    open_ = rooted.groupBy("token").agg(F.min("root").alias("lo"), F.max("root").alias("hi"), F.sum("n").alias("weight")).filter("lo < hi").select("token", "weight")
    blocks = F.ceil(F.col("weight") / BLOCK).cast("int")
    own = F.pmod(F.xxhash64("name"), blocks).cast("int")
    far = rooted.join(open_, "token").withColumn("own", own).withColumn("peer", F.explode(F.sequence(F.lit(0), blocks - 1)))
    far = far.select("token", F.least("own", "peer").alias("i"), F.greatest("own", "peer").alias("j"), (F.col("own") > F.col("peer")).cast("int").alias("side"), "name", "root")
    across = joined_in_tasks(far.join(shingles, "name").withColumn("bundle", F.col("token")), ["token", "i", "j"])
    return start.unionByName(cut(across))


def linked(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, row, n_shingles, name, root (the component's: its least name; null for empty sets) of every row of docs."""
    spark = docs.sparkSession
    named = cut(named_sets(docs, key, text))
    total = named.agg(F.sum("n_shingles")).first()[0] or 0
    buckets = max(1, math.ceil(total * 0.6 / KEYS_PER_BUCKET))
    kept, path = written(rarest(shared_tokens(docs, text, buckets)))
    meta = named.filter("name is not null").groupBy("name").agg(F.min("row").alias("row"), F.greatest(F.max("n_shingles"), F.lit(LEAST_WEIGHT)).alias("n"))
    placed = cut(bundled(kept).join(meta, "name"))
    large = placed.groupBy("bundle").agg(F.sum("n").alias("n")).filter(F.col("n") > MOST_SHINGLES).select("bundle")
    large = cut(placed.join(large, "bundle", "left_semi"))
    tasks = max(1, math.ceil((placed.agg(F.sum("n")).first()[0] or 0) / TASK_SHINGLES))
    some = not large.isEmpty()
    small = placed.join(large.select("bundle").distinct(), "bundle", "left_anti") if some else placed
    links = cut(joined_in_tasks(sets_of(docs, small.select("row", "bundle"), key, text).withColumn("task", F.pmod(F.xxhash64("bundle"), F.lit(tasks))), ["task"]))
    if some:
        sets, more = written(sets_of(docs, large.select("row", "bundle"), key, text))
        links = links.unionByName(links_of_large(kept, large, sets))
        labels = components(links)
        removed(spark, more)
    else:
        labels = components(links)
    removed(spark, path)  # nothing below reads it
    return named.join(labels, "name", "left").select("doc_id", "row", "n_shingles", "name", F.coalesce("root", "name").alias("root"))


def near_duplicates(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id of every document."""
    found = cut(linked(docs, key, text))
    least = found.filter("root is not null").groupBy("root").agg(F.min("doc_id").alias("component_id"))
    return found.join(least, "root", "left").select(F.col("doc_id").alias(key), "n_shingles", F.coalesce("component_id", "doc_id").alias("component_id"))


def one_of_each(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """docs with one row of each component, that with the smallest id (rows without an id last); all columns as they were."""
    found = cut(linked(docs, key, text))
    order = F.struct(F.col("doc_id").isNull().alias("none"), F.col("doc_id").alias("id"), F.col("row").alias("row"))
    chosen = found.filter("root is not null").groupBy("root").agg(F.min(order)["row"].alias("first"))
    rows = found.join(chosen, "root").groupBy("row").agg(F.first("first").alias("first"), F.count("*").alias("n"))
    gone = cut(rows.filter("row <> first OR n > 1").select("row", (F.col("row") == F.col("first")).alias("stays")))
    return without_rows(docs, gone, key, text)
