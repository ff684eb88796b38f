"""Operators on documents against brute force, round trips and the library, with the odd cases."""

import hashlib
import itertools
import random
import re
import textwrap
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from turnwise.llm import decontamination, exact_dedup, jaccard_join, license_scan, packing, queries, sharding, token_counts
from turnwise.llm.common import table

from .conftest import LONG, WORDS, odd_rows


def words(text):
    return [w for w in re.split(r"[\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m.group().lower(), text or "")) if w]


def shingles(text):
    w = words(text)
    return {" ".join(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set()


def brute_components(rows):
    """rows: (id, text). Returns id-less list of (n, least id of the component) in the rows' order."""
    sets = [shingles(t) for _, t in rows]
    parent = list(range(len(rows)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i, j in itertools.combinations(range(len(rows)), 2):
        if sets[i] and sets[j] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
            parent[find(j)] = find(i)
    least = {}
    for i, (key, _) in enumerate(rows):
        if key is not None:
            least[find(i)] = min(key, least.get(find(i), key))
    return [(len(sets[i]), least.get(find(i), rows[i][0])) for i in range(len(rows))]


def mutants(seed=3):
    """Families of texts around the threshold, of many sizes, with a passage that unrelated texts share."""
    rng = np.random.default_rng(seed)
    fresh = lambda n: [f"w{v}" for v in rng.integers(0, 10**6, n)]
    passage, rows = fresh(30), []
    for size in (3, 5, 6, 7, 9, 12, 20, 40, 90, 200, 500):
        for _ in range(3):
            base = fresh(size)
            for share in (0, 0.01, 0.02, 0.03, 0.05, 0.08):
                w = list(base)
                for at in rng.integers(0, size, int(round(share * size))):
                    w[at] = f"m{rng.integers(0, 10**6)}"
                rows.append(" ".join(w[: max(1, size - int(rng.integers(0, 1 + size // 12)))]))
    rows += [" ".join(fresh(int(rng.integers(5, 60))) + passage + fresh(int(rng.integers(5, 60)))) for _ in range(40)]
    return list(enumerate(rows))


def test_jaccard_join(spark):
    rows = mutants()
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_join.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()}
    want = dict(zip([k for k, _ in rows], brute_components(rows), strict=True))
    assert got == want and len({c for _, c in want.values()}) < len(rows) - 60


@pytest.mark.parametrize("seed,block", [(8, 700), (9, 5000)])
def test_jaccard_join_in_blocks(spark, monkeypatch, seed, block):
    """Every bundle as one that is too large for a task, in tiny blocks."""
    rows = mutants(seed)
    monkeypatch.setattr(jaccard_join, "MOST_SHINGLES", 600)
    monkeypatch.setattr(jaccard_join, "BLOCK", block)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_join.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()}
    assert got == dict(zip([k for k, _ in rows], brute_components(rows), strict=True))


def test_jaccard_join_loose_cluster(spark):
    """One large group of near copies of which some link and most do not: one link for each set at most comes out of a task."""
    rng = np.random.default_rng(4)
    base = [f"b{k}" for k in range(60)]
    rows = []
    for k in range(400):
        w = list(base)
        for at in rng.integers(0, 60, int(rng.integers(0, 6))):
            w[at] = f"x{rng.integers(0, 50)}"
        rows.append((k, " ".join(w)))
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_join.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()}
    assert got == dict(zip([k for k, _ in rows], brute_components(rows), strict=True))


def test_rarest_tokens_are_enough():
    """Of two linked sets' shared tokens, the h - a + 1 rarest of each have one in common, in any order of rarity."""
    rng = np.random.default_rng(6)
    for _ in range(300):
        n = int(rng.integers(4, 300))
        a = np.unique(rng.integers(0, 2**63, n, dtype=np.uint64))
        b = np.unique(np.concatenate((a[int(rng.integers(0, n // 6 + 1)) :], rng.integers(0, 2**63, int(rng.integers(0, n // 8 + 1)), dtype=np.uint64))))
        common = len(np.intersect1d(a, b))
        if not len(b) or not jaccard_join.similar(len(a), len(b), common) or common == len(a) == len(b):
            continue
        rank = lambda t: (int(t) * 2654435761) % 1000003
        x, y = ({band: set(sorted(t.tolist(), key=lambda v: (rank(v), v))[: len(t) - ask + 1]) for band, ask, t in jaccard_join.tokens(s)} for s in (a, b))
        assert any(x[k] & y[k] for k in x.keys() & y.keys())


def test_packed_blocks():
    rng = np.random.default_rng(0)
    name, band = rng.integers(-(2**62), 2**62, 5), np.array([0, 1, 255, 3, 4], dtype=np.uint8)
    ask, count = np.array([1, 70_000, 3, 4, 5], dtype=np.uint32), np.array([2, 1, 70_000, 1, 3], dtype=np.uint32)
    token = rng.integers(0, 2**40, int(count.sum()), dtype=np.uint64)
    for got, want in zip(jaccard_join.unpack_block(jaccard_join.pack_block(name, band, ask, count, token)), (np.repeat(name, count), np.repeat(band, count), np.repeat(ask, count), token), strict=True):
        assert (got == want).all()


def test_jaccard_join_odd(odd, nothing):
    rows = [(r[0], r[1]) for r in odd_rows()]
    got = sorted(((r.doc_id, r.n_shingles, r.component_id) for r in jaccard_join.near_duplicates(odd).collect()), key=str)
    assert got == sorted(((k, n, c) for (k, _), (n, c) in zip(rows, brute_components(rows), strict=True)), key=str)
    assert jaccard_join.near_duplicates(nothing).collect() == []
    left = jaccard_join.one_of_each(odd)
    assert left.columns == odd.columns and sorted((r.doc_id, r.text) for r in left.collect() if r.doc_id is None) == [(None, "nobody's row, with <|endoftext|> inside")]
    assert sorted(r.doc_id for r in left.collect() if r.doc_id is not None) == [1, 5, 6, 7, 8, 10, 12, 13]


def test_shown_tokens_meet():
    """The pigeonhole promise itself: linked pairs share as many shown tokens as are asked for."""
    rng = np.random.default_rng(1)
    for _ in range(300):
        n = int(rng.integers(4, 400))
        a = rng.integers(0, 2**63, n, dtype=np.uint64)
        cut = int(rng.integers(0, n // 6 + 1))
        b = np.unique(np.concatenate((a[cut:], rng.integers(0, 2**63, int(rng.integers(0, n // 8 + 1)), dtype=np.uint64))))
        a = np.unique(a)
        common = len(np.intersect1d(a, b))
        if not len(b) or not jaccard_join.similar(len(a), len(b), common) or common == len(a) == len(b):
            continue
        x, y = ({band: (ask, set(t.tolist())) for band, ask, t in jaccard_join.tokens(s)} for s in (a, b))
        assert any(len(x[k][1] & y[k][1]) >= max(x[k][0], 1) and len(x[k][1] & y[k][1]) >= max(y[k][0], 1) for k in x.keys() & y.keys())


def test_shown_tokens_meet_at_every_size():
    """All pairs of sizes from 4 to 40 shingles that can link, as far apart as a link allows: each set gets its own ask."""
    rng = np.random.default_rng(2)
    for s, t in itertools.combinations_with_replacement(range(4, 41), 2):
        common = -(-75 * (s + t) // 175)
        if common > s:
            continue
        for k in range(120):
            n = min(s, common + (k % 3))  # the largest difference most of the time
            h = np.unique(rng.integers(0, 2**63, 2 * (s + t), dtype=np.uint64) * np.uint64(2))
            h = rng.permutation(h)[: s + t - n]
            a, b = np.sort(h[:s]), np.sort(np.concatenate((h[:n], h[s:])))
            assert (len(a), len(b)) == (s, t) and jaccard_join.similar(s, t, n)
            if n == s == t:
                continue
            x, y = ({band: (ask, set(v.tolist())) for band, ask, v in jaccard_join.tokens(z)} for z in (a, b))
            assert any(len(x[z][1] & y[z][1]) >= max(x[z][0], y[z][0], 1) for z in x.keys() & y.keys()), (s, t, n)


def normal(text):
    return re.sub(r"[\x20\x09-\x0D]+", " ", text or "")


def test_exact_dedup_odd(odd, nothing):
    rows = [(r[0], normal(r[1])) for r in odd_rows()]
    got = exact_dedup.progressive_duplicates(odd, digest_all=True).collect()
    assert len(got) == len(rows) and sum(r.kept for r in got) == len({t for _, t in rows})
    for r in got:
        same = [k for k, t in rows if hashlib.sha256(t.encode()).hexdigest() == r.text_sha256]
        assert r.group_size == len(same) and r.keep_id == min((k for k in same if k is not None), default=None)
    assert exact_dedup.progressive_duplicates(nothing).collect() == []
    kept = exact_dedup.keep_first(odd)
    assert kept.columns == odd.columns
    ids = [r.doc_id for r in kept.collect()]
    assert sorted(i for i in ids if i is not None) == [1, 4, 5, 7, 8, 9, 10, 11, 12, 13] and ids.count(None) == 1


def test_sharding(spark, small, odd, nothing):
    docs = table(spark, small, "documents")
    hot = docs.unionByName(spark.range(300).select((F.col("id") + 10_000).alias("doc_id"), F.lit("copy " * 40).alias("text")), allowMissingColumns=True)
    for df, shards in ((docs, 40), (hot, 7), (odd, 4)):
        got = sharding.assign_shards(df, shards).toPandas()
        assert len(got) == df.count() and set(got["law"]) == {"bytes"}
        for _, g in got.groupby("shard"):
            assert sorted(g["slot"]) == list(range(len(g)))
    got = sharding.assign_shards(hot, 7).toPandas().groupby("shard")["size"].sum()
    assert len(got) == 7 and got.max() / got.min() < 1.02
    nobody = docs.unionByName(spark.range(300).select(F.lit(None).cast("long").alias("doc_id"), F.lit("copy " * 400).alias("text")), allowMissingColumns=True)
    sizes = sharding.assign_shards(nobody, 7).toPandas().groupby("shard")["size"].sum()  # one text without an id holds most bytes
    assert len(sizes) == 7 and sizes.max() / sizes.min() < 1.02
    crc = {r.doc_id: (r.text_crc32, r["size"]) for r in sharding.assign_shards(docs).collect()}
    assert all(crc[r.doc_id] == (zlib.crc32(r.text.encode()), len(r.text.encode()) + 16) for r in docs.collect())
    assert sharding.assign_shards(nothing).collect() == []


HARD = ["", "x's we'll I'M 'S \"'s", "½ ² 12½", "日本 語", "é́", "_a_b__ c", "\x1c\x1d a", "a<|endoftext|>b", " " * 7 + "\n", "  a  \n\n b\t", "naïve Über ÑANDÚ", "tab\tand\r\nbreak", "0123456789", "a" * 3000]


def test_token_counts(spark, small, nothing):
    from tokenizers import Tokenizer

    path = queries.tokenizer_path("byte_bpe_50k.json")
    texts = HARD + [r.text for r in table(spark, small, "documents").collect()]
    got = {r.doc_id: r for r in token_counts.count_tokens(spark.createDataFrame([*enumerate(texts), (-1, None)], "doc_id long, text string"), path).collect()}
    want = [len(e.ids) for e in Tokenizer.from_file(path).encode_batch(texts, add_special_tokens=False)]
    assert [got[i].n_tokens for i in range(len(texts))] == want and got[-1].n_tokens == 0
    assert all(got[i].n_bytes == len(t.encode()) and got[i].over_limit == (n > 512) for i, (t, n) in enumerate(zip(texts, want, strict=True)))
    assert token_counts.count_tokens(nothing, path).collect() == []


def check_packing(rows, docs, tokenizer):
    """rows hold exactly the documents' ids, in sequences of at most 2048 without gaps."""
    want = sorted(
        (str(k), i, p, min(2048, len(ids) - p), zlib.crc32(np.asarray(ids[p : p + 2048], dtype="<u4").tobytes()))
        for k, text in docs for ids in [[*tokenizer.encode(text or "", add_special_tokens=False).ids, 0]] for i, p in enumerate(range(0, len(ids), 2048))
    )
    assert sorted((str(r.doc_id), r.piece, r.start, r.length, r.ids_crc32) for r in rows) == want
    bins = {}
    for r in rows:
        bins.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for held in bins.values():
        at = 0
        for offset, length in sorted(held):
            assert offset == at
            at += length
        assert at <= 2048
    return len(bins), -(-sum(r.length for r in rows) // 2048)


def test_packing(spark, small, odd, nothing):
    from tokenizers import Tokenizer

    path = queries.tokenizer_path("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    docs = [(r.doc_id, r.text) for r in table(spark, small, "documents").collect()] + [(-1 - i, t) for i, t in enumerate(HARD)]
    n, least = check_packing(packing.pack_documents(spark.createDataFrame(docs, "doc_id long, text string"), path).collect(), docs, library)
    assert n <= least + 1
    check_packing(packing.pack_documents(odd, path).collect(), [(r[0], r[1]) for r in odd_rows()], library)
    assert packing.pack_documents(nothing, path).collect() == []


def test_packing_encoder(monkeypatch):
    """Ids as the library gives them: mixed chunks, signs in runs, contractions, letters of two bytes, long chunks, a full memory."""
    encoder = packing.Encoder(queries.tokenizer_path("word_bpe_49k.json"))
    draw = random.Random(5)
    signs = "abcdestmrvlABZ'’  \n\t019_.,!?-éßüÄÿ日"
    texts = ["".join(draw.choice(signs) for _ in range(draw.randint(0, 80))) for _ in range(3000)]
    texts += ["", " \x0b ", "I'm don't we'LL 'sup 's's'd", "a... b,c. d_.e", "<|startoftext|> a", "x<|endoftext|>", "Ab1+/" * 20_000, "é" * 3_000]
    for chars in (packing.MEMO_CHARS, 500):
        monkeypatch.setattr(packing, "MEMO_CHARS", chars)
        for k in range(0, len(texts), 64):
            part = texts[k : k + 64]
            assert encoder.encode_all(part) == [encoder.whole(t) for t in part]
        # what is remembered is at most the bound, or one batch's own chunks
        assert encoder.held <= max(chars, sum(map(len, part)))


def test_packing_learns_a_word_once(monkeypatch):
    """While the memory lasts, no chunk is encoded twice; a full one keeps at most the last batch; slices, nulls, no texts."""
    import pyarrow as pa

    encoder = packing.Encoder(queries.tokenizer_path("word_bpe_49k.json"))
    learned, learn = [], encoder.learn
    monkeypatch.setattr(encoder, "learn", lambda chunks: learned.extend(chunks) or learn(chunks))
    letters = [chr(97 + n % 26) + chr(97 + n // 26 % 26) + chr(97 + n // 676 % 26) + chr(97 + n // 17576) for n in range(120_000)]
    texts = [" ".join(letters[k : k + 2000]) for k in range(0, 120_000, 2000)]
    first = encoder.encode_all(texts)
    assert len(learned) == len(set(learned)) == 120_000
    assert encoder.encode_all(texts) == first and len(learned) == 120_000
    assert first[7] == encoder.whole(texts[7])
    monkeypatch.setattr(packing, "MEMO", 2500)
    assert encoder.encode_all([texts[3], "new one"]) == [first[3], encoder.whole("new one")] and len(encoder.words) == 2002
    assert encoder.encode_all(texts) == first and len(encoder.words) == encoder.held == 0
    column = pa.array(["out", None, "", " a, b ", "日 x", "a's"]).slice(1)
    assert encoder.encode(column) == [encoder.whole(t or "") for t in column.to_pylist()]
    assert encoder.encode_all([]) == [] and encoder.encode_all(["", " "]) == [b"", b""]
    assert [p.to_pylist() for p in packing.batched(pa.array(["aaaa", None, "", "b", "cc", "ddddd", "e"]).slice(1), 3)] == [[None, "", "b", "cc"], ["ddddd"], ["e"]]


def test_packing_spreads_one_id(spark, monkeypatch):
    """Rows without an id, and copies of one row, go to all cells."""
    monkeypatch.setattr(packing, "CELL_DOCS", 50)
    path = queries.tokenizer_path("word_bpe_49k.json")
    from tokenizers import Tokenizer

    docs = [(None, "the same words again")] * 300 + [(7, f"text {i}") for i in range(100)]
    rows = packing.pack_documents(spark.createDataFrame(docs, "doc_id long, text string"), path).collect()
    check_packing(rows, docs, Tokenizer.from_file(path))
    cells = {}
    for r in rows:
        cells[r.sequence_id >> 32] = cells.get(r.sequence_id >> 32, 0) + 1
    assert len(cells) == 8 and max(cells.values()) < 100


def test_local_search_improves():
    rng = np.random.default_rng(5)
    for low, high in ((1, 2048), (400, 1300), (600, 1100)):
        lengths = rng.integers(low, high, 3000).tolist()
        b = packing.Bins(lengths, 2048)
        b.best_fit()
        before = sum(map(bool, b.items))
        b.improve()
        assert sorted(i for x in b.items for i in x) == list(range(3000)) and all(sum(lengths[i] for i in x) <= 2048 for x in b.items)
        assert all(b.room[k] == 2048 - sum(lengths[i] for i in x) for k, x in enumerate(b.items))
        assert -(-sum(lengths) // 2048) <= sum(map(bool, b.items)) <= before


def test_decontamination(spark, odd, nothing):
    item = " ".join(f"q{i}" for i in range(30))
    far = " ".join(f"z{i}" for i in range(3000))
    edited = item.replace("q3 ", "xx ")
    rows = [(1, f"{far} {item} {far}"), (2, far), (3, f"{far} {edited} {far}"), (4, " ".join(item.split()[:15])), (5, "Tiny Item here"), (6, None), (7, item.upper()), (7, "other words only"), (8, "")]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("item_id", F.lit("clash"))
    items = spark.createDataFrame([(10, item), (11, "tiny item"), (12, None), (13, ""), (14, "absent one two three four five")], "item_id long, text string")
    got = {(r.doc_id, r.item_id): (r.common, r.item_shingles) for r in decontamination.contained(docs, items).collect()}
    want = {}
    for k, t in rows:
        for q, x in ((10, item), (11, "tiny item"), (14, "absent one two three four five")):
            w = words(x)
            width = min(5, len(w))
            grams = lambda v, width=width: {tuple(v[i : i + width]) for i in range(len(v) - width + 1)}
            a = grams(w)
            n = len(a & grams(words(t)))
            if n * 100 >= 75 * len(a):
                want[k, q] = (n, len(a))
    assert got == want and (1, 10) in got and (3, 10) in got and (4, 10) not in got and (5, 11) in got
    left = decontamination.clean(docs, items)
    assert left.columns == docs.columns and {(r.doc_id, r.text) for r in left.collect()} == {r for r in rows if r[0] in (2, 4, 6, 8) or r[1] == "other words only"}
    assert decontamination.contained(nothing, items).collect() == [] and decontamination.contained(docs, nothing.withColumnRenamed("doc_id", "item_id")).collect() == []
    assert decontamination.clean(odd, items).count() == odd.count()


def test_decontamination_without_broadcast(spark, small, monkeypatch):
    args = (table(spark, small, "documents"), table(spark, small, "benchmark"))
    want = sorted(map(str, decontamination.contained(*args).collect()))
    monkeypatch.setattr(decontamination, "is_small", lambda *a, **k: False)
    assert sorted(map(str, decontamination.contained(*args).collect())) == want


def test_decontamination_searches_by_sketch(spark, monkeypatch):
    """A size partition has one sketch length, and nothing but the sketches' candidates is verified."""
    items = spark.createDataFrame([(n, " ".join(f"i{n}w{k}" for k in range(n + 4))) for n in (1, 2, 3, 7, 16, 20, 31, 32)], "item_id long, text string")
    got = {r.item_id: r.n for r in decontamination.item_shingles(items, "item_id", "text").groupBy(F.col("item_id")["id"].alias("item_id")).agg(F.sum(F.col("in_sketch").cast("int")).alias("n")).collect()}
    assert got == {1: 1, 2: 1, 3: 1, 7: 2, 16: 8, 20: 8, 31: 8, 32: 16}
    docs = items.withColumnRenamed("item_id", "doc_id").unionByName(spark.createDataFrame([(None, "i7w0 " + " ".join(f"i7w{k}" for k in range(11)))], "doc_id long, text string"))
    assert len(decontamination.contained(docs, items).collect()) == 9
    search = decontamination.candidates
    monkeypatch.setattr(decontamination, "candidates", lambda *a: search(*a).filter("item_id.id <> 20"))
    assert {r.item_id for r in decontamination.contained(docs, items).collect()} == {1, 2, 3, 7, 16, 31, 32}


@pytest.mark.parametrize("digest_all", [False, True])
def test_exact_dedup_without_broadcast(spark, small, odd, monkeypatch, digest_all):
    """The same rows by broadcast pairs and by bitmap, digests of survivors alone included."""
    for docs in (table(spark, small, "documents"), odd):
        want = sorted(map(str, exact_dedup.progressive_duplicates(docs, digest_all=digest_all).collect()))
        assert digest_all or any("text_sha256=None" in r for r in want)
        kept = sorted(map(str, exact_dedup.keep_first(docs).collect()))
        with monkeypatch.context() as m:
            m.setattr(exact_dedup, "is_small", lambda *a, **k: False)
            assert sorted(map(str, exact_dedup.progressive_duplicates(docs, digest_all=digest_all).collect())) == want
            assert sorted(map(str, exact_dedup.keep_first(docs).collect())) == kept


def test_rows_go_by_row(spark):
    """Null and repeated ids: what goes is the row, not its id."""
    item = " ".join(f"q{i}" for i in range(30))
    near = item.replace("q29", "qq")
    rows = [(None, item), (None, "clean words of nobody"), (5, item), (5, "another clean text"), (5, "another clean text"), (6, near), (None, near), (None, near)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").withColumn("_row", F.lit("clash"))
    items = spark.createDataFrame([(1, item), (1, item), (None, item)], "item_id long, text string")
    same = lambda df: sorted(map(str, [(r.doc_id, r.text) for r in df.collect()]))
    left = decontamination.clean(docs, items)
    assert left.columns == docs.columns and same(left) == sorted(map(str, [r for r in rows if r[1] not in (item, near)]))
    assert {(r.doc_id, r.item_id) for r in decontamination.contained(docs, items).collect()} == {(k, i) for k in (None, 5, 6) for i in (1, None)}
    assert same(exact_dedup.keep_first(docs)) == sorted(map(str, [(None, "clean words of nobody"), (5, item), (5, "another clean text"), (6, near)]))
    assert same(jaccard_join.one_of_each(docs)) == sorted(map(str, [(None, "clean words of nobody"), (5, item), (5, "another clean text")]))


def test_license_scan(spark, odd, nothing):
    apache = "Licensed under the Apache License, Version 2.0 (the License). You may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0"
    rows = [(1, f"Prose.\n{apache}\nMore."), (2, "Released under the MIT License. All rights reserved."), (3, "no licence here"), (4, None), (5, "Licensed under CC BY-NC 4.0."), (6, "Released under the MIT License.\n" * 2)]
    got = {r.doc_id: (r.n_sentences, r.sentence_ids, r.licenses) for r in license_scan.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {
        1: (3, "apache2-notice|apache2-use|apache2-obtain", "Apache-2.0"), 2: (2, "mit-notice|reserved", "MIT|Proprietary"), 5: (1, "ccbync4-notice", "CC-BY-NC-4.0"), 6: (2, "mit-notice|mit-notice", "MIT"),
    }
    assert license_scan.scan(odd).collect() == [] and license_scan.scan(nothing).collect() == []


def test_license_scan_of_wrapped_text(spark, odd, nothing):
    """Licence texts as they stand in source files: wrapped, and behind comment marks."""
    grant = textwrap.fill(license_scan.SENTENCES["mit-grant"][0].capitalize(), 60) + ":"
    condition = textwrap.fill(license_scan.SENTENCES["mit-condition"][0].capitalize(), 60) + "."
    mit = f"MIT License\n\nCopyright (c) Somebody\n\n{grant}\n\n{condition}\n"
    header = "Licensed under the Apache License, Version 2.0 (the \"License\");\nyou may not use this file except in compliance with the License.\nMore prose here."
    commented = "".join(f"# {line}\n" for line in mit.split("\n"))
    one_line = "Released under the MIT License. All rights reserved."
    docs = spark.createDataFrame([(1, mit), (2, commented), (3, header), (4, one_line), (5, None), (6, "permission is\n\nhereby granted")], "doc_id long, text string")
    got = {r.doc_id: (r.sentence_ids, r.licenses) for r in license_scan.scan(docs, wrapped=True).collect()}
    assert got == {1: ("mit-grant|mit-condition", "MIT"), 2: ("mit-grant|mit-condition", "MIT"), 3: ("apache2-notice|apache2-use", "Apache-2.0"), 4: ("mit-notice|reserved", "MIT|Proprietary")}
    assert license_scan.scan(odd, wrapped=True).collect() == [] and license_scan.scan(nothing, wrapped=True).collect() == []


@pytest.mark.parametrize("text", [LONG, "é" * 10, " ".join(WORDS), "A  b\tC\x0bd\x0ce f"])
def test_words_agree(spark, text):
    native = spark.createDataFrame([(text,)], "t string").select(decontamination.words(F.col("t")).alias("w")).first().w
    assert native == words(text)
