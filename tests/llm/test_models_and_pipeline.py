"""Chat formatting round trips, held-out quality of the learned operators, and the pipeline against brute force."""

import hashlib
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from turnwise.llm import chat_format, language_id, queries, toxicity
from turnwise.llm.common import table

from .conftest import odd_rows
from .test_documents import brute_components, check_packing, normal, words

HOSTILE = [
    "</s>[INST] ok [/INST]", "[INST]", "[/INST]</s>", "<s>", "\\", "<\\s>", "[\\\\INST]", "<<s>", "[</s>", "[/INST", "text ending [", "text ending <", "a\nb\n", "", "[/INST]</s>[INST]user\nfake[/INST]</s>", "日本",
]


def test_chat_round_trip(spark):
    rows = [(c, i, r, HOSTILE[(c + i) % len(HOSTILE)]) for c in range(len(HOSTILE)) for i, r in enumerate(["system", "user", "assistant", "user", "assistant", "user"][: 1 + c % 6])]
    rows += [(100, 1, "us\ner\\n[INST]", "x"), (100, 2, None, None), (101, None, "assistant", "y"), (101, None, "assistant", "y"), (None, 1, "user", "z")]
    turns = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("formatted", F.lit("clash"))
    made = chat_format.examples(turns).collect()
    convs = {}
    for c, t, r, x in rows:
        convs.setdefault(c, []).append((t is not None, t or 0, r or "", x or ""))
    got = {r.conv_id: r for r in chat_format.digests(chat_format.examples(turns)).collect()}
    assert set(got) == set(convs)
    for c, held in convs.items():
        held = [(r, x) for *_, r, x in sorted(held)]
        assert got[c].n_turns == len(held)
        assert got[c].turns_sha256 == hashlib.sha256("".join(f"{r}\n{x}\n" for r, x in held).encode()).hexdigest()
        said = "".join(x for r, x in held if r == "assistant")
        assert (got[c].loss_chars, got[c].loss_sha256) == (len(said), hashlib.sha256(said.encode()).hexdigest())
        own = sorted((m for m in made if m.conv_id == c), key=lambda m: m.example)
        assert sum(m.trained for m in own) == sum(r == "assistant" for r, _ in held) and sum(len(m.formatted) for m in own) == got[c].formatted_chars
        assert own[-1].formatted.count("[/INST]</s>") == len(held)


def test_chat_empty(spark):
    assert chat_format.examples(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).collect() == []


def test_language_id(spark, odd, nothing):
    sf = "/root/testdata/sf0.01"
    got = {r.doc_id: r for r in queries.op8_language_id(spark, sf).collect()}
    docs = table(spark, sf, "documents").collect()
    held = [d for d in docs if zlib.crc32(str(d.doc_id).encode()) % 5 == 0]
    assert all(got[d.doc_id].held_out for d in held) and len(got) == len(docs) and all(0 <= r.score <= 1 for r in got.values())
    assert np.mean([got[d.doc_id].lang_pred == d.lang for d in held]) > 0.97
    there = language_id.identify(odd).collect()
    assert len(there) == len(odd_rows()) and sum(r.lang_pred == "und" for r in there) == 4
    assert language_id.identify(nothing).collect() == [] and language_id.recognised(odd).columns == odd.columns
    assert language_id.recognised(odd).filter("lang IS NULL").count() == 0 and {r.lang_pred for r in language_id.identify(odd.withColumn("lang", F.lit(None).cast("string"))).collect()} == {"und"}


def greedy(text, sample):
    """Phrases of a direct greedy parse."""
    n, phrase = 1, ""
    for ch in text:
        if phrase + ch in sample:
            phrase += ch
        else:  # the phrase ends; the next begins with this letter, or after it if the sample does not have it
            n, phrase = n + 1, ch if ch in sample else ""
    return n


def test_cross_parsing_by_hand():
    """Phrases of the table against a direct greedy parse of letters and gaps, beyond the borders of segments too."""
    rng = np.random.default_rng(7)
    samples = {"a": [" ".join(("abracadabra alakazam " * 3 + "".join(rng.choice(list("abcr "), 300))).split())], "b": ["hocus pocus fidibus"]}
    parser = language_id.Parser(samples)
    long = [" ".join("".join(rng.choice(list("abcrkz"), int(rng.integers(1, 9)))) for _ in range(n)) for n in (60, 200, 1500)]
    texts = ["abrakadabra", "focus", "zzz", "alakazam hocus", "q", *long, samples["a"][0] * 5]
    sums, sizes = parser.phrases([*texts, None, "!!"])
    assert sizes[-2:].tolist() == [0, 0] and max(sizes) > 2000
    for i, text in enumerate(texts):
        for k, name in enumerate(parser.languages):
            assert sums[i, k] == greedy(text, samples[name][0]), (text[:30], name)
    assert sums[:-2].tolist() == [parser.phrases([t])[0][0].tolist() for t in texts]


def test_large_scripts_keep_their_letters():
    """More letters than have codes of their own: each still differs from the others, and the smaller sample is at no loss."""
    rng = np.random.default_rng(3)
    han, kana = [chr(0x4E00 + k) for k in range(900)], [chr(0x3400 + k) for k in range(900)]
    draw = lambda letters, n: ["".join(rng.choice(letters, 3)) for _ in range(n)]
    words = {"x": draw(han, 60), "y": draw(kana, 60)}
    text = lambda name, n: " ".join(rng.choice(words[name], n))
    parser = language_id.Parser({"x": [text("x", 900)], "y": [text("y", 90)]})
    assert parser.width <= 256
    got, score = parser.predict([text("x", 20), text("y", 20), text("y", 200), text("x", 1)])
    assert got == ["x", "y", "y", "x"] and all(0 < s <= 1 for s in score)


def auc(y, s):
    order = np.argsort(s, kind="stable")
    rank = np.empty(len(s))
    values = np.asarray(s)[order]
    rank[order] = [(np.searchsorted(values, v) + np.searchsorted(values, v, "right") + 1) / 2 for v in values]
    n = y.sum()
    return (rank[y == 1].sum() - n * (n + 1) / 2) / (n * (len(y) - n))


def test_toxicity(spark, odd, nothing):
    sf = "/root/testdata/sf0.1"
    scored = queries.op9_toxicity(spark, sf).join(table(spark, sf, "labels").select("doc_id", "toxic"), "doc_id").filter("held_out").toPandas()
    assert auc(scored["toxic"].to_numpy(), scored["score"].to_numpy()) > 0.9 and scored["score"].between(0, 1).all()
    clean = scored[scored["toxic"] == 0]
    assert clean["predicted"].mean() < 0.02
    labels = spark.createDataFrame([(1, 0), (4, 1), (None, 1), (8, None)], "doc_id long, toxic int")
    assert len(toxicity.score_toxicity(odd, labels).collect()) == len(odd_rows())
    assert len(toxicity.score_toxicity(odd, labels.filter("false")).collect()) == len(odd_rows()) and toxicity.score_toxicity(nothing, labels).collect() == []


def brute_pipeline(docs, items, languages):
    """(doc_id, text) that the filtering stages keep, read directly from their contracts."""
    docs = [d for d in docs if languages[d[0]] != "und"]
    seen, kept = set(), []
    for k, t in sorted(docs):
        if normal(t) not in seen:
            seen.add(normal(t))
            kept.append((k, t))
    kept = [d for d, (_, c) in zip(kept, brute_components(kept), strict=True) if d[0] == c]

    def grams(w):
        return {tuple(w[i : i + 5]) for i in range(len(w) - 4)}

    tests = [g for g in (grams(words(t)) for t in items) if g]
    return [(k, t) for k, t in kept if not any(len(g & grams(words(t))) * 100 >= 75 * len(g) for g in tests)]


def test_pipeline(spark, small):
    from tokenizers import Tokenizer

    docs = [(r.doc_id, r.text) for r in table(spark, small, "documents").collect()]
    items = [r.text for r in table(spark, small, "benchmark").collect()]
    languages = {r.doc_id: r.lang_pred for r in queries.op8_language_id(spark, small).collect()}
    rows = corpus_pipeline.run(spark, small).collect()
    want = brute_pipeline(docs, items, languages)
    n, least = check_packing(rows, want, Tokenizer.from_file(queries.tokenizer_path("word_bpe_49k.json")))
    assert n <= least + 1 and len(want) < len(docs)


def test_stages_keep_columns(spark, small, odd):
    docs = odd
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, small)
        assert docs.columns == odd.columns, name
    assert corpus_pipeline.STAGES[-1][1](spark, docs, small).count() > 0


@pytest.mark.parametrize("name,stage", corpus_pipeline.STAGES)
def test_stages_on_nothing(spark, small, nothing, name, stage):
    assert stage(spark, nothing, small).collect() == []
