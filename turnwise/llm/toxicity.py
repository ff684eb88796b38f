"""Toxicity by weak supervision.

Many voters (lexicon voters that each own some learned words or word beginnings, and pattern voters over the
shape of a text) vote on a bounded sample. A generative label model estimates each voter's class-conditional
accuracies by expectation maximisation, and how correlated voters are given the class; correlated voters count
less. Its posteriors are the labels on which a linear (logistic) classifier is trained, which scores every
whole text. Labels of the folds that may be learned from choose the lexicon, start the label model and hold it, for
every round begins half way between its posterior and the labels; at the end they set the score's scale and shift.
They are never a feature. So the model is one of labelled rows: fitted on votes alone it found half of the toxic rows.

Bounds of what is learned from: SAMPLE_ROWS labelled rows drawn by a hash of the id (of a repeated id one row),
TERMS lexicon entries. Counts of words over the sample are taken on the executors.

Defined cases: null and empty texts get the score of a text without any feature; without labels of both classes
every score is 0; repeated rows are scored alike; texts are read whole whatever their length; other columns
are ignored.
"""

from __future__ import annotations

import hashlib
import re
import uuid
from collections import Counter

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_value, cut, process_cache
from .language_id import held_out

by_value(__name__)

SAMPLE_ROWS = 20_000
TERMS = 600
VOTERS = 200
#: A lexicon entry is in at least so many toxic rows, that share of them, and that much more often there than in others.
LEAST_ROWS, LEAST_SHARE, LEAST_RATIO = 8, 0.015, 6.0
#: So many of the most frequent entries of toxic rows are compared with the clean rows.
FREQUENT = 20_000
PREFIXES = (4, 5, 6, 7)

_WORD = re.compile(r"[^\W\d_]+")


def terms_of(word: str) -> list[str]:
    """The lexicon entries that a word can match: itself, and its beginnings (marked by a star)."""
    return [word, *(word[:k] + "*" for k in PREFIXES if len(word) > k)]


def shape(text: str, words: int) -> list[float]:
    """Pattern features: shares of exclamation marks, capitals, digits and other signs."""
    n = max(len(text), 1)
    capitals = sum(map(str.isupper, text))
    return [text.count("!") / n, capitals / n, sum(map(str.isdigit, text)) / n, text.count("*") / n]


SHAPES = 4


class Matcher:
    """Counts of lexicon entries in texts, each distinct word looked up once."""

    def __init__(self, terms: list[str]):
        self.index = {t: i for i, t in enumerate(terms)}
        self.memo: dict[str, tuple[int, ...]] = {}

    def hits(self, words: list[str]) -> Counter:
        memo, index = self.memo, self.index
        if len(memo) > 1_000_000:
            memo.clear()
        out: Counter = Counter()
        for w in words:
            found = memo.get(w)
            if found is None:
                found = memo[w] = tuple(index[t] for t in terms_of(w) if t in index)
            if found:
                out.update(found)
        return out

    def features(self, texts: list[str]) -> np.ndarray:
        x = np.zeros((len(texts), len(self.index) + SHAPES), dtype=np.float32)
        for row, text in zip(x, texts, strict=True):
            words = _WORD.findall(text.lower())
            for i, n in self.hits(words).items():
                row[i] = np.log1p(n)
            row[len(self.index) :] = shape(text, len(words))
        return x


def labelled(docs: DataFrame, labels: DataFrame, key: str, text: str, label: str) -> DataFrame:
    """At most about SAMPLE_ROWS labelled rows that may be learned from: text, y."""
    known = labels.select(F.col(key).alias("_id"), F.col(label).alias("y")).filter(F.col("y").isin(0, 1) & F.col("_id").isNotNull() & ~held_out(F.col("_id"))).groupBy("_id").agg(F.max("y").alias("y"))
    share = min(1.0, SAMPLE_ROWS / max(known.count(), 1))
    drawn = F.pmod(F.xxhash64(F.lit("draw"), F.col("_id")), F.lit(1 << 30)) < int(share * (1 << 30))
    rows = docs.select(F.col(key).alias("_id"), F.coalesce(F.col(text), F.lit("")).alias("text")).join(F.broadcast(known.filter(drawn)), "_id")
    return rows.groupBy("_id").agg(F.min("text").alias("text"), F.first("y").cast("int").alias("y"))  # the join is bounded by ids, this by rows


def copies_weighed(rows: DataFrame) -> DataFrame:
    """rows with a weight: 1 over the number of sample rows that seem copies of one text: they share a whole band of BAND
    min-hashes of five-word runs, as near copies nearly always do and texts with a passage in common hardly ever."""
    import pandas as pd

    def sketch(column):
        out = []
        for text in column:
            words = text.lower().split()
            grams = np.array([hash_of(" ".join(words[k : k + 5])) for k in range(max(1, len(words) - 4))], dtype=np.uint64)
            least = np.array([(grams * m).min() for m in MULTIPLIERS], dtype=np.uint64).reshape(-1, BAND)
            out.append([hash_of(band.tobytes().hex()) for band in least])
        return pd.Series(out, dtype=object)

    sketch.__annotations__ = {"column": pd.Series, "return": pd.Series}
    seen = rows.select("_id", F.pandas_udf(sketch, "array<long>")("text").alias("s")).collect()  # at most about SAMPLE_ROWS rows of numbers
    sizes = Counter((j, h) for r in seen for j, h in enumerate(r["s"]))
    weights = {r["_id"]: 1.0 / max(sizes[j, h] for j, h in enumerate(r["s"])) for r in seen}
    known = rows.sparkSession.sparkContext.broadcast(weights)

    def weight(ids):
        return pd.Series([known.value.get(i, 1.0) for i in ids], dtype=float)

    weight.__annotations__ = {"ids": pd.Series, "return": pd.Series}
    return rows.withColumn("w", F.pandas_udf(weight, "double")("_id"))


BAND = 3
#: Four bands of odd numbers.
MULTIPLIERS = np.random.default_rng(11).integers(1, 2**63, 4 * BAND, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def hash_of(text: str) -> int:
    return int.from_bytes(hashlib.blake2b(text.encode("utf-8", "replace"), digest_size=8).digest(), "little") >> 1


def lexicon(rows: DataFrame) -> tuple[list[str], np.ndarray]:
    """Entries that toxic rows have far more often, the surest first."""
    import pandas as pd

    def counted(batches):
        toxic, clean = Counter(), Counter()
        for pdf in batches:
            for text, y, w in zip(pdf["text"], pdf["y"], pdf["w"], strict=True):
                into = toxic if y else clean
                for t in {t for x in set(_WORD.findall(text.lower())) for t in terms_of(x)} if y else ():
                    into[t] += w
                into["\n"] += w
        keys = list(toxic | clean)
        yield pd.DataFrame({"term": pd.Series(keys, dtype=object), "a": [float(toxic[k]) for k in keys], "b": [float(clean[k]) for k in keys]})

    # Only entries of toxic rows can qualify; what clean rows say is counted for the likeliest of them.
    def clean_of(wanted):
        def run(batches):
            out = Counter()
            for pdf in batches:
                for text, y, w in zip(pdf["text"], pdf["y"], pdf["w"], strict=True):
                    for t in () if y else wanted.value.intersection(t for x in set(_WORD.findall(text.lower())) for t in terms_of(x)):
                        out[t] += w
            yield pd.DataFrame({"term": pd.Series(list(out), dtype=object), "b": [float(n) for n in out.values()]})

        return run

    counts = rows.mapInPandas(counted, "term string, a double, b double").groupBy("term").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    totals = {r["term"]: (r["a"], r["b"]) for r in counts.filter(F.col("term") == "\n").collect()}
    n1, n0 = totals.get("\n", (0, 0))
    if not n1 or not n0:
        return [], np.zeros((0, 2))
    frequent = counts.filter((F.col("a") >= max(LEAST_ROWS, LEAST_SHARE * n1)) & (F.col("term") != "\n"))
    first = frequent.orderBy(F.desc("a"), "term").limit(FREQUENT).collect()
    wanted = rows.sparkSession.sparkContext.broadcast(frozenset(r["term"] for r in first))
    clean = {r["term"]: r["b"] for r in rows.mapInPandas(clean_of(wanted), "term string, b double").groupBy("term").agg(F.sum("b").alias("b")).collect()}
    kept = []
    for r in first:
        b = clean.get(r["term"], 0)
        ratio = (r["a"] + 0.05) / n1 / ((b + 0.5) / n0)
        if ratio >= LEAST_RATIO:
            kept.append((-r["a"] * np.log(ratio), r["term"], r["a"] / n1, b / n0))
    # Of entries with the same beginning and the same rows one is enough: the word itself, else the longest beginning.
    one = {}
    for k in sorted(kept, key=lambda k: (k[1].endswith("*"), -len(k[1]), k[1])):
        one.setdefault((k[1][:4], k[2], k[3]), k)
    kept = sorted(one.values())[:TERMS]
    return [k[1] for k in kept], np.array([k[2:] for k in kept]).reshape(-1, 2)


class LabelModel:
    """Voters with class-conditional vote rates, estimated by expectation maximisation that the labels hold."""

    def fit(self, votes: np.ndarray, start: np.ndarray, w: np.ndarray, rounds: int = 25) -> np.ndarray:
        """votes: 0/1 per row and voter; start: first guess of the posterior. Returns the posterior."""
        q = start.astype(float)
        v = votes.astype(float)
        self.prior = np.clip(np.average(start, weights=w), 1e-3, 1 - 1e-3)
        for _ in range(rounds):
            q = (q + start) / 2  # the first guess holds the model to the right labelling of its two classes
            self.on = np.clip(((w * q) @ v + 0.5) / ((w * q).sum() + 1), 1e-4, 1 - 1e-4)
            self.off = np.clip(((w * (1 - q)) @ v + 0.05) / ((w * (1 - q)).sum() + 1), 1e-5, 1 - 1e-4)
            self.weight = self.independence(v, q, w)
            q = self.posterior(v)
        return q

    def independence(self, v: np.ndarray, q: np.ndarray, w: np.ndarray) -> np.ndarray:
        """1 over 1 plus the correlations, given the class, with the other voters."""
        r = v - np.outer(q, self.on) - np.outer(1 - q, self.off)
        sd = np.sqrt(np.average(r**2, axis=0, weights=w)) + 1e-9
        c = np.abs(((r * w[:, None]).T @ r) / w.sum() / np.outer(sd, sd))
        np.fill_diagonal(c, 0)
        return 1 / (1 + np.where(c > 0.5, c, 0).sum(axis=1))

    def posterior(self, v: np.ndarray) -> np.ndarray:
        odds = np.log(self.prior / (1 - self.prior)) + (v * np.log(self.on / self.off)) @ self.weight  # a voter that does not fire abstains
        return 1 / (1 + np.exp(-np.clip(odds, -30, 30)))


def logistic(x: np.ndarray, q: np.ndarray, row: np.ndarray, ridge: float = 0.1, rounds: int = 30) -> tuple[np.ndarray, float]:
    """Weights and intercept for soft labels, by Newton steps."""
    a = np.hstack([x, np.ones((len(x), 1))]).astype(float)
    w = np.zeros(a.shape[1])
    penalty = np.full(len(w), ridge)
    penalty[-1] = 1e-3
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        step = np.linalg.solve((a * (row * (p * (1 - p) + 1e-6))[:, None]).T @ a + np.diag(penalty), a.T @ (row * (p - q)) + penalty * w)
        w -= step
        if np.abs(step).max() < 1e-6:
            break
    return w[:-1], float(w[-1])


def train(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "toxic") -> tuple[list[str], np.ndarray, float]:
    """Lexicon entries, weights of entries and patterns, intercept."""
    import pandas as pd

    rows = cut(copies_weighed(labelled(docs, labels, key, text, label)))  # bounded, read three times
    terms, rates = lexicon(rows)
    if not terms:
        return [], np.zeros(SHAPES), -30.0
    known = rows.sparkSession.sparkContext.broadcast(terms)

    def featured(batches):
        matcher = Matcher(known.value)
        for pdf in batches:
            x = matcher.features(pdf["text"].tolist())
            yield pd.DataFrame({"y": pdf["y"], "w": pdf["w"], "x": pd.Series([r.tobytes() for r in x], dtype=object)})

    got = rows.mapInPandas(featured, "y int, w double, x binary").collect()  # at most about SAMPLE_ROWS rows
    x = np.stack([np.frombuffer(r["x"], dtype=np.float32) for r in got])
    y = np.array([r["y"] for r in got], dtype=float)
    w = np.array([r["w"] for r in got])
    owner = np.arange(len(terms)) % VOTERS
    lexical = np.stack([(x[:, : len(terms)][:, owner == k] > 0).any(axis=1) for k in range(min(VOTERS, len(terms)))], axis=1)
    shapes = x[:, len(terms) :]
    patterns = shapes > np.quantile(shapes, 0.98, axis=0)
    q = LabelModel().fit(np.hstack([lexical, patterns]), 0.98 * y + 0.02 * np.average(y, weights=w), w)
    weights, intercept = logistic(x, q, w)
    # The posteriors rank well but need not be calibrated: one scale and shift, fitted to the sample's labels.
    scale, shift = logistic((x @ weights + intercept)[:, None], y, w)
    scale = max(float(scale[0]), 0.1)
    return terms, weights * scale, intercept * scale + shift


def score_toxicity(docs: DataFrame, labels: DataFrame, key: str = "doc_id", text: str = "text", label: str = "toxic") -> DataFrame:
    """key, held_out, score, predicted for every row."""
    import pandas as pd

    model = docs.sparkSession.sparkContext.broadcast((uuid.uuid4().hex, *train(docs, labels, key, text, label)))

    def score(column):
        name, terms, weights, intercept = model.value
        cache = process_cache("toxicity")
        if cache.get("matcher_of") != name:
            cache["matcher"], cache["matcher_of"] = Matcher(terms), name
        values, out = column.tolist(), []
        for k in range(0, len(values), 512):
            odds = cache["matcher"].features([v or "" for v in values[k : k + 512]]) @ weights + intercept
            out.append(1 / (1 + np.exp(-np.clip(odds, -30, 30))))
        return pd.Series(np.concatenate(out) if out else np.zeros(0))

    score.__annotations__ = {"column": pd.Series, "return": pd.Series}
    scored = docs.select(F.col(key), held_out(F.col(key)).alias("held_out"), F.pandas_udf(score, "double")(F.col(text)).alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= 0.5).cast("int"))
