"""Language identification by cross-parsing entropy.

For each language a suffix automaton is built over a bounded sample of labelled text. A text is parsed against
it greedily: each phrase is the longest stretch that occurs in the sample. Phrases against a sample of n codes
weigh log2(n) bits each, so that samples of unequal sizes compare: the language that needs the fewest phrases so
normalised wins. The automaton is made a complete transition table in which a dead end counts a phrase and
starts the next one, so that whole batches of text run through all languages in step.

Texts are read whole. Long ones run as segments side by side: each begins in the state in which the one before it
ended, and those whose first state turns out to be another one run again, until none does; so the phrases are
those of one parse from end to end. Letters beyond the COMMON most frequent ones are written as three digit
codes each, so that no letter of the samples is lost however large the script.

What is learned from: at most SAMPLE_ROWS rows a language, drawn by a hash of the id, and of each a stretch of
ROW_CHARS characters from anywhere in its text; nothing else about the corpus is gathered. More than MAX_LANGUAGES
distinct labels are an error, as the models would not fit a worker.

Defined cases: a text that is null or has no letter is `und` with score 0; with one learned language every
other text gets it with score 1; ties go to the language first in order; with nothing to learn from every text
is `und`; repeated rows and very long texts are ordinary; other columns are ignored.
"""

from __future__ import annotations

import uuid

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .common import by_value, free_name, process_cache, trim

by_value(__name__)

UND = "und"
FOLDS, HELD_OUT = 5, 0
SAMPLE_ROWS, ROW_CHARS = 200, 200
MAX_LANGUAGES = 200
SEGMENT = 256
#: Codes: 0 is a letter that no sample has, 1 anything but letters, 2 padding; then the samples' common letters, then digits.
UNKNOWN, GAP, PAD, FIRST = 0, 1, 2, 3
#: Letters with a code of their own; the others are three digits of this base.
COMMON, BASE = 120, 104


#: Added to the number of a letter that is spelled in digits.
RARE = 1 << 20


def held_out(key) -> F.Column:
    return F.coalesce(F.crc32(key.cast("string").cast("binary")) % FOLDS == HELD_OUT, F.lit(False))


def samples(docs: DataFrame, key: str = "doc_id", text: str = "text", lang: str = "lang") -> dict[str, list[str]]:
    """Bounded sample of labelled texts by language, drawn by a hash of the id."""
    labelled = docs.filter(F.col(lang).isNotNull() & F.col(text).isNotNull() & F.col(key).isNotNull() & ~held_out(F.col(key)))
    counts = {r[0]: r[1] for r in labelled.groupBy(lang).count().limit(MAX_LANGUAGES + 1).collect()}
    if len(counts) > MAX_LANGUAGES:
        raise ValueError(f"more than {MAX_LANGUAGES} languages are labelled")
    if not counts:
        return {}
    draw = F.pmod(F.xxhash64(F.lit("draw"), F.col(key)), F.lit(1 << 30))
    share = F.lit(None)
    for name, n in counts.items():
        share = F.when(F.col(lang) == name, F.lit(int(min(1.0, 4 * SAMPLE_ROWS / n) * (1 << 30)))).otherwise(share)
    room = F.greatest(F.length(text) - ROW_CHARS, F.lit(0)) + 1
    stretch = F.substr(F.col(text), (F.pmod(F.xxhash64(F.lit("stretch"), F.col(key)), room) + 1).cast("int"), F.lit(ROW_CHARS))
    near = labelled.filter(draw < share).select(F.col(lang).alias("lang"), stretch.alias("text"), draw.alias("draw"), F.col(key).alias("key"))
    best = Window.partitionBy("lang").orderBy("draw", "key", "text")
    rows = near.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= SAMPLE_ROWS).orderBy("lang", "rank").collect()
    out: dict[str, list[str]] = {}
    for r in rows:
        out.setdefault(r["lang"], []).append(r["text"])
    return out


def automaton(codes: list[int]) -> list[dict[int, int]]:
    """Transitions of the suffix automaton of a code sequence; state 0 is the root."""
    moves: list[dict[int, int]] = [{}]
    link, length, last = [-1], [0], 0
    for c in codes:
        new = len(moves)
        moves.append({})
        link.append(0)
        length.append(length[last] + 1)
        p = last
        while p >= 0 and c not in moves[p]:
            moves[p][c] = new
            p = link[p]
        if p >= 0:
            q = moves[p][c]
            if length[q] == length[p] + 1:
                link[new] = q
            else:
                twin = len(moves)
                moves.append(dict(moves[q]))
                link.append(link[q])
                length.append(length[p] + 1)
                while p >= 0 and moves[p].get(c) == q:
                    moves[p][c] = twin
                    p = link[p]
                link[q] = link[new] = twin
        last = new
    return moves


class Parser:
    """Phrase counts of texts against every language's sample."""

    def __init__(self, texts: dict[str, list[str]]):
        self.languages = sorted(texts)
        joined = {k: "\n".join(v).lower() for k, v in texts.items()}
        seen: dict[str, int] = {}
        for t in joined.values():
            for ch in t:
                if ch.isalpha():
                    seen[ch] = seen.get(ch, 0) + 1
        letters = sorted(seen, key=lambda ch: (-seen[ch], ch))
        common, rare = letters[:COMMON], letters[COMMON:]
        self.digits = FIRST + len(common)
        self.width = self.digits + (BASE if rare else 0)
        # Of each code point its code; from RARE on, that much more than the number that its digits spell.
        self.code = np.full(0x110000, GAP, dtype=np.int32)
        alpha = process_cache("language").setdefault("alpha", np.fromiter((chr(i).isalpha() for i in range(0x110000)), dtype=bool, count=0x110000))
        self.code[alpha] = UNKNOWN
        for i, ch in enumerate(common):
            self.code[ord(ch)] = FIRST + i
        for i, ch in enumerate(rare):
            self.code[ord(ch)] = RARE + i
        coded = [self.codes(joined[name]) for name in self.languages]
        self.bits = np.array([np.log2(max(len(c), 2)) for c in coded])
        kind = np.int32 if (2 * sum(map(len, coded)) + len(coded)) * self.width * 2 < 2**31 else np.int64  # 2n states at most
        tables, self.roots, at = [], [], 0
        for c in coded:
            moves = automaton(c.tolist())
            table = np.full((len(moves), self.width), -1, dtype=kind)
            for s, m in enumerate(moves):
                table[s, list(m)] = list(m.values())
            del moves
            table[table >= 0] *= self.width * 2
            restart = np.where(table[0] >= 0, table[0], 0) + 1  # the low bit counts a phrase
            table = np.where(table >= 0, table, restart)
            table[:, PAD] = np.arange(len(table)) * self.width * 2
            table += at * 2
            tables.append(table.ravel())
            self.roots.append(at * 2)
            at += len(table) * self.width
        self.table = np.concatenate(tables) if tables else np.zeros(0, np.int32)
        del tables
        trim()

    def codes(self, text: str) -> np.ndarray:
        """Letter codes, each run of anything else as one gap."""
        c = self.code[np.frombuffer(text.lower().encode("utf-32-le", "replace"), dtype="<u4")]
        gap = c == GAP
        c = c[~(gap & np.concatenate(([False], gap[:-1])))] if len(c) else c
        rare = c >= RARE
        if rare.any():
            spelled = np.where(rare, 3, 1)
            out = np.repeat(c, spelled)
            place = np.cumsum(spelled) - spelled
            for k in range(3):
                out[place[rare] + k] = self.digits + (c[rare] - RARE) // BASE**k % BASE
            c = out
        return c.astype(np.uint8)

    def phrases(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """Phrases per text and language, and the codes of each text (0 if it has no letter)."""
        coded = [self.codes(t) if t else np.zeros(0, np.uint8) for t in texts]
        size = np.array([len(c) if len(c) and (c != GAP).any() else 0 for c in coded], dtype=np.int64)
        parts = -(-size // SEGMENT)
        grid = np.full(int(parts.sum()) * SEGMENT, PAD, dtype=np.uint8)
        at = 0
        for c, n, p in zip(coded, size.tolist(), parts.tolist(), strict=True):
            grid[at : at + n] = c[:n]
            at += p * SEGMENT
        grid = grid.reshape(-1, SEGMENT)
        many = len(self.languages)
        owner = np.repeat(np.arange(len(texts)), parts)
        opens = np.concatenate(([True], owner[1:] != owner[:-1]))[: len(grid)]
        counts = np.zeros((len(grid), many), dtype=np.int64)
        first = np.repeat(np.array(self.roots, dtype=self.table.dtype)[None, :], len(grid), axis=0)
        last = first.copy()
        todo = np.arange(len(grid))
        while len(todo) and many:
            for k in range(0, len(todo), 8192):
                some = todo[k : k + 8192]
                steps = np.ascontiguousarray(grid[some].T)
                value = np.ascontiguousarray(first[some].T)
                total = np.zeros(value.shape, dtype=np.int32)
                for c in steps:
                    value = self.table.take((value >> 1) + c)
                    total += value & 1
                counts[some], last[some] = total.T, value.T & ~1
            true = first.copy()
            later = np.flatnonzero(~opens)
            true[later] = last[later - 1]  # where the segment before ended
            todo = np.flatnonzero((true != first).any(axis=1))
            first = true
        counts[opens] += 1
        sums = np.stack([np.bincount(owner, weights=counts[:, j], minlength=len(texts)) for j in range(many)], axis=1) if many else np.zeros((len(texts), 0))
        return sums, size

    def predict(self, texts: list[str | None]) -> tuple[list[str], list[float]]:
        if not self.languages:
            return [UND] * len(texts), [0.0] * len(texts)
        sums, size = self.phrases(texts)
        sums = sums * self.bits
        best = sums.argmin(axis=1)
        if len(self.languages) > 1:
            low = np.partition(sums, 1, axis=1)
            score = low[:, 1] / np.maximum(low[:, 0] + low[:, 1], 1)
        else:
            score = np.ones(len(texts))
        return [self.languages[b] if n else UND for b, n in zip(best, size, strict=True)], np.where(size > 0, score, 0.0).tolist()


def worker_parser(learned) -> Parser:
    """The process's parser of one broadcast (name, samples)."""
    cache = process_cache("language")
    name, texts = learned.value
    if cache.get("parser_of") != name:
        cache["parser"], cache["parser_of"] = Parser(texts), name
    return cache["parser"]


def predictor(docs: DataFrame, learn_from: DataFrame, key: str, text: str, lang: str):
    """A column function: struct<lang_pred, score> of a text."""
    import pandas as pd

    learned = docs.sparkSession.sparkContext.broadcast((uuid.uuid4().hex, samples(learn_from, key, text, lang)))

    def predict(column):
        parser, values, names, scores = worker_parser(learned), column.tolist(), [], []
        for k in range(0, len(values), 512):
            n, s = parser.predict(values[k : k + 512])
            names += n
            scores += s
        trim()
        return pd.DataFrame({"lang_pred": pd.Series(names, dtype=object), "score": scores})

    predict.__annotations__ = {"column": pd.Series, "return": pd.DataFrame}
    return F.pandas_udf(predict, "lang_pred string, score double").asNondeterministic()  # so that no plan runs it twice a row


def identify(docs: DataFrame, learn_from: DataFrame | None = None, key: str = "doc_id", text: str = "text", lang: str = "lang") -> DataFrame:
    """key, held_out, lang_pred, score for every row."""
    predict = predictor(docs, docs if learn_from is None else learn_from, key, text, lang)
    found = docs.select(F.col(key), held_out(F.col(key)).alias("held_out"), predict(F.col(text)).alias("_p"))
    return found.select(key, "held_out", "_p.lang_pred", "_p.score")


def recognised(docs: DataFrame, key: str = "doc_id", text: str = "text", lang: str = "lang") -> DataFrame:
    """docs without the rows whose text is in no language (null or without a letter); where lang is null it is the one
    predicted, all other columns are as they were."""
    predict = predictor(docs, docs, key, text, lang)
    found = free_name(docs, "_found")
    named = docs.withColumn(found, predict(F.col(text))).filter(F.col(found)["lang_pred"] != UND)
    return named.withColumn(lang, F.coalesce(F.col(lang), F.col(found)["lang_pred"])).select(*docs.columns)
