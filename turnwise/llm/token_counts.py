"""Token counts by the whole-token shortcut.

Offline, every vocabulary string is encoded by the library; those that come back as exactly their own one id
are proven whole tokens. A text is cut into pre-tokens by the tokenizer's own rule; a pre-token in the proven
set counts one, and only the rest are merged, each distinct one once per worker, by the library.

The cut is done here for texts of plain characters (ASCII and the Latin-1 letters, for which the rule is
unambiguous); a text with any other character, or with the string of a special token, goes whole to the
library. Defined cases: null or empty text has 0 tokens; texts of any length are counted whole; repeated rows
are rows; other columns are ignored.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_value, process_cache

by_value(__name__)

LIMIT = 512
#: Merged pre-tokens remembered per worker; beyond that the memory starts anew.
MEMO = 400_000

_UNUSUAL = re.compile("[^\\t\\n\\r\\x20-\\x7eÀ-ÖØ-öø-ÿ]")
_PRE_TOKEN = re.compile(r"'(?:[stmd]|re|ve|ll)| ?[^\W\d_]+| ?[0-9]+| ?(?:[^\s\w]|_)+|\s+(?!\S)|\s+")


class Counter:
    """Token counts of one byte-level tokenizer file."""

    def __init__(self, path: str, whole: list[str] | None = None):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.special = [t.content for t in self.library.get_added_tokens_decoder().values()]
        self.whole = self.proven() if whole is None else dict.fromkeys(whole, 1)
        self.memo = dict(self.whole)

    def proven(self) -> dict[str, int]:
        """Pre-tokens that are one token: each vocabulary string that is one pre-token and encodes alone to its own id."""
        decode = self.library.decode
        vocabulary = self.library.get_vocab(with_added_tokens=False)
        strings = [(decode([i], skip_special_tokens=False), i) for i in vocabulary.values()]
        strings = [(s, i) for s, i in strings if s and "�" not in s and not _UNUSUAL.search(s) and _PRE_TOKEN.findall(s) == [s]]
        encoded = self.library.encode_batch([s for s, _ in strings], add_special_tokens=False)
        return {s: 1 for (s, i), e in zip(strings, encoded, strict=True) if e.ids == [i]}

    def plain(self, text: str) -> bool:
        return not _UNUSUAL.search(text) and not any(s in text for s in self.special)

    def count(self, texts: list[str]) -> list[int]:
        cut = [_PRE_TOKEN.findall(t) if self.plain(t) else None for t in texts]
        if len(self.memo) > MEMO + len(self.whole):
            self.memo = dict(self.whole)
        new = list({p for c in cut if c for p in c} - self.memo.keys())
        for k in range(0, len(new), 4096):
            part = new[k : k + 4096]
            self.memo.update(zip(part, (len(e.ids) for e in self.library.encode_batch(part, add_special_tokens=False)), strict=True))
        get = self.memo.__getitem__
        return [len(self.library.encode(t, add_special_tokens=False).ids) if c is None else sum(map(get, c)) for t, c in zip(texts, cut, strict=True)]


def worker_counter(path: str, whole=None) -> Counter:
    """The process's counter; whole: a broadcast of the proven strings, so that the proof runs once, on the driver."""
    cache = process_cache("tokens")
    if ("counter", path) not in cache:
        cache["counter", path] = Counter(path, whole and whole.value)
    return cache["counter", path]


def count_tokens(docs: DataFrame, tokenizer: str, limit: int = LIMIT, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, n_bytes, n_tokens, over_limit for every row."""
    import pandas as pd

    # At most the vocabulary's size.
    proven = docs.sparkSession.sparkContext.broadcast(list(worker_counter(tokenizer).whole))

    def counted_all(column):
        counter = worker_counter(tokenizer, proven)
        values = column.tolist()
        out: list[int] = []
        for k in range(0, len(values), 256):
            out += counter.count([v or "" for v in values[k : k + 256]])
        return pd.Series(out, dtype="int64")

    counted_all.__annotations__ = {"column": pd.Series, "return": pd.Series}
    tokens = F.pandas_udf(counted_all, "long")
    body = F.coalesce(F.col(text), F.lit(""))
    counted = docs.select(F.col(key), F.octet_length(body).cast("long").alias("n_bytes"), tokens(body).alias("n_tokens"))
    return counted.withColumn("over_limit", F.col("n_tokens") > limit)
