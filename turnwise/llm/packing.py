"""Best-fit packing of documents into token sequences, improved by a swap-based local search.

Documents become token ids closed by an end id; only documents over the capacity are cut. Pieces are dealt by
a hash to cells of a set number of documents, each packed alone: best-fit decreasing, then a local search that
moves one item, exchanges one for one, or two for one, between underfull bins. A step is taken only if the sum
of squared fills grows; the emptiest bins lose items until they are empty. A cell leaves at most a few
underfull bins, so cells cost next to nothing against one global packing, and a lost executor repeats a cell.

Texts of plain characters are cut at white space, which no word of the tokenizer crosses, in Arrow columns: only the
distinct chunks of a batch become Python strings, and of those only the ones that the worker does not remember, as two
Arrow columns of words and ids. A text with any other character or with the string of a special token is encoded whole
by the library.

Defined cases: a null or empty text is the end id alone; repeated rows are packed as rows of their own; very
long texts give as many pieces as they need; an empty table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

import math
import re
import zlib
from itertools import chain

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import by_value, process_cache, trim

by_value(__name__)

CAPACITY = 2048
END_ID = 0
#: Documents of a cell; chunks and their characters remembered per worker; bytes of texts encoded at once (a longer
#: text alone), and new chunks.
CELL_DOCS = 50_000
MEMO = 200_000
MEMO_CHARS = 2_000_000
BATCH_BYTES = 1_000_000
LEARN = 4096
#: The local search ends after so many bins in a row that it could not empty.
STALL = 300

_UNUSUAL = "[^\\t\\n\\r\\x20-\\x7eÀ-ÖØ-öø-ÿ]"
_JOINED = r"'|[!-/:-@\[-`{-~]{2}"
_WORD = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_]+|[0-9]|(?:[^\s\w]|_)+")


def runs(start: np.ndarray, length: np.ndarray) -> np.ndarray:
    """The places of all runs (start, length), one run after the other."""
    ends = np.cumsum(length)
    return np.repeat(start - ends + length, length) + np.arange(ends[-1] if len(ends) else 0)


class Encoder:
    """Token ids, as little-endian unsigned 32-bit bytes, of one word-level tokenizer file."""

    def __init__(self, path: str):
        import os

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # a task has one core
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.special = [t.content for t in self.library.get_added_tokens_decoder().values()]
        self.merge = self.library.model.tokenize
        # the tokenizer's own name of each letter's bytes
        self.letters = {n: "".join(w for w, _ in self.library.pre_tokenizer.pre_tokenize_str(chr(n))) for n in (*range(0x61, 0x7B), *range(0xC0, 0x100)) if chr(n).isalpha()}
        self.remember(pa.array([], pa.large_string()), np.zeros(0, "<u4"), np.zeros(0, np.int64))
        trim()  # what reading the file left behind

    def remember(self, words: pa.Array, ids: np.ndarray, count: np.ndarray) -> None:
        """Distinct chunks, their ids one after the other, and how many each has."""
        self.words, self.ids, self.count = words, ids, count
        self.held = pc.sum(pc.utf8_length(words)).as_py() or 0  # characters

    def merged(self, words: list[str]) -> list[list[int]]:
        """The ids of words of letters."""
        return [[t.id for t in self.merge(w)] for w in " ".join(words).translate(self.letters).split(" ")] if words else []

    def learn(self, chunks: list[str]) -> list[list[int]]:
        """The ids of distinct chunks: words of letters are merged at once, signs and digits go to the library, one by one."""
        mixed = {c: _WORD.findall(c) for c in chunks if not c.isalpha()}
        words = [c for c in chunks if c.isalpha()]
        found = dict(zip(words, self.merged(words), strict=True))
        parts = set().union(*mixed.values()).difference(found)
        words = [w for w in parts if w.isalpha()]
        found.update(zip(words, self.merged(words), strict=True))
        others = [w for w in parts if not w.isalpha()]
        found.update(zip(others, (e.ids for e in self.library.encode_batch(others, add_special_tokens=False)), strict=True))
        return [list(chain.from_iterable(found[w] for w in mixed[c])) if c in mixed else found[c] for c in chunks]

    def known(self, chunks: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids of distinct chunks, and where each chunk's begin and how many they are; new chunks are learned and remembered."""
        at = pc.fill_null(pc.index_in(chunks, self.words), -1).to_numpy()
        fresh = pc.filter(chunks, pa.array(at < 0))
        ids, count = [self.ids], [self.count]
        for k in range(0, len(fresh), LEARN):  # lists of ids take far more memory than their arrays
            learned = self.learn(fresh.slice(k, LEARN).to_numpy(zero_copy_only=False).tolist())
            ids.append(np.fromiter(chain.from_iterable(learned), "<u4"))
            count.append(np.fromiter(map(len, learned), np.int64, len(learned)))
        ids, count = np.concatenate(ids), np.concatenate(count)
        at = at.astype(np.int64)
        at[at < 0] = np.arange(len(self.words), len(count))
        start = (np.cumsum(count) - count)[at]
        self.remember(pa.concat_arrays([self.words, fresh]), ids, count)
        if len(self.words) > MEMO or self.held > MEMO_CHARS:  # anew, with what this batch has
            self.remember(chunks, ids[runs(start, count[at])], count[at])
            if len(self.words) > MEMO or self.held > MEMO_CHARS:
                self.remember(self.words[:0], self.ids[:0], self.count[:0])
        return ids, start, count[at]

    def whole(self, text: str) -> bytes:
        return np.asarray(self.library.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()

    def encode(self, texts: pa.Array) -> list[bytes]:
        texts = texts.cast(pa.large_string()).fill_null("")
        whole = pc.match_substring_regex(texts, _UNUSUAL)
        for s in self.special:
            whole = pc.or_(whole, pc.match_substring(texts, s))
        cut = pc.utf8_lower(pc.if_else(whole, "", texts))
        alone = cut
        for sign in ".,;:!?-":
            alone = pc.replace_substring(alone, sign, f" {sign} ")
        # fewer distinct chunks where each sign is a word of its own
        words = pc.ascii_split_whitespace(pc.if_else(pc.match_substring_regex(cut, _JOINED), cut, alone))
        flat = words.flatten()
        flat = pc.if_else(pc.equal(flat, ""), None, flat).dictionary_encode()
        ids, start, count = self.known(flat.dictionary)
        where = flat.indices
        used = np.concatenate([[0], np.cumsum(pc.fill_null(pc.take(pa.array(count), where), 0).to_numpy())])
        where = where.drop_null().to_numpy()
        out = ids[runs(start[where], count[where])].tobytes()
        ends = (4 * used[words.offsets.to_numpy() - words.offsets[0].as_py()]).tolist()
        return [self.whole(texts[i].as_py()) if w else out[ends[i] : ends[i + 1]] for i, w in enumerate(whole.to_pylist())]

    def encode_all(self, texts: list[str]) -> list[bytes]:
        return self.encode(pa.array(texts, pa.large_string()))


def batched(texts: pa.Array, most: int | None = None):
    """Slices of at most BATCH_BYTES, or of one text."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(texts), 0).to_numpy().astype(np.int64))
    k = 0
    while k < len(texts):
        n = max(k + 1, int(np.searchsorted(ends, (ends[k - 1] if k else 0) + (most or BATCH_BYTES), "right")))
        yield texts.slice(k, n - k)
        k = n


def worker_encoder(path: str) -> Encoder:
    cache = process_cache("packing")
    if ("encoder", path) not in cache:
        cache["encoder", path] = Encoder(path)
    return cache["encoder", path]


def pieces(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, end_id: int = END_ID, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, piece, start, length, ids_crc32: the documents' token ids, cut at the capacity."""
    end = int(end_id).to_bytes(4, "little")

    def cut(batches):
        encoder = worker_encoder(tokenizer)
        for batch in batches:
            rows, piece, start, length, crc = [], [], [], [], []
            encoded = (e for part in batched(batch.column(1)) for e in encoder.encode(part))
            for i, ids in enumerate(encoded):
                if i % 2048 == 2047:
                    trim()
                ids += end
                n = len(ids) // 4
                for k in range(0, n, capacity):
                    part = ids[4 * k : 4 * (k + capacity)]
                    rows.append(i)
                    piece.append(k // capacity)
                    start.append(k)
                    length.append(len(part) // 4)
                    crc.append(zlib.crc32(part))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).take(pa.array(rows, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())],
                ["doc_id", "piece", "start", "length", "ids_crc32"],
            )
        trim()

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(F.col(key).alias("doc_id"), F.col(text).alias("text")).mapInArrow(cut, f"doc_id {kind}, piece int, start long, length long, ids_crc32 long")


class Bins:
    """Bins of one cell: what they hold, what room they have, and which have a given room."""

    def __init__(self, lengths: list[int], capacity: int):
        self.lengths, self.capacity = lengths, capacity
        self.items: list[list[int]] = []
        self.room: list[int] = []
        self.by_room: list[set[int]] = [set() for _ in range(capacity + 1)]
        self.mask = 0  # bit r: some bin has room r

    def _index(self, b: int) -> None:
        r = self.room[b]
        self.by_room[r].add(b)
        self.mask |= 1 << r

    def _forget(self, b: int) -> None:
        r = self.room[b]
        self.by_room[r].discard(b)
        if not self.by_room[r]:
            self.mask &= ~(1 << r)

    def tightest(self, length: int, but: int = -1) -> int:
        """The bin with the least room that still takes length; -1: none."""
        m = self.mask >> length
        while m:
            low = (m & -m).bit_length() - 1
            found = next((b for b in self.by_room[length + low] if b != but), -1)
            if found >= 0:
                return found
            m &= m - 1
        return -1

    def put(self, i: int, b: int) -> None:
        self._forget(b)
        self.items[b].append(i)
        self.room[b] -= self.lengths[i]
        self._index(b)

    def take(self, i: int, b: int) -> None:
        self._forget(b)
        self.items[b].remove(i)
        self.room[b] += self.lengths[i]
        if self.items[b]:
            self._index(b)

    def best_fit(self) -> None:
        for i in sorted(range(len(self.lengths)), key=lambda i: (-self.lengths[i], i)):
            b = self.tightest(self.lengths[i])
            if b < 0:
                b = len(self.items)
                self.items.append([])
                self.room.append(self.capacity)
                self._index(b)
            self.put(i, b)

    def improve(self, stall: int = STALL, window: int = 48) -> None:
        """Empty the emptiest bins, one after the other, by moves and exchanges that raise the sum of squared fills."""
        underfull = sorted((b for b in range(len(self.items)) if self.room[b] and self.items[b]), key=lambda b: -self.room[b])
        spots: dict[int, list[tuple[int, int]]] = {}  # room after taking out one item -> (bin, item)

        def offer(b: int) -> None:
            for j in self.items[b]:
                spots.setdefault(self.room[b] + self.lengths[j], []).append((b, j))

        for b in underfull:
            offer(b)

        def partner(need: int, victim: int) -> tuple[int, int] | None:
            """A fuller bin and an item shorter than need whose place would hold need."""
            for c in range(need, min(need + window, self.capacity) + 1):
                for k, (b, j) in enumerate(reversed(spots.get(c, ())[-64:])):
                    if b != victim and j in self.items[b] and self.room[b] + self.lengths[j] == c and self.lengths[j] < need and self.room[b] <= self.room[victim]:
                        return b, j
            return None

        failed = 0
        for victim in underfull:
            if failed >= stall:
                break
            if not self.items[victim]:
                continue
            moved = True
            while moved and self.items[victim]:
                moved = False
                held = sorted(self.items[victim], key=lambda i: -self.lengths[i])
                for i in held:
                    b = self.tightest(self.lengths[i], victim)
                    if b >= 0:
                        self.take(i, victim)
                        self.put(i, b)
                        offer(b)
                        moved = True
                if moved or not self.items[victim]:
                    continue
                tries = [(i,) for i in held] + [(i, j) for x, i in enumerate(held[:12]) for j in held[x + 1 : 12]]
                for group in tries:
                    need = sum(self.lengths[i] for i in group)
                    if need <= self.capacity and (found := partner(need, victim)):
                        b, j = found
                        self.take(j, b)
                        for i in group:
                            self.take(i, victim)
                            if not self.items[b]:  # its last item went out: index it anew
                                self._index(b)
                            self.put(i, b)
                        if not self.items[victim]:
                            self._index(victim)
                        self.put(j, victim)
                        offer(b)
                        moved = True
                        break
            failed = failed + 1 if self.items[victim] else 0


def pack(lengths: list[int], capacity: int = CAPACITY) -> tuple[list[int], list[int]]:
    """Bin and offset of each length; bins are numbered without gaps."""
    bins = Bins(lengths, capacity)
    bins.best_fit()
    bins.improve()
    where, offset = [0] * len(lengths), [0] * len(lengths)
    for n, held in enumerate(h for h in bins.items if h):
        at = 0
        for i in held:
            where[i], offset[i] = n, at
            at += lengths[i]
    return where, offset


def pack_documents(docs: DataFrame, tokenizer: str, capacity: int = CAPACITY, end_id: int = END_ID, key: str = "doc_id", text: str = "text") -> DataFrame:
    """One row per piece: doc_id, piece, start, length, ids_crc32, sequence_id, offset."""
    cells = max(1, math.ceil(docs.count() / CELL_DOCS))
    cut = pieces(docs, tokenizer, capacity, end_id, key, text).withColumn("cell", F.pmod(F.xxhash64("doc_id", "piece", F.monotonically_increasing_id()), F.lit(cells)))  # by row: many rows may share an id

    def packed(cell: pa.Table) -> pa.Table:
        # a fixed order, so that a repeated task gives the same bins
        cell = cell.sort_by([("length", "descending"), ("doc_id", "ascending"), ("piece", "ascending"), ("ids_crc32", "ascending")])
        where, offset = pack(cell.column("length").to_pylist(), capacity)
        first = (cell.column("cell")[0].as_py() if cell.num_rows else 0) << 32
        ids = pa.array(np.asarray(where, dtype=np.int64) + first, pa.int64())
        return cell.drop_columns(["cell"]).append_column("sequence_id", ids).append_column("offset", pa.array(offset, pa.int64()))

    kind = docs.schema[key].dataType.simpleString()
    out = cut.groupBy("cell").applyInArrow(packed, f"doc_id {kind}, piece int, start long, length long, ids_crc32 long, sequence_id long, offset long")
    return out.withColumnRenamed("doc_id", key)
