"""Benchmark decontamination: exact containment of item windows, found by a prefix-filtered join of shingles.

A window (WINDOW consecutive words of an item; a shorter item is one window) occurs in a document only if all its
shingles do. With the shingles of a window ordered by rarity in the corpus, one necessary prefix token is enough: its rarest
shingle. Documents are joined to windows by that shingle alone; its place in the window and the lengths of both bound where
the window may start; the words there are then compared.
"""

from __future__ import annotations

from itertools import chain, repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsieve.llm.common import materialize, utf8

WINDOW = 10
SHINGLE = 5
#: Words of benchmark items that are held at a time; a larger benchmark is joined block by block, a longer item part by part.
BLOCK_WORDS = 200_000

#: Letters A-Z to lower case; other ASCII characters than letters and digits part words.
_FOLD = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))


def words_of(text: bytes) -> list[bytes]:
    return text.translate(_FOLD).split()


def _roll(ids: np.ndarray, size: int) -> np.ndarray:
    """A hash of every ``size`` consecutive word ids; 0 where one is unknown (-1)."""
    n = len(ids) - size + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    h, known = np.zeros(n, np.uint64), np.ones(n, bool)
    for k in range(size):
        part = ids[k : k + n]
        h = (h ^ part.astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        h ^= h >> np.uint64(29)
        known &= part >= 0
    return np.where(known, h | np.uint64(1), np.uint64(0))


class Windows:
    """Windows of a block of items, and the shingles that they can be found by."""

    def __init__(self, items: list[tuple[str, list[bytes]]], window: int = WINDOW, shingle: int = SHINGLE):
        self.vocabulary: dict[bytes, int] = {}
        self.items = sorted({i for i, _ in items})
        place = {x: k for k, x in enumerate(self.items)}
        grams: dict[bytes, tuple[np.ndarray, set[int]]] = {}
        for item, words in items:
            ids = np.array([self.vocabulary.setdefault(w, len(self.vocabulary)) for w in words], np.int32)
            size = min(window, len(ids))
            for k in range(len(ids) - size + 1 if size else 0):
                w = ids[k : k + size]
                grams.setdefault(w.tobytes(), (w, set()))[1].add(place[item])
        self.words = [w for w, _ in grams.values()]
        self.of = [sorted(x) for _, x in grams.values()]
        self.sizes = sorted({min(shingle, len(w)) for w in self.words})
        self.shingles = {s: np.unique(np.concatenate([_roll(w, s) for w in self.words if min(shingle, len(w)) == s])) for s in self.sizes}
        self.shingle = shingle

    def ids(self, words: list[bytes]) -> np.ndarray:
        get = self.vocabulary.get
        return np.fromiter(map(get, words, repeat(-1)), np.int32, len(words))

    def order(self, counts: dict[int, dict[int, int]]) -> None:
        """Index every window by its rarest shingle; counts: of shingles in the corpus, by size and hash."""
        rows: dict[int, list[tuple[int, int, int]]] = {s: [] for s in self.sizes}
        for k, w in enumerate(self.words):
            s = min(self.shingle, len(w))
            hashes = [int(h) for h in _roll(w, s)]
            at = min(range(len(hashes)), key=lambda i: (counts.get(s, {}).get(hashes[i], 0), hashes[i], i))
            rows[s].append((hashes[at], k, at))
        self.index = {}
        for s, found in rows.items():
            found.sort()
            self.index[s] = (np.array([h for h, _, _ in found], np.uint64), np.array([k for _, k, _ in found]), np.array([a for _, _, a in found]))

    def match(self, ids: np.ndarray) -> tuple[np.ndarray, set[int]]:
        """Which words are hit, and the places of the items with windows here."""
        edges, found = np.zeros(len(ids) + 1, np.int32), set()
        for s, (keys, windows, places) in self.index.items():
            h = _roll(ids, s)
            where = np.flatnonzero(h)
            if not where.size:
                continue
            lo, hi = np.searchsorted(keys, h[where]), np.searchsorted(keys, h[where], "right")
            for p, a, b in zip(where[hi > lo], lo[hi > lo], hi[hi > lo]):
                for k in range(a, b):
                    w, start = self.words[windows[k]], p - places[k]
                    if start >= 0 and start + len(w) <= len(ids) and np.array_equal(ids[start : start + len(w)], w):
                        edges[start] += 1
                        edges[start + len(w)] -= 1
                        found.update(self.of[windows[k]])
        return np.cumsum(edges[:-1]) > 0, found


def _blocks(benchmark: DataFrame, window: int, shingle: int, most: int | None = None):
    """Items in blocks of at most BLOCK_WORDS words and a window, one after another; the rows come to the driver one partition at a time.

    Parts of a long item overlap by a word less than a window, so that together they have its windows and no others.
    """
    most, block, held = max(window, most or BLOCK_WORDS), [], 0
    for r in benchmark.select(F.coalesce(F.col("item_id").cast("string"), F.lit("null")).alias("i"), F.coalesce("text", F.lit("")).alias("t")).toLocalIterator():
        words = words_of(r.t.encode())
        for at in range(0, max(1, len(words) - window + 1), most):
            if part := words[at : at + most + window - 1]:
                if held and held + len(part) > most:
                    yield Windows(block, window, shingle)
                    block, held = [], 0
                block.append((r.i, part))
                held += len(part)
    if block:
        yield Windows(block, window, shingle)


def _shingle_counts(docs: DataFrame, held) -> list:
    """Rows (size, shingle, n): how often each shingle of the items occurs in all documents."""

    def counted(batches):
        w = held.value
        totals = {s: np.zeros(len(k), np.int64) for s, k in w.shingles.items()}
        for batch in batches:
            for text in utf8(batch["text"]):
                ids = w.ids(words_of(text))
                for s, keys in w.shingles.items():
                    h = _roll(ids, s)
                    h = h[h != 0]
                    if h.size:
                        at = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
                        totals[s] += np.bincount(at[keys[at] == h], minlength=len(keys))
        for s, n in totals.items():
            hit = np.flatnonzero(n)
            yield pa.RecordBatch.from_pydict({"size": pa.array(np.full(len(hit), s)), "shingle": pa.array(w.shingles[s][hit].view(np.int64)), "n": pa.array(n[hit])})

    return docs.select("text").mapInArrow(counted, "size long, shingle long, n long").groupBy("size", "shingle").agg(F.sum("n").alias("n")).collect()


def find_contamination(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW, shingle: int = SHINGLE) -> DataFrame:
    """``docs`` with n_words, n_hit (words inside an occurrence of a window) and items (ids, sorted as strings).

    Null texts have no words; a null item_id reads "null"; items without words have no window. Repeated items and rows
    count each. Blocks of the benchmark follow one another, each read after the one before is written and gone, so that the driver and every worker
    hold one block, whatever the benchmark's size. Columns of these names are replaced.
    """
    sc = docs.sparkSession.sparkContext
    out = docs.drop("n_words", "n_hit", "items", "_spans").withColumns({"n_words": F.lit(0).cast("long"), "n_hit": F.lit(0).cast("long"), "items": F.array().cast("array<string>"), "_spans": F.lit(b"").cast("binary")})
    schema = out.schema
    before = None
    for k, block in enumerate(chain(_blocks(benchmark, window, shingle), [None])):
        if block is None:
            if k:
                break
            block = Windows([], window, shingle)
        if before is not None:
            out = materialize(out, "contamination")
            before.unpersist()
        held = sc.broadcast(block)
        counts: dict[int, dict[int, int]] = {}
        if block.words:
            for r in _shingle_counts(docs, held):
                counts.setdefault(r.size, {})[r.shingle % (1 << 64)] = r.n
        held.unpersist()
        block.order(counts)
        before = sc.broadcast(block)
        out = out.mapInArrow(_matcher(before), schema)
    return out.drop("_spans")


def _matcher(held):
    def matched(batches):
        w = held.value
        for batch in batches:
            n_words, n_hit, items, spans = [], [], [], []
            for text, before, old in zip(utf8(batch["text"]), batch["items"].to_pylist(), batch["_spans"].to_pylist()):
                words = words_of(text)
                hit, found = w.match(w.ids(words))
                if old:  # bits of the blocks before
                    hit = hit | np.unpackbits(np.frombuffer(old, np.uint8), count=len(words)).astype(bool)
                n_words.append(len(words)), n_hit.append(int(hit.sum()))
                items.append(sorted({*before, *(w.items[k] for k in found)}) if found else before)
                spans.append(np.packbits(hit).tobytes() if hit.any() else b"")
            new = {"n_words": pa.array(n_words, pa.int64()), "n_hit": pa.array(n_hit, pa.int64()), "items": pa.array(items, pa.list_(pa.string())), "_spans": pa.array(spans, pa.binary())}
            yield pa.RecordBatch.from_arrays([new.get(n, batch.column(k)) for k, n in enumerate(batch.schema.names)], names=batch.schema.names)

    return matched


def contamination_report(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """One row per document: how many words are hit, and a digest of the items found in it."""
    found = find_contamination(docs.select("doc_id", "text"), benchmark)
    return found.select(
        "doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.concat_ws(",", "items").cast("binary"), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated")
    )


def drop_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The documents in which no window of any item occurs."""
    return find_contamination(docs, benchmark).filter("n_hit = 0").select(*docs.columns)


