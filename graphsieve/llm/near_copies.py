"""Near copies by SimHash, checked by the similarity of whole texts: shingle sets whose Jaccard similarity is at least 0.8.

Texts of the same words are one from the start. Every other text gets a SimHash fingerprint of its shingles, and operator 8's index of byte
places with its count filter links fingerprints of up to four differing bits. Similarity 0.8 is some ten bits, beyond that index, so candidates are
widened by MinHash keys of the same shingles (BANDS keys of ROWS minima each): two sets of similarity 0.8 share none with a chance of 5 in a million.
Candidates that links or keys connect come together with their texts, and those near by fingerprint or with a key in common are compared set by set,
exactly. A group gives a spanning forest of its links; long groups are split into blocks, of which every two are compared in a task of their own.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from graphsieve.llm.common import materialize, utf8
from graphsieve.llm.simhash import MAX_BITS, _close, links, majority, order_of, shingle_hashes, with_rows
from graphsieve.operators.components import connected_components

SHINGLE = 5
#: Least similarity, as a fraction.
LEAST = (4, 5)
BANDS, ROWS = 40, 6
#: Members and bytes of text of a block.
LONG, LONG_BYTES = 1_000, 4_000_000

_DRAW = np.random.default_rng(5)
_XOR = _DRAW.integers(0, 1 << 32, BANDS * ROWS, np.uint32)
_ODD = _DRAW.integers(0, 1 << 31, BANDS * ROWS, np.uint32) * np.uint32(2) + np.uint32(1)
_MIX = _DRAW.integers(0, 1 << 63, (BANDS, ROWS), np.uint64) * np.uint64(2) + np.uint64(1)


def shingle_set(text: bytes, shingle: int = SHINGLE) -> np.ndarray:
    """Sorted distinct hashes of the shingles of a text's words; a shorter text is one shingle, one without words none."""
    return np.unique(shingle_hashes(text, shingle))


def keys_of(hashes: np.ndarray) -> np.ndarray:
    """The keys of a set, as signed 64-bit integers; an empty set has none."""
    if not hashes.size:
        return np.empty(0, np.int64)
    folded = (hashes ^ (hashes >> np.uint64(32))).astype(np.uint32)
    least = np.full(BANDS * ROWS, 0xFFFFFFFF, np.uint32)
    for k in range(0, len(folded), 2048):
        x = folded[k : k + 2048, None] ^ _XOR
        x *= _ODD
        np.minimum(least, x.min(0), out=least)
    keys = (least.reshape(BANDS, ROWS).astype(np.uint64) * _MIX).sum(1, dtype=np.uint64)
    return ((keys & ~np.uint64(63)) | np.arange(BANDS, dtype=np.uint64)).view(np.int64)


def similar(a: np.ndarray, b: np.ndarray) -> bool:
    """Whether two sorted sets are at least as similar as LEAST, exactly."""
    n, m, (over, under) = len(a), len(b), LEAST
    if min(n, m) * under < max(n, m) * over:
        return False
    at = np.searchsorted(a, b)
    shared = int((a[np.minimum(at, n - 1)] == b).sum())
    return shared * under >= (n + m - shared) * over


def forest(rows: list[int], sets: list[np.ndarray], keys: np.ndarray, fps: np.ndarray) -> list[tuple[int, int]]:
    """Links that join the rows as all links of similar ones that share a key, or whose fingerprints are near, would."""
    left, out = np.arange(len(rows)), []
    while left.size:
        frontier, left = [left[0]], left[1:]
        while frontier and left.size:
            f = frontier.pop()
            near = (keys[left] == keys[f]).any(1) | _close(np.full(left.shape, fps[f], np.uint64), fps[left], MAX_BITS)
            near[near] = [similar(sets[f], sets[x]) for x in left[near]]
            out += [(rows[f], rows[x]) for x in left[near]]
            frontier += list(left[near])
            left = left[~near]
    return out


def _sketches(docs: DataFrame) -> DataFrame:
    """Rows ``(row, doc_id, words, fp, keys)``: the digest of a text's words, its fingerprint and the keys of its set."""

    def made(batches):
        import xxhash

        for batch in batches:
            texts = utf8(batch["text"])
            words = [xxhash.xxh3_128_digest(b" ".join(t.lower().split())) for t in texts]
            hashes = [shingle_hashes(t, SHINGLE) for t in texts]
            fp = np.array([majority(h) for h in hashes], "<u8").view("<i8")
            keys = [keys_of(np.unique(h)) for h in hashes]
            yield pa.RecordBatch.from_pydict({"row": batch["_row"], "doc_id": batch["doc_id"].cast(pa.int64()), "words": pa.array(words, pa.binary()), "fp": pa.array(fp), "keys": pa.array(keys, pa.list_(pa.int64()))})

    return docs.select("_row", "doc_id", "text").mapInArrow(made, "row long, doc_id long, words binary, fp long, keys array<long>")


def candidates(single: DataFrame) -> DataFrame:
    """Rows ``(row, least)`` that connect what may be similar: by SimHash links of up to MAX_BITS bits, and by keys in common."""
    fps = materialize(single.groupBy("fp").agg(F.min("row").alias("rep")), "near-fps")
    alike = single.join(fps, "fp").filter("row <> rep").select("row", F.col("rep").alias("least"))
    linked = links(fps.select("fp")).join(fps.select(F.col("fp").alias("src"), F.col("rep").alias("row")), "src").join(fps.select(F.col("fp").alias("dst"), F.col("rep").alias("least")), "dst")
    least = F.min("row").over(Window.partitionBy("key"))
    keyed = single.select("row", F.explode("keys").alias("key")).withColumn("least", least).filter("row <> least").select("row", "least")
    return keyed.unionByName(alike).unionByName(linked.select("row", "least")).distinct()


def _links(met: DataFrame) -> DataFrame:
    """Rows ``(src, dst)`` from candidates ``(group, row, text)``, dealt by blocks."""
    sizes = met.groupBy("group").agg(F.count("*").alias("n"), F.sum(F.length("text")).alias("bytes"))
    blocks = F.ceil(F.greatest(F.col("n") / LONG, F.col("bytes") / LONG_BYTES)).cast("int")
    dealt = met.join(sizes.select("group", F.greatest(blocks, F.lit(1)).alias("blocks")), "group").withColumn("own", F.expr("cast(pmod(xxhash64(row), blocks) as int)"))
    # (low, high): the two blocks that meet; a text goes to every meeting of its own block
    meeting = F.explode(F.expr("transform(sequence(0, blocks - 1), x -> struct(least(x, own) as low, greatest(x, own) as high))"))
    place = ["group", "low", "high"]
    dealt = dealt.select("group", "row", "text", meeting.alias("m")).select("group", "m.low", "m.high", "row", "text")

    def compared(batches):
        def links(rows, sets):
            fps = np.array([f for _, f in sets], np.uint64)
            sets = [s for s, _ in sets]
            found = forest(rows, sets, np.array([keys_of(s) for s in sets]), fps) if len(rows) > 1 else []
            if found:
                pairs = np.array(found, np.int64)
                yield pa.RecordBatch.from_pydict({"src": pa.array(pairs[:, 0]), "dst": pa.array(pairs[:, 1])})

        at, rows, sets = None, [], []
        for batch in batches:
            for *here, row, text in zip(*[batch[c].to_pylist() for c in (*place, "row")], utf8(batch["text"])):
                if here != at:
                    yield from links(rows, sets)
                    at, rows, sets = here, [], []
                rows.append(row)
                h = shingle_hashes(text, SHINGLE)
                sets.append((np.unique(h), majority(h)))
        yield from links(rows, sets)

    return dealt.repartition(*place).sortWithinPartitions(*place, "row").mapInArrow(compared, "src long, dst long")


def keep_one_similar(docs: DataFrame) -> DataFrame:
    """One row of each group of near copies stays: that of the smallest doc_id, null ids last. A group is what links of similar texts connect;
    texts without words are one group."""
    docs = with_rows(docs)
    sketches = _sketches(docs).groupBy("words").agg(F.min(order_of("row")).alias("first"), F.any_value("fp").alias("fp"), F.any_value("keys").alias("keys"))
    single = materialize(sketches.select("first", F.col("first.row").alias("row"), "fp", "keys"), "near-texts")
    groups = connected_components(materialize(candidates(single), "near-met"), "row", "least")
    texts = docs.select(F.col("_row").alias("row"), "text").join(groups.select(F.col("node").alias("row"), F.col("component").alias("group")), "row")
    linked = connected_components(materialize(_links(materialize(texts, "near-candidates")), "near-links")).withColumnRenamed("node", "row")
    kept = single.join(linked, "row", "left").groupBy(F.coalesce("component", "row").alias("group")).agg(F.min("first").alias("first"))
    return docs.join(kept.select(F.col("first.row").alias("_row")), "_row", "left_semi").drop("_row")
