"""SimHash near-duplicates: an inverted index of byte positions with count filtering.

Fingerprints of 64 bits that differ in at most 4 share at least 4 of their 8 bytes in place. Any 4 of 8 places hold one of 20
triples of places (three rings of places; two from one ring with one of the next, or a whole ring), so every such pair meets in a
posting list of some triple. Within a list the shared positional bytes of a pair are tallied, pairs with 4 or more are
verified by their bits. Equal fingerprints are one entry from the start. A list gives a spanning forest of its links,
never all pairs; lists longer than LONG are split into blocks, of which every two are compared in a task of their own.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsieve.llm.common import materialize, utf8
from graphsieve.operators.components import connected_components

MAX_BITS = 4
LEAST_SHARED = 8 - MAX_BITS
LONG = 4_000


def _triples() -> list[tuple[int, int, int]]:
    """Triples of 8 places of which every 4 places hold one (rings 0-2, 3-5, 6-7)."""
    rings = [(0, 1, 2), (3, 4, 5), (6, 7)]
    out = [r for r in rings if len(r) == 3]
    for k, ring in enumerate(rings):
        out += [(*two, one) for two in combinations(ring, 2) for one in rings[(k + 1) % 3]]
    out = sorted(tuple(sorted(x)) for x in out)
    assert all(any(set(t) <= set(four) for t in out) for four in combinations(range(8), 4))
    return out


TRIPLES = _triples()


def shingle_hashes(text: bytes, shingle: int = 4) -> np.ndarray:
    """XXH64 of every shingle of a text's words, repeats included; a shorter text is one shingle, one without words none."""
    import xxhash

    words, digest = text.lower().split(), xxhash.xxh64_intdigest
    if not words:
        return np.empty(0, "<u8")
    joined = b" ".join(words)
    if len(words) <= shingle:
        return np.array([digest(joined, 42)], "<u8")
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1)
    starts = np.concatenate([[0], ends[: len(words) - shingle]]).tolist()
    return np.array([digest(joined[a:b], 42) for a, b in zip(starts, (ends[shingle - 1 :] - 1).tolist())], "<u8")


def majority(h: np.ndarray) -> int:
    """The bits that more than half of the hashes set."""
    total = np.zeros(64, np.int64)
    for k in range(0, len(h), 1 << 16):
        total += np.unpackbits(h[k : k + (1 << 16)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(total * 2 > len(h), bitorder="little").view("<u8")[0])


def fingerprint_of(text: bytes, shingle: int = 4) -> int:
    """SimHash of the words of a text: a bit is set if more than half of the shingles' hashes set it; 0 without words."""
    return majority(shingle_hashes(text, shingle))


def fingerprints(docs: DataFrame, shingle: int = 4) -> DataFrame:
    """Rows ``(doc_id, fp)`` of whole texts; fp as a signed 64-bit integer. Null and empty texts have fingerprint 0."""

    def made(batches):
        for batch in batches:
            fp = np.array([fingerprint_of(t, shingle) for t in utf8(batch["text"])], "<u8")
            yield pa.RecordBatch.from_pydict({"doc_id": batch["doc_id"].cast(pa.int64()), "fp": pa.array(fp.view("<i8"))})

    return docs.select("doc_id", "text").mapInArrow(made, "doc_id long, fp long")


def _close(a: np.ndarray, b: np.ndarray, max_bits: int) -> np.ndarray:
    """Count filter, then the bits: which entries of two arrays are linked."""
    x = a ^ b
    shared = (np.ascontiguousarray(x)[..., None].view(np.uint8) == 0).sum(-1)
    out = shared >= 8 - max_bits
    out[out] = np.bitwise_count(x[out]) <= max_bits
    return out


def _forest(fps: np.ndarray, max_bits: int) -> list[tuple[int, int]]:
    """Links that join the entries of a list as all their links would: each newly met entry and the one that met it."""
    left, out = np.sort(fps), []
    while left.size:
        frontier, left = [left[0]], left[1:]
        while frontier and left.size:
            f = frontier.pop()
            near = _close(np.full(left.shape, f, np.uint64), left, max_bits)
            if near.any():
                out += [(int(f), int(x)) for x in left[near]]
                frontier += list(left[near])
                left = left[~near]
    return out


def links(fps: DataFrame, max_bits: int = MAX_BITS, long_list: int = LONG) -> DataFrame:
    """Rows ``(src, dst)`` between distinct fingerprints; their components are those of all links of up to ``max_bits`` bits."""
    if not 0 <= max_bits <= MAX_BITS:
        raise ValueError(f"the triples cover distances of up to {MAX_BITS} bits")
    byte = lambda p: F.shiftrightunsigned("fp", 8 * p).bitwiseAND(0xFF)
    keys = F.array(*[F.lit(k << 24).bitwiseOR(F.shiftleft(byte(a), 16)).bitwiseOR(F.shiftleft(byte(b), 8)).bitwiseOR(byte(c)) for k, (a, b, c) in enumerate(TRIPLES)])
    index = fps.select("fp", F.explode(keys).alias("key"))
    counts = index.groupBy("key").agg(F.count("*").alias("n")).filter("n > 1")
    index = index.join(counts, "key")
    blocks = F.expr(f"cast(ceil(n / {long_list}) as int)")
    # (low, high): the two blocks that meet; an entry goes to every meeting of its own block
    own = F.expr("cast(pmod(xxhash64(fp), blocks) as int)")
    index = index.withColumn("blocks", blocks).withColumn("own", own)
    index = index.select("fp", "key", F.explode(F.expr("transform(sequence(0, blocks - 1), x -> struct(least(x, own) as low, greatest(x, own) as high))")).alias("m")).select("fp", "key", "m.low", "m.high")
    place = ["key", "low", "high"]

    def met(batches):
        held: list[np.ndarray] = [np.empty(0, np.int64)] * 4
        for batch in batches:
            cols = [np.concatenate([h, batch[c].to_numpy(zero_copy_only=False).astype(np.int64)]) for h, c in zip(held, ("fp", *place))]
            n = len(cols[0])
            change = np.flatnonzero((cols[1][1:] != cols[1][:-1]) | (cols[2][1:] != cols[2][:-1]) | (cols[3][1:] != cols[3][:-1])) + 1
            last = int(change[-1]) if change.size else 0
            yield from _batch([*change.tolist()], cols[0][:last], n)
            held = [c[last:] for c in cols]
        yield from _batch([len(held[0])], held[0], 0)

    def _batch(ends, values, _n):
        values, out, start = values.view(np.uint64), [], 0
        bounds = np.array([0, *[e for e in ends if e <= len(values)]])
        sizes = np.diff(bounds)
        two = bounds[:-1][sizes == 2]  # most lists: one pair
        if two.size:
            near = _close(values[two], values[two + 1], max_bits)
            out += list(zip(values[two][near].tolist(), values[two + 1][near].tolist()))
        for start, size in zip(bounds[:-1][sizes > 2].tolist(), sizes[sizes > 2].tolist()):
            out += _forest(values[start : start + size], max_bits)
        if out:
            pairs = np.array(out, np.uint64).view(np.int64)
            yield pa.RecordBatch.from_pydict({"src": pa.array(pairs[:, 0]), "dst": pa.array(pairs[:, 1])})

    dealt = index.repartition(*place).sortWithinPartitions(*place)
    return dealt.mapInArrow(met, "src long, dst long").distinct()


def near_duplicates(docs: DataFrame, shingle: int = 4, max_bits: int = MAX_BITS) -> DataFrame:
    """Rows ``(doc_id, fingerprint, component_id)``: the smallest doc_id that links reach.

    Texts are read whole. Null and empty texts have fingerprint zero, linked like any other. Repeated ids give a row each; a null
    id never becomes a component's id unless it has no other (then null).
    """
    made = materialize(fingerprints(docs, shingle), "fingerprints")
    fps = materialize(made.groupBy("fp").agg(F.min("doc_id").alias("rep")), "fp-distinct")
    groups = connected_components(materialize(links(fps.select("fp"), max_bits), "fp-links"))
    tagged = materialize(fps.join(groups.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "rep", F.coalesce("component", "fp").alias("component")), "fp-tagged")
    ids = materialize(tagged.groupBy("component").agg(F.min("rep").alias("component_id")), "fp-ids")
    named = materialize(tagged.join(ids, "component").select("fp", "component_id"), "fp-named")
    return made.join(named, "fp").select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def with_rows(docs: DataFrame) -> DataFrame:
    """``docs`` with a unique ``_row``, written once so that the numbers hold."""
    return materialize(docs.withColumn("_row", F.monotonically_increasing_id()), "near-docs")


def order_of(row: str = "_row"):
    """What orders the rows of a group: the smallest doc_id first, nulls last, then the row."""
    return F.struct(F.col("doc_id").isNull().alias("no_id"), F.col("doc_id"), F.col(row).alias("row"))


def keep_one(docs: DataFrame, shingle: int = 4, max_bits: int = MAX_BITS) -> DataFrame:
    """One row of each group stays: that of the smallest doc_id, null ids last. Rows are told apart by a number of their own, so null and repeated
    ids of different groups all stay."""
    docs = with_rows(docs)
    found = near_duplicates(docs.select(F.col("_row").alias("doc_id"), "text"), shingle, max_bits).select(F.col("doc_id").alias("_row"), "component_id")
    kept = docs.select("_row", "doc_id").join(found, "_row").groupBy("component_id").agg(F.min(order_of()).alias("first"))
    return docs.join(kept.select(F.col("first.row").alias("_row")), "_row", "left_semi").drop("_row")
