"""Best-fit packing whose bin counts are certified by dual-feasible-function bounds.

Each group of pieces is packed best-fit decreasing. Lower bounds from two families of dual feasible functions certify the
group's number of bins or show a gap. Groups with a gap then exchange pieces: the pieces of their bins that are not full
(and of every group's emptiest bin) are dealt anew, whole bins at a time, and packed again; a new packing counts only if it
takes no more bins than the old.
"""

from __future__ import annotations

import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsieve.llm.common import PieceEncoder, materialize, worker_kept

CAPACITY = 2048
GROUP = 8_000  # pieces that are packed together
_PIECE = "uid long, doc_id long, piece int, start long, length long, ids_crc32 long"
_PACKED = _PIECE + ", grp long, bin long, offset long, fill long, gap long, low long"


def lower_bound(lengths, capacity: int = CAPACITY) -> int:
    """Bins that any packing needs: the best of the sum, the threshold functions and the rounding functions."""
    x = np.asarray(lengths, np.int64)
    if not x.size:
        return 0
    h = np.bincount(x, minlength=capacity + 1)
    sizes = np.arange(capacity + 1)
    best = -(-int(x.sum()) // capacity)
    n, mass = np.concatenate([[0], np.cumsum(h)]), np.concatenate([[0], np.cumsum(h * sizes)])  # n[k]: pieces below k
    for a in range(1, capacity // 2 + 1):  # threshold: large pieces fill a bin, small ones are ignored
        total = capacity * int(n[-1] - n[capacity - a + 1]) + int(mass[capacity - a + 1] - mass[a])
        best = max(best, -(-total // capacity))
    there = np.flatnonzero(h)
    for k in range(1, 31):  # rounding: pieces count by how often they exceed shares of 1/(k+1)
        scaled = (k + 1) * there
        value = np.where(scaled % capacity == 0, k * there, (scaled // capacity) * capacity)  # times k * capacity
        best = max(best, -(-int((h[there] * value).sum()) // (k * capacity)))
    return best


def best_fit_decreasing(lengths, capacity: int = CAPACITY) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Bin and offset of every piece, and the fill of every bin. Each piece goes where it leaves least room; ties by position."""
    x = np.asarray(lengths, np.int64)
    bins, offsets, fills = np.empty(len(x), np.int64), np.empty(len(x), np.int64), []
    room: dict[int, list[int]] = {}
    open_ = 0  # bit r is set: a bin has room for r more
    for k in np.argsort(-x, kind="stable").tolist():
        size = int(x[k])
        fits = open_ >> size
        if fits and size:
            left = size + (fits & -fits).bit_length() - 1
            b = room[left].pop()
            if not room[left]:
                open_ &= ~(1 << left)
        else:
            b, left = len(fills), capacity
            fills.append(0)
        bins[k], offsets[k] = b, fills[b]
        fills[b] += size
        if left := left - size:
            room.setdefault(left, []).append(b)
            open_ |= 1 << left
    return bins, offsets, np.array(fills, np.int64)


def cut_pieces(docs: DataFrame, tokenizer: str, kind: str = "word", capacity: int = CAPACITY, end_id: int = 0) -> DataFrame:
    """Encode ``docs(doc_id, text)``, add the end id, and cut only what exceeds the capacity. Null text is empty: one id."""
    end = np.array([end_id], "<u4").tobytes()

    def cut(batches):
        from pyspark import TaskContext

        encoder, uid = PieceEncoder.get(tokenizer, kind), TaskContext.get().partitionId() << 40
        for batch in batches:
            rows = []
            for d, text in zip(batch["doc_id"].to_pylist(), batch["text"]):
                ids = encoder.encode(text.as_py() or "") + end
                for k, at in enumerate(range(0, len(ids), 4 * capacity)):
                    part = ids[at : at + 4 * capacity]
                    rows.append((uid, d, k, at // 4, len(part) // 4, zlib.crc32(part)))
                    uid += 1
            names = ("uid", "doc_id", "piece", "start", "length", "ids_crc32")
            cols = list(zip(*rows)) or [()] * 6
            yield pa.RecordBatch.from_pydict({n: pa.array(c, pa.int32() if n == "piece" else pa.int64()) for n, c in zip(names, cols)})

    return docs.select("doc_id", "text").mapInArrow(cut, _PIECE)


def _packer(capacity: int, again: bool):
    """Packs one group; when ``again``, keeps the bins that came unless fewer are found."""

    def packed(table):
        worker_kept(("packer",), bool)  # the encoder of the stage before goes, with its memory
        table = table.sort_by([("length", "descending"), ("uid", "ascending")])
        lengths = table["length"].to_numpy()
        bins, offsets, fills = best_fit_decreasing(lengths, capacity)
        gap = len(fills) - lower_bound(lengths, capacity)
        if again:
            olds = table["grp"].to_numpy(), table["bin"].to_numpy()
            old = {k: n for n, k in enumerate(dict.fromkeys(zip(*(x.tolist() for x in olds))))}
            if len(old) <= len(fills):
                bins = np.array([old[k] for k in zip(*(x.tolist() for x in olds))], np.int64)
                offsets = table["offset"].to_numpy()
                fills = np.bincount(bins, lengths).astype(np.int64)
                gap = len(fills) - lower_bound(lengths, capacity)
        group = table["to"].to_numpy()
        out = {n: table[n].combine_chunks() for n in ("uid", "doc_id", "piece", "start", "length", "ids_crc32")}
        out |= {"grp": pa.array(group), "bin": pa.array(bins), "offset": pa.array(offsets), "fill": pa.array(fills[bins]), "gap": pa.array(np.full(len(bins), gap)), "low": pa.array(np.full(len(bins), int(fills.min(initial=capacity))))}
        return pa.Table.from_pydict(out)

    return packed


def pack(pieces: DataFrame, capacity: int = CAPACITY, group: int = GROUP, rounds: int | None = None) -> DataFrame:
    """Pieces with sequence_id, offset, and for their group the gap between bins and bound when it was last packed.

    Groups exchange pieces until every group is certified, or a round saves no sequence (or for so many ``rounds``); gaps that stay open
    are in the result.

    Groups are dealt by a hash of a number that is unique to a row, so repeated ids and rows spread evenly. Pieces of full length
    need no packing. Each round is written before the next reads it. An empty table gives an empty result.
    """
    pieces = materialize(pieces, "pieces")
    full = pieces.filter(F.col("length") == capacity).select("*", F.lit(-1).cast("long").alias("grp"), F.col("uid").alias("bin"), F.lit(0).cast("long").alias("offset"), F.col("length").alias("fill"), F.lit(0).cast("long").alias("gap"), F.lit(capacity).cast("long").alias("low"))
    rest = pieces.filter(F.col("length") < capacity)
    n = rest.count()
    groups = max(1, -(-n // group))
    key = F.pmod(F.xxhash64("uid"), F.lit(groups))
    now = materialize(rest.withColumn("to", key).groupBy("to").applyInArrow(_packer(capacity, False), _PACKED), "packed-0")
    done, base = [full], groups
    r, bins = 0, F.count_distinct(F.struct("grp", "bin"))
    while groups > 1 and (rounds is None or r < rounds):
        r += 1
        moves = (F.col("fill") < capacity) & ((F.col("gap") > 0) | (F.col("fill") == F.col("low")))
        marked = now.withColumn("moves", moves)
        pool = marked.filter("moves").drop("moves")
        m, before, open_ = pool.agg(F.count("*"), bins, F.coalesce(F.max("gap"), F.lit(0))).first()
        if not m or not open_:
            break
        groups = max(1, -(-m // group))
        pool = pool.withColumn("to", F.lit(base) + F.pmod(F.xxhash64("grp", "bin", F.lit(r)), F.lit(groups)))
        base += groups
        repacked = materialize(pool.groupBy("to").applyInArrow(_packer(capacity, True), _PACKED), f"packed-{r}")
        done.append(marked.filter("not moves").drop("moves"))
        now = repacked
        if now.agg(bins).first()[0] >= before:
            break
    out = now
    for d in done:
        out = out.unionByName(d)
    # a sequence is a group's bin; full pieces have group -1 and their own number
    sequence = F.when(F.col("grp") < 0, F.lit(-1) - F.col("uid")).otherwise(F.col("grp") * (1 << 24) + F.col("bin"))
    return out.select("doc_id", "piece", "start", "length", "ids_crc32", sequence.alias("sequence_id"), "offset", "gap")


def pack_documents(docs: DataFrame, tokenizer: str, kind: str = "word", capacity: int = CAPACITY) -> DataFrame:
    return pack(cut_pieces(docs, tokenizer, kind, capacity), capacity)
