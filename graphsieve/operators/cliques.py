"""Cliques without a table of wedges: triangles by blocks of three ranges of vertices, larger cliques from those that share their smallest vertex.

Wedges of a dense graph are many times its edges, and a join writes them all to the shuffle. Here the edges between three ranges meet in one
task, which makes the wedges a part at a time and keeps those that close. An edge goes once to every third range that has edges to both of its own.
What is dealt goes as packs, a row for many edges or cliques of one place.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Edges that a task holds, in a graph whose edges join all ranges alike; wedges that are made at once.
BLOCK, WEDGES = 1_000_000, 4_000_000
#: Places that cliques are dealt to by their smallest vertex; cliques of a pack's part and of a task's step.
PLACES, PACKED = 4096, 250_000


def closed(p: np.ndarray, a: tuple, b: tuple, c: tuple, wedges: int = WEDGES):
    """``(rows of a, last vertices)``, part by part: pairs ``x, y`` of ``a`` and ``y, z`` of ``b`` of the same prefix whose ``x, z`` is in ``c``.

    Each is ``(prefix, from, to)`` of numbers below ``p[0]`` (prefixes) and ``p[1]`` (vertices).
    """
    n = int(p[1])
    (ap, ax, ay), (bp, by, bz), (cp, cx, cz) = a, b, c
    if int(p[0]) * n * n < 1 << 62:
        held, code = np.sort((cp * n + cx) * n + cz), None
    else:  # pairs are numbered first
        code = np.unique(cp * n + cx)
        held = np.sort(np.searchsorted(code, cp * n + cx) * n + cz)
    order = np.lexsort((bz, bp * n + by))
    start_of, z_of = (bp * n + by)[order], bz[order]
    rows = np.lexsort((ay, ap * n + ax))  # neighbouring queries, neighbouring answers
    key = (ap * n + ay)[rows]
    at, upto = np.searchsorted(start_of, key), np.searchsorted(start_of, key, "right")
    some = upto > at
    rows, at, many = rows[some], at[some], (upto - at)[some]
    if not len(rows) or not len(held):
        return
    own = (ap * n + ax)[rows]
    if code is not None:
        place = np.minimum(np.searchsorted(code, own), len(code) - 1)
        there = code[place] == own
        rows, at, many, own = rows[there], at[there], many[there], place[there]
    ends = np.cumsum(many)
    first = 0
    while first < len(rows):
        before = int(ends[first - 1]) if first else 0
        last = max(first + 1, int(np.searchsorted(ends, before + wedges, "right")))
        m = many[first:last]
        k = np.repeat(np.arange(first, last), m)
        z = z_of[np.arange(int(m.sum())) - np.repeat(np.cumsum(m) - m, m) + at[k]]
        wanted = own[k] * n + z
        found = np.searchsorted(held, wanted)
        found[found == len(held)] = 0
        ok = held[found] == wanted
        yield rows[k[ok]], z[ok]
        first = last


def _by(batches, column: str):
    """Columns of the rows of one value of ``column`` after another; the rows come ordered by it."""
    held, at = [], None
    for batch in batches:
        cols = {c: batch[c].to_numpy(zero_copy_only=False) for c in batch.schema.names}
        values = cols[column]
        if not len(values):
            continue
        cuts = [0, *(np.flatnonzero(values[1:] != values[:-1]) + 1).tolist(), len(values)]
        for i, j in zip(cuts, cuts[1:]):
            if values[i] != at and held:
                yield {c: np.concatenate([h[c] for h in held]) for c in cols}
                held = []
            at = values[i]
            held.append({c: v[i:j] for c, v in cols.items()})
    if held:
        yield {c: np.concatenate([h[c] for h in held]) for c in held[0]}


def _batches(columns: list[np.ndarray], size: int = 1 << 18):
    for k in range(0, len(columns[0]), size):
        yield pa.RecordBatch.from_arrays([pa.array(c[k : k + size], pa.int64()) for c in columns], names=[f"c{q}" for q in range(len(columns))])


def triangles(edges: DataFrame, block: int = BLOCK, packed: bool = False) -> DataFrame:
    """Rows ``(c0 < c1 < c2)`` of the edges ``(src, dst)``, which are simple and both ways. ``packed``: packs of them, by the smallest vertex."""
    up = edges.filter("src < dst").select("src", "dst")
    n = up.count()
    ranges = int(np.ceil(np.sqrt(6 * n / block))) if n else 1
    bounds = sorted(set(edges.approxQuantile("src", [k / ranges for k in range(1, ranges)], 0.1 / ranges))) if ranges > 1 else []
    bounds = np.array(bounds, np.int64)
    ranges = len(bounds) + 1

    def between(batch):
        """The ranges of both ends."""
        return tuple(np.searchsorted(bounds, batch[c].to_numpy(zero_copy_only=False)) for c in ("src", "dst"))

    def met(batches):
        for batch in batches:
            a, b = between(batch)
            yield pa.RecordBatch.from_pydict({"pair": np.unique(a * ranges + b)})

    there = {r[0] for r in up.mapInArrow(met, "pair long").distinct().collect()}  # at most a row for every two ranges
    has = np.zeros((ranges, ranges), bool)
    for x in there:
        has[x // ranges, x % ranges] = has[x % ranges, x // ranges] = True
    # the third ranges of every two, as one list with their starts
    thirds = [np.flatnonzero(has[a] & has[b]) if a * ranges + b in there else np.empty(0, np.int64) for a in range(ranges) for b in range(ranges)]
    many = np.array([len(x) for x in thirds])
    start, thirds = np.cumsum(many) - many, np.concatenate(thirds)

    def deal(batches):
        for batch in batches:
            a, b = between(batch)
            m = many[a * ranges + b]
            e = np.repeat(np.arange(len(a)), m)
            c = thirds[np.arange(int(m.sum())) - np.repeat(np.cumsum(m) - m, m) + start[(a * ranges + b)[e]]]
            a, b = a[e], b[e]
            low, high = np.minimum(a, c), np.maximum(b, c)
            place = (low * ranges + (a + b + c - low - high)) * ranges + high
            yield from _packs(place, [batch[x].to_numpy(zero_copy_only=False)[e] for x in ("src", "dst")])

    def found(batches):
        for place, (src, dst) in _unpacked(batches, 2):
            own = place // ranges // ranges, place // ranges % ranges, place % ranges
            i, j = np.searchsorted(bounds, src), np.searchsorted(bounds, dst)
            ids, x = np.unique(np.concatenate([src, dst]), return_inverse=True)
            s, d, none = x[: len(x) // 2], x[len(x) // 2 :], np.zeros(len(x) // 2, np.int64)
            part = [(none[w], s[w], d[w]) for w in [(i == own[u]) & (j == own[v]) for u, v in ((0, 1), (1, 2), (0, 2))]]
            for rows, z in closed((1, len(ids)), *part):
                yield [ids[part[0][1][rows]], ids[part[0][2][rows]], ids[z]]

    tasks = max(int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(10_000, int(many.sum())))
    dealt = up.mapInArrow(deal, PACK).repartition(tasks, "place").sortWithinPartitions("place")
    return _listed(dealt, found, 3, packed)


def grow(cliques: DataFrame) -> DataFrame:
    """Cliques of one vertex more than ``(c0 < c1 < ...)``, of three or more: two that differ in their last but one vertex, and the one that closes."""
    names = cliques.columns
    packs = cliques.mapInArrow(lambda batches: _packed([b[c].to_numpy(zero_copy_only=False) for c in names] for b in batches), PACK)
    return _grown(packs, len(names))


def listed(edges: DataFrame, k: int) -> DataFrame:
    """Rows ``(c0 < c1 < ...)`` of all cliques of ``k`` vertices, three or more, of the edges ``(src, dst)``, which are simple and both ways."""
    out = triangles(edges, packed=k > 3)
    for q in range(3, k):
        out = _grown(out, q, q < k - 1)
    return out


def _grown(packs: DataFrame, k: int, packed: bool = False) -> DataFrame:
    def found(batches):
        for cols in _together(_unpacked(batches, k)):
            ids, flat = np.unique(np.concatenate(cols), return_inverse=True)
            cols = flat.reshape(k, -1)
            prefix = np.zeros(cols.shape[1], np.int64)
            for c in cols[: k - 2]:
                _, prefix = np.unique(prefix * len(ids) + c, return_inverse=True)
            part = prefix, cols[k - 2], cols[k - 1]
            for rows, z in closed((int(prefix.max()) + 1, len(ids)), part, part, part):
                yield [*(ids[c[rows]] for c in cols), ids[z]]

    return _listed(packs.repartition("place").sortWithinPartitions("place"), found, k + 1, packed)


def _listed(dealt: DataFrame, found, k: int, packed: bool) -> DataFrame:
    """What ``found`` makes of the packs, as rows or as packs by the smallest vertex."""
    if packed:
        return dealt.mapInArrow(lambda batches: _packed(found(batches)), PACK)
    return dealt.mapInArrow(lambda batches: (b for cols in found(batches) for b in _batches(cols)), ", ".join(f"c{q} long" for q in range(k)))


#: Rows of one place: their columns' numbers, a row after another.
PACK = "place long, ends binary"


def _packs(place: np.ndarray, columns: list[np.ndarray]):
    """One pack of every place."""
    if not len(place):
        return
    order = np.argsort(place, kind="stable")
    place, ends = place[order], np.stack(columns, 1)[order].astype("<i8")
    first = np.flatnonzero(np.r_[True, place[1:] != place[:-1]])
    at = np.r_[first, len(place)] * (8 * len(columns))
    held = pa.Array.from_buffers(pa.binary(), len(first), [None, pa.py_buffer(at.astype(np.int32).tobytes()), pa.py_buffer(ends.tobytes())])
    yield pa.RecordBatch.from_arrays([pa.array(place[first], pa.int64()), held], names=["place", "ends"])


def _packed(parts):
    """Packs of cliques, by their smallest vertex; small parts are put together, large ones cut."""
    for cols in _together((None, cols) for cols in parts):
        for k in range(0, len(cols[0]), 4 * PACKED):
            some = [c[k : k + 4 * PACKED] for c in cols]
            mixed = some[0] * 0x9E3779B1
            yield from _packs((mixed ^ mixed >> 33) % PLACES, some)


def _together(parts):
    """Columns of one part after another, joined until they are ``PACKED`` rows or more."""
    held, n = [], 0
    for _, cols in parts:
        held.append(cols)
        n += len(cols[0])
        if n >= PACKED:
            yield [np.concatenate(c) for c in zip(*held)]
            held, n = [], 0
    if n:
        yield [np.concatenate(c) for c in zip(*held)]


def _unpacked(batches, k: int):
    """``(place, columns)`` of one place after another; packs come ordered by it."""
    held, at = [], None
    told = lambda: (at, list(np.frombuffer(b"".join(held), "<i8").reshape(-1, k).T.copy()))
    for batch in batches:
        for place, ends in zip(batch["place"].to_pylist(), batch["ends"].to_pylist()):
            if place != at and held:
                yield told()
                held = []
            at = place
            held.append(ends)
    if held:
        yield told()
