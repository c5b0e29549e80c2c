"""Quality classifier: hashed word n-grams, logistic regression learnt with follow-the-regularised-leader updates."""

from __future__ import annotations

import re
import zlib
from operator import eq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from graphsieve.functions.storage import discard
from graphsieve.llm.common import id_crc, materialize, worker_kept

BITS = 18
#: About so many labelled rows are learnt from at most: a share of the hashes of their ids.
MAX_TRAINING_ROWS = 6_000
THRESHOLD = 0.7
REPEAT = 0  # the feature of a repeated word

_SPLIT = re.compile(r"(\w*)(.*)", re.S)


def _word_codes(word: str) -> tuple[int, int]:
    """A white-space word as two hashed tokens: its letters in lower case, and its case with the marks behind it."""
    head, marks = _SPLIT.match(word).groups()
    shape = "upper" if len(head) > 1 and head.isupper() else "title" if head[:1].isupper() else "digits" if head.isdigit() else "lower" if head else "marks"
    return zlib.crc32(head.lower().encode()), zlib.crc32(f"\x01{shape}\x02{marks}".encode())


class Hasher:
    """Sparse features of a text: counts of n-grams (n = 1, 2) of its words and of their styles, each hashed to BITS bits, of Euclidean length 1."""

    LIMIT = 400_000

    def __init__(self):
        self.codes: dict[str, bytes] = {}

    def features(self, text: str) -> tuple[np.ndarray, np.ndarray]:
        words, codes = text.split(), self.codes
        new = {w for w in words if w not in codes}
        if len(codes) + len(new) > self.LIMIT:
            codes.clear()
            new = set(words)
        codes.update((w, np.array(_word_codes(w), "<u4").tobytes()) for w in new)
        h = np.frombuffer(b"".join(map(codes.__getitem__, words)), "<u4").reshape(-1, 2)
        pairs = h[:-1] * np.uint32(2654435761) + h[1:]  # a word and the next one; a style and the next one
        mixed = np.concatenate([(h * np.uint32(2246822519)).ravel(), (pairs * np.uint32(3266489917)).ravel()]) >> np.uint32(32 - BITS)
        again = sum(map(eq, words, words[1:]))  # pairs of a word with itself are one feature, whatever the word
        if again:
            mixed = np.append(mixed, np.full(again, REPEAT, np.uint32))
        counts = np.bincount(mixed) if mixed.size > 4096 else None
        index, n = (np.flatnonzero(counts), counts[counts > 0]) if counts is not None else np.unique(mixed, return_counts=True)
        value = np.sqrt(n).astype(np.float32)
        return index.astype(np.int32), value / max(1e-9, float(np.sqrt((value * value).sum())))


class Ftrl:
    """Per-coordinate follow-the-regularised-leader (proximal) logistic regression with a bias."""

    def __init__(self, alpha: float = 0.5, beta: float = 1.0, l1: float = 0.02, l2: float = 0.1):
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.z, self.n = np.zeros((1 << BITS) + 1), np.zeros((1 << BITS) + 1)

    def weights(self, index=slice(None)) -> np.ndarray:
        z, n = self.z[index], self.n[index]
        return np.where(np.abs(z) <= self.l1, 0.0, (np.sign(z) * self.l1 - z) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2))

    def learn(self, index: np.ndarray, value: np.ndarray, label: float, weight: float = 1.0) -> None:
        index, value = np.append(index, 1 << BITS), np.append(value, 0.3)
        w = self.weights(index)
        g = (1 / (1 + np.exp(-np.clip(w @ value, -30, 30))) - label) * value * weight
        sigma = (np.sqrt(self.n[index] + g * g) - np.sqrt(self.n[index])) / self.alpha
        self.z[index] += g - sigma * w
        self.n[index] += g * g


def train_quality(docs: DataFrame, labels: DataFrame, max_rows: int = MAX_TRAINING_ROWS, epochs: int = 4, seed: int = 7) -> np.ndarray:
    """Weights learnt from about ``max_rows`` labelled rows at most, whose crc32(doc_id) mod 4 is not 2.

    A share of the hashes of doc_id is taken that makes so many, so the sample is the same on every run. The learner is a task; the driver passes its
    2 * 2**18 numbers from epoch to epoch. Labels that are null or not 0 or 1 are
    left out; if an id has several labels, the smallest counts. Without labels all weights are 0 and every score 0.5.
    """
    known = labels.filter(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull() & (id_crc() % 4 != 2)).groupBy("doc_id").agg(F.min("quality").alias("quality"))
    share = min(1.0, max_rows / max(1, known.count()))
    chosen = known.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 40)) < F.lit(int(share * (1 << 40))))
    rows = docs.select("doc_id", "text").join(F.broadcast(chosen), "doc_id")  # at most max_rows pairs of numbers

    def featured(batches):
        hasher = worker_kept("hasher", Hasher)
        for batch in batches:
            found = [hasher.features(t or "") for t in batch["text"].to_pylist()]
            yield pa.RecordBatch.from_pydict({"doc_id": batch["doc_id"], "quality": batch["quality"].cast(pa.int32()), "index": pa.array([i.tobytes() for i, _ in found], pa.binary()), "value": pa.array([v.astype("<f4").tobytes() for _, v in found], pa.binary())})

    schema = "doc_id long, quality int, index binary, value binary"
    featured_rows = rows.select("doc_id", "quality", "text").mapInArrow(featured, schema)
    sample = materialize(featured_rows.withColumn("_first", F.row_number().over(Window.partitionBy("doc_id").orderBy("index", "value"))).filter("_first = 1").drop("_first"), "quality-sample")
    n, positive = sample.agg(F.count("*"), F.coalesce(F.sum("quality"), F.lit(0))).first()
    weigh = {1: 1.0, 0: min(4.0, max(1.0, (positive / max(1, n - positive)) ** 0.5))}
    model = Ftrl()
    for epoch in range(epochs if n else 0):
        start = model.z, model.n

        def learnt(batches, start=start):
            """One pass in the order of a hash, a batch at a time: memory holds the model and a batch, whatever the texts' lengths."""
            own = Ftrl()
            own.z, own.n = (x.copy() for x in start)
            for batch in batches:
                for index, value, label in zip(*(batch[c].to_pylist() for c in ("index", "value", "quality"))):
                    own.learn(np.frombuffer(index, "<i4"), np.frombuffer(value, "<f4").astype(np.float64), label, weigh[label])
            yield pa.RecordBatch.from_pydict({"z": pa.array([own.z.tobytes()], pa.binary()), "n": pa.array([own.n.tobytes()], pa.binary())})

        order = F.xxhash64("doc_id", F.lit(seed + epoch))
        found = sample.repartition(1).sortWithinPartitions(order, "doc_id").select("quality", "index", "value").mapInArrow(learnt, "z binary, n binary").collect()
        found = max(found, key=lambda r: np.frombuffer(r.n).sum())  # one task with rows; others, if any, returned what they were given
        model.z, model.n = (np.frombuffer(x).copy() for x in (found.z, found.n))
    discard(sample)
    return model.weights().astype(np.float32)


def score_quality(docs: DataFrame, weights: np.ndarray, threshold: float = THRESHOLD) -> DataFrame:
    """``docs`` with ``score`` (0 to 1) and ``predicted`` (1 from ``threshold`` on): sparse dot products with the weights.

    Null and empty texts have no features and get the score of the bias. The model is 2**18 numbers, whatever the input.
    Input columns named score or predicted are replaced.
    """
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(weights)
    docs = docs.drop("score", "predicted")

    def scored(batches):
        hasher = worker_kept("hasher", Hasher)
        w = shared.value
        for batch in batches:
            out = []
            for t in batch["text"].to_pylist():
                index, value = hasher.features(t or "")
                out.append(float(w[index] @ value) + 0.3 * float(w[-1]))
            s = 1 / (1 + np.exp(-np.clip(np.array(out, np.float64), -30, 30)))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(s), pa.array((s >= threshold).astype(np.int32))], names=[*batch.schema.names, "score", "predicted"])

    schema = T.StructType([*docs.schema.fields, T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType())])
    return docs.mapInArrow(scored, schema)


def quality_scores(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """Learn and score; ``held_out`` marks the rows never learnt from. Ids, languages, sources and labels enter no score."""
    weights = train_quality(docs, labels)
    return score_quality(docs.select("doc_id", (id_crc() % 4 == 2).alias("held_out"), "text"), weights, threshold).drop("text")
