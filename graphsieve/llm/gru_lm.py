"""Language-model scores by a gated recurrent network in numpy.

Words are the commonest of the corpus and one stand-in for all others. Output is factored by classes of about equal mass: the class,
then the word within it, both from the recurrent state. Training is truncated backpropagation through time over all
training documents (dealt to trainers whose parameters are averaged round by round); scoring carries the state across windows to the
document's end. A word outside the vocabulary is the stand-in times its share among such words, from counts over all training documents,
so scores are log-likelihoods of whole texts over an open vocabulary. The counts also give the unigram base score.
"""

from __future__ import annotations

import math
import os
from collections import Counter
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from graphsieve.llm.common import id_crc, materialize, utf8

WORDS, CLASSES, HIDDEN = 2048, 32, 16
#: Words whose counts are held by every task; the rest are joined.
HELD_WORDS = 150_000
ROUNDS = 2
#: Tokens of a trainer, at least, before there are more trainers; parameters are averaged in parts of PART numbers.
TRAINER_TOKENS, PART = 500_000, 8192
LANES, STEPS = 256, 32
#: Lanes and rate of training.
TRAIN_LANES, RATE = 128, 0.2
SMOOTH = 0.1
END = b""  # no word is empty


def tokens_of(text: bytes) -> list[bytes]:
    """Words of a text with A-Z in lower case, and the end."""
    return [*text.lower().split(), END]


class Vocabulary:
    """The commonest words by class: ids are in order of class. ``unk`` stands for all other words."""

    def __init__(self, counts: list[tuple[bytes, int]], total: int, words: int = WORDS, classes: int = CLASSES):
        top = counts[: words - 1]
        mass = [n for _, n in top]
        rest = max(1, total - sum(mass))
        entries = sorted([*zip([w for w, _ in top], mass), (None, rest)], key=lambda x: (-x[1], x[0] is None, x[0] or b""))
        self.ids, self.starts, seen, whole = {}, [0], 0.0, float(sum(mass) + rest)
        for k, (w, n) in enumerate(entries):
            if seen >= len(self.starts) / classes and k > self.starts[-1] and len(self.starts) < classes:
                self.starts.append(k)
            if w is None:
                self.unk = k
            else:
                self.ids[w] = k
            seen += n / whole
        self.mass = np.array([n for _, n in entries], np.float64) / whole
        self.ends = [*self.starts[1:], len(entries)]
        self.size = len(entries)
        self.class_of = np.repeat(np.arange(len(self.starts)), np.diff([*self.starts, len(entries)]))


class Gru:
    """Parameters, one step of which is shared by training and scoring."""

    NAMES = ("x", "u", "b", "wc", "bc", "wo", "bo")

    def __init__(self, vocabulary: Vocabulary, hidden: int = HIDDEN, seed: int = 1):
        v, h, c, rng = vocabulary.size, hidden, len(vocabulary.starts), np.random.default_rng(seed)
        class_mass = np.add.reduceat(vocabulary.mass, vocabulary.starts)
        self.v, self.h = vocabulary, h
        self.p = {
            "x": rng.normal(0, 0.3, (v, 3 * h)), "u": rng.normal(0, 0.6 / math.sqrt(h), (h, 3 * h)), "b": np.zeros(3 * h),
            "wc": np.zeros((h, c)), "bc": np.log(class_mass), "wo": np.zeros((h, v)), "bo": np.log(vocabulary.mass / class_mass[vocabulary.class_of]),
        }
        self.p = {k: x.astype(np.float32) for k, x in self.p.items()}

    def flat(self) -> np.ndarray:
        return np.concatenate([self.p[k].ravel() for k in self.NAMES])

    def load(self, flat: np.ndarray) -> Gru:
        at = 0
        for k in self.NAMES:
            n = self.p[k].size
            self.p[k] = flat[at : at + n].reshape(self.p[k].shape).astype(np.float32).copy()
            at += n
        return self

    def forward(self, inputs: np.ndarray, fresh: np.ndarray, state: np.ndarray, keep: bool):
        """Run (steps, lanes) inputs; ``fresh`` marks where a document starts (state 0, no input word: -1)."""
        h = self.h
        table = np.concatenate([self.p["x"] + self.p["b"], self.p["b"][None]])  # its last row, -1, is no word
        gates_in = np.take(table, inputs, axis=0)
        u_zr, u_n = np.ascontiguousarray(self.p["u"][:, : 2 * h]), np.ascontiguousarray(self.p["u"][:, 2 * h :])
        states, kept = np.empty((len(inputs), inputs.shape[1], h), np.float32), []
        starts = fresh.any(1)
        for t in range(len(inputs)):
            if starts[t]:
                state = np.where(fresh[t][:, None], np.float32(0), state)
            zr = state @ u_zr
            zr += gates_in[t, :, : 2 * h]
            np.negative(zr, out=zr)
            np.exp(zr, out=zr)
            zr += 1
            np.reciprocal(zr, out=zr)
            z, r = zr[:, :h], zr[:, h:]
            rs = r * state
            n = rs @ u_n
            n += gates_in[t, :, 2 * h :]
            np.tanh(n, out=n)
            new = state - n
            new *= z
            new += n
            if keep:
                kept.append((state, z, r, n, rs))
            states[t] = state = new
        return states, kept, state

    def _exponents(self, logits: np.ndarray, tame: bool) -> np.ndarray:
        """Exponentials of logits, row-wise moved into range where the weights would let them out of it. Changes the logits."""
        if not tame:
            logits -= logits.max(1, keepdims=True)
        return np.exp(logits)

    def output(self, flat_states: np.ndarray, targets: np.ndarray, grads: dict | None = None, weight: np.ndarray | None = None):
        """Log-probabilities of targets; with grads, also the gradient of the states (sum of losses)."""
        v, p = self.v, self.p
        # states are within -1 and 1, so weights bound the logits; single precision holds exponentials up to 88
        tame = [float((np.abs(p[w]).sum(0) + np.abs(p[b])).max()) < 60 for w, b in (("wc", "bc"), ("wo", "bo"))]
        cls = np.take(v.class_of, targets)
        logits = flat_states @ p["wc"]
        logits += p["bc"]
        e = self._exponents(logits, tame[0])
        total = e @ np.ones(e.shape[1], np.float32)
        rows = np.arange(len(targets))
        out = logits[rows, cls] - np.log(total)
        d_state = None
        if grads is not None:
            d = e / total[:, None]
            d[rows, cls] -= 1
            d *= weight[:, None]
            grads["wc"] += flat_states.T @ d
            grads["bc"] += d.sum(0)
            d_state = d @ p["wc"].T
        order = np.argsort(cls.astype(np.int16), kind="stable")
        bounds = np.searchsorted(cls[order], np.arange(len(v.starts) + 1))
        by_class, hit = np.take(flat_states, order, axis=0), np.take(targets, order)
        found, d_by_class = np.zeros(len(order), np.float32), None if grads is None else np.zeros_like(by_class)
        for c, (a, b) in enumerate(zip(v.starts, v.ends)):
            lo, hi = bounds[c], bounds[c + 1]
            if lo == hi or b - a == 1:
                continue
            s = by_class[lo:hi]
            logits = s @ p["wo"][:, a:b]
            logits += p["bo"][a:b]
            e = self._exponents(logits, tame[1])
            total = e @ np.ones(b - a, np.float32)
            k, at = rows[: hi - lo], hit[lo:hi] - a
            found[lo:hi] = logits[k, at] - np.log(total)
            if grads is not None:
                e /= total[:, None]
                e[k, at] -= 1
                e *= np.take(weight, order[lo:hi])[:, None]
                grads["wo"][:, a:b] += s.T @ e
                grads["bo"][a:b] += e.sum(0)
                d_by_class[lo:hi] = e @ p["wo"][:, a:b].T
        out[order] += found
        if grads is not None:
            d_state[order] += d_by_class
        return out, d_state

    def gradients(self, inputs, fresh, targets, valid, state) -> tuple[dict, np.ndarray, np.ndarray]:
        """Gradients of one window's mean loss, truncated at its start, the rows of "x" that have one, and the state for the next window."""
        h, p = self.h, self.p
        states, kept, last = self.forward(inputs, fresh, state, True)
        grads = {k: np.zeros_like(p[k]) for k in self.NAMES if k != "x"}
        weight = (valid / max(1, valid.sum())).astype(np.float32).ravel()
        _, d_out = self.output(states.reshape(-1, h), targets.ravel(), grads, weight)
        d_out, d_next = d_out.reshape(states.shape), np.zeros_like(last)
        d_gates = np.empty((len(inputs), inputs.shape[1], 3 * h), np.float32)
        befores, resets, starts = np.empty_like(states), np.empty_like(states), fresh.any(1)
        u_zr_t, u_n_t = np.ascontiguousarray(p["u"][:, : 2 * h].T), np.ascontiguousarray(p["u"][:, 2 * h :].T)
        for t in range(len(inputs) - 1, -1, -1):
            s, z, r, n, rs = kept[t]
            d = d_out[t] + d_next
            d_n = d * (1 - z) * (1 - n * n)
            d_rs = d_n @ u_n_t
            d_z, d_r = d * (s - n) * z * (1 - z), d_rs * s * r * (1 - r)
            here = d_gates[t]
            here[:, :h], here[:, h : 2 * h], here[:, 2 * h :] = d_z, d_r, d_n
            befores[t], resets[t] = s, rs
            d_next = d * z + d_rs * r + here[:, : 2 * h] @ u_zr_t
            if starts[t]:
                d_next[fresh[t]] = 0
        flat, words = d_gates.reshape(-1, 3 * h), inputs.ravel()
        grads["u"][:, : 2 * h] = befores.reshape(-1, h).T @ flat[:, : 2 * h]
        grads["u"][:, 2 * h :] = resets.reshape(-1, h).T @ flat[:, 2 * h :]
        grads["b"] += flat.sum(0)
        known = np.flatnonzero(words >= 0)
        order = known[np.argsort(words[known].astype(np.int16) if self.v.size < 1 << 15 else words[known], kind="stable")]
        distinct = np.empty(0, np.int64)
        grads["x"] = np.empty((0, 3 * h), np.float32)
        if order.size:
            distinct, first = np.unique(words[order], return_index=True)
            grads["x"] = np.add.reduceat(np.take(flat, order, axis=0), first)
        return grads, distinct, last

    def learn(self, inputs, fresh, targets, valid, state, sums: dict, rate: float):
        """One window of truncated backpropagation (adaptive gradient steps); returns the state for the next window."""
        grads, distinct, last = self.gradients(inputs, fresh, targets, valid, state)
        norm = math.sqrt(sum(float((g * g).sum()) for g in grads.values()))
        scale = np.float32(min(1.0, 1.0 / max(norm, 1e-9)))
        for k, g in grads.items():
            g = g * scale
            at = distinct if k == "x" else slice(None)
            sums[k][at] += g * g
            self.p[k][at] -= np.float32(rate) * g / (np.sqrt(sums[k][at]) + np.float32(1e-4))
        return last


#: Steps that are laid out at a time: memory follows lanes and BLOCK, however long a document is.
BLOCK = 4096


def lanes_of(documents: list[np.ndarray], lanes: int, steps: int, block: int = BLOCK):
    """Documents end to end in lanes of about equal lengths, a window of ``steps`` at a time: which lanes still run, and their inputs, targets,
    starts and owners, each (steps, lanes). Lanes that have ended take no further part."""
    lanes = max(1, min(lanes, len(documents)))
    rows: list[list[int]] = [[] for _ in range(lanes)]
    import heapq

    heap = [(0, k) for k in range(lanes)]
    for d in sorted(range(len(documents)), key=lambda d: -len(documents[d])):
        n, k = heapq.heappop(heap)
        rows[k].append(d)
        heapq.heappush(heap, (n + len(documents[d]), k))
    length = np.zeros(lanes, np.int64)
    for n, k in heap:
        length[k] = n
    at_document, at_token = [0] * lanes, [0] * lanes
    running = np.arange(lanes)
    for begin in range(0, int(length.max(initial=0)), block):
        running = running[length[running] > begin]
        size = min(block, int(length[running].max()) - begin)
        targets, inputs = np.zeros((size, len(running)), np.int32), np.full((size, len(running)), -1, np.int32)
        fresh, owner = np.zeros((size, len(running)), bool), np.full((size, len(running)), -1, np.int32)
        for column, k in enumerate(running.tolist()):
            at = 0
            while at < size and at_document[k] < len(rows[k]):
                d, a = rows[k][at_document[k]], at_token[k]
                ids = documents[d]
                n = min(size - at, len(ids) - a)
                targets[at : at + n, column] = ids[a : a + n]
                inputs[at + (a == 0) : at + n, column] = ids[max(0, a - 1) : a + n - 1]
                fresh[at, column] |= a == 0
                owner[at : at + n, column] = d
                at, at_token[k] = at + n, a + n
                if at_token[k] == len(ids):
                    at_document[k], at_token[k] = at_document[k] + 1, 0
        for t in range(0, size, steps):
            here = slice(t, t + steps)
            live = np.flatnonzero(length[running] > begin + t)
            if len(live) == len(running):
                yield running, inputs[here], targets[here], fresh[here], owner[here]
            else:
                yield running[live], inputs[here, live], targets[here, live], fresh[here, live], owner[here, live]


def score_documents(model: Gru, documents: list[np.ndarray], lanes: int = LANES, steps: int = 64) -> np.ndarray:
    """Natural log-likelihood of every document (ids with the end); the state runs through all its windows."""
    scores = np.zeros(len(documents))
    state = np.zeros((lanes, model.h), np.float32)
    for running, inputs, targets, fresh, owner in lanes_of(documents, lanes, steps):
        states, _, last = model.forward(inputs, fresh, state[running], False)
        state[running] = last
        flat = owner.ravel()
        here = flat >= 0
        if here.all():
            logp, _ = model.output(states.reshape(-1, model.h), targets.ravel())
        else:
            flat = flat[here]
            logp, _ = model.output(states.reshape(-1, model.h)[here], targets.ravel()[here])
        scores += np.bincount(flat, logp.astype(np.float64), len(documents))
    return scores


def train_documents(model: Gru, documents: list[np.ndarray], lanes: int = TRAIN_LANES, steps: int = STEPS, rate: float = RATE) -> int:
    """One pass of truncated backpropagation over the documents; returns the number of their tokens."""
    state, sums = np.zeros((lanes, model.h), np.float32), {k: np.zeros_like(x) for k, x in model.p.items()}
    for running, inputs, targets, fresh, owner in lanes_of(documents, lanes, steps):
        state[running] = model.learn(inputs, fresh, targets, owner >= 0, state[running], sums, rate)
    return sum(map(len, documents))


def _one_thread() -> None:
    for k in ("OMP_NUM_THREADS", "OPENBLAS_NUM_THREADS", "MKL_NUM_THREADS"):
        os.environ.setdefault(k, "1")


def word_counts(training: DataFrame) -> DataFrame:
    """Rows ``(word, n)`` over all tokens of all training texts. Tasks add up their own words before the shuffle."""

    def counted(batches):
        seen: Counter = Counter()

        def flushed():
            return pa.RecordBatch.from_pydict({"word": pa.array(list(seen), pa.binary()), "n": pa.array(list(seen.values()), pa.int64())})

        for batch in batches:
            for text in utf8(batch["text"]):
                seen.update(text.lower().split())
                seen[END] += 1
                if len(seen) > 400_000:
                    yield flushed()
                    seen.clear()
        yield flushed()

    return training.select("text").mapInArrow(counted, "word binary, n long").groupBy("word").agg(F.sum("n").alias("n"))


def _averaged(found: DataFrame) -> dict[int, tuple[int, np.ndarray]]:
    """Tokens and means of parts of parameters, weighted by tokens, from rows ``(trainer, part, tokens, p)``: summed on the cluster, part by part."""

    def summed(batches):
        part, weight, total = None, 0, 0.0
        for batch in batches:
            for k, n, p in zip(batch["part"].to_pylist(), batch["tokens"].to_pylist(), batch["p"]):
                if k != part:
                    if part is not None:
                        yield one(part, weight, total / weight)
                    part, weight, total = k, 0, 0.0
                weight, total = weight + n, total + np.frombuffer(p.as_py(), np.float32).astype(np.float64) * n
        if part is not None:
            yield one(part, weight, total / weight)

    def one(part, weight, mean):
        return pa.RecordBatch.from_pydict({"part": pa.array([part], pa.int32()), "tokens": pa.array([weight], pa.int64()), "p": pa.array([mean.astype(np.float32).tobytes()], pa.binary())})

    dealt = found.repartition("part").sortWithinPartitions("part", "trainer").drop("trainer")
    return {r.part: (r.tokens, np.frombuffer(r.p, np.float32)) for r in dealt.mapInArrow(summed, "part int, tokens long, p binary").collect()}  # one model, half a MB


def train(training: DataFrame, vocabulary: Vocabulary, tokens: int, rounds: int = ROUNDS, seed: int = 1) -> tuple[np.ndarray, int]:
    """Parameters after ``rounds`` of averaging, and the tokens learnt from. Every document is dealt to one trainer and one round; copies are spread.

    Trainers grow with ``tokens`` (those of all training texts), as far as the session's shuffle partitions. Their parameters are averaged on
    the cluster; the driver gets the mean alone.
    """
    spark = training.sparkSession
    trainers = max(1, min(tokens // TRAINER_TOKENS, int(spark.conf.get("spark.sql.shuffle.partitions"))))
    dealt = training.select("text", F.xxhash64(F.monotonically_increasing_id(), F.lit(seed)).alias("draw"))
    dealt = dealt.select("text", "draw", F.pmod(F.xxhash64("draw"), F.lit(rounds)).alias("round"))
    chosen = materialize(dealt.repartition(trainers, "draw").select("text", "round"), "lm-training")
    flat, seen = Gru(vocabulary, seed=seed).flat(), 0
    for r in range(rounds):
        held = spark.sparkContext.broadcast((vocabulary, flat))

        def learnt(batches):
            from pyspark import TaskContext

            _one_thread()
            v, start = held.value
            ids, unk, documents = v.ids.get, v.unk, []
            model, total = Gru(v).load(start), 0
            for batch in batches:
                documents += [np.fromiter(map(ids, words, repeat(unk)), np.int32, len(words)) for words in map(tokens_of, utf8(batch["text"]))]
                if sum(map(len, documents)) > 1_000_000:
                    total += train_documents(model, documents)
                    documents = []
            total += train_documents(model, documents)
            if total:
                p, trainer = model.flat(), TaskContext.get().partitionId()
                parts = [p[at : at + PART].tobytes() for at in range(0, len(p), PART)]
                n = len(parts)
                yield pa.RecordBatch.from_pydict({"trainer": pa.array([trainer] * n, pa.int32()), "part": pa.array(range(n), pa.int32()), "tokens": pa.array([total] * n, pa.int64()), "p": pa.array(parts, pa.binary())})

        part = chosen.filter(F.col("round") == r).select("text").coalesce(trainers)
        means = _averaged(part.mapInArrow(learnt, "trainer int, part int, tokens long, p binary"))
        if means:
            flat, seen = np.concatenate([means[k][1] for k in sorted(means)]), seen + means[0][0]
        held.unpersist()
    return flat, seen


def _commonest(lexicon: DataFrame, most: int) -> list[tuple[bytes, int]]:
    """All words of at least some count, the least one that leaves at most ``most``; commonest first, ties by word."""
    band = F.floor(F.log2("n") * 8).cast("int")
    bands = sorted(lexicon.groupBy(band.alias("band")).count().collect(), reverse=True)
    held, least = 0, None
    for b, n in bands:
        if held + n > most:
            break
        held, least = held + n, b
    if least is None:
        return []
    return sorted(((bytes(r.word), r.n) for r in lexicon.filter(band >= least).collect()), key=lambda x: (-x[1], x[0]))


def lm_scores(docs: DataFrame, held_words: int = HELD_WORDS) -> DataFrame:
    """One row per document: counts, the unigram base score and the model's log10 probability of the whole text.

    Learns from documents whose crc32(doc_id as text) mod 10 is not 0 (a null id counts as the empty text: held out). Null texts are empty:
    one token, the end. Without training documents, c and N are 0 and the model is uniform over its one class.
    """
    spark = docs.sparkSession
    rows = docs.select("doc_id", (id_crc() % 10 == 0).alias("held_out"), F.coalesce("text", F.lit("")).alias("text"))
    training = rows.filter(~F.col("held_out"))
    lexicon = materialize(word_counts(training), "lexicon")
    total, distinct = lexicon.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    top = _commonest(lexicon, held_words)
    vocabulary = Vocabulary(top, total)
    flat = train(training, vocabulary, total)[0] if total else Gru(vocabulary).flat()
    counts = dict(top)
    in_model = sum(counts[w] for w in vocabulary.ids)
    outside = (total - in_model) + SMOOTH * (distinct - len(vocabulary.ids) + 1)
    base_log, outside_log = math.log10(total + SMOOTH * (distinct + 1)), math.log10(outside)
    held = spark.sparkContext.broadcast((vocabulary, flat, counts))

    def scored(batches):
        from pyspark import TaskContext

        _one_thread()
        v, parameters, known = held.value
        model, unk, uid = Gru(v).load(parameters), v.unk, TaskContext.get().partitionId() << 40
        unseen = math.log10(SMOOTH)
        # a place for every word that is held; the last one stands for all others
        place = {w: k for k, w in enumerate(known)}.get
        held_ids = np.array([*(v.ids.get(w, unk) for w in known), unk], np.int32)
        held_logs = np.array([*(math.log10(n + SMOOTH) for n in known.values()), unseen])

        def done(rows_, documents):
            nonlocal uid
            gru = score_documents(model, documents) / math.log(10)
            cols = list(zip(*rows_))
            n = len(rows_)
            out = {"uid": pa.array(np.arange(uid, uid + n)), "doc_id": pa.array(cols[0], pa.int64()), "held_out": pa.array(cols[1]), "n_tokens": pa.array(cols[2], pa.int64()), "n_known": pa.array(cols[3], pa.int64()), "sum_log": pa.array(cols[4], pa.float64()), "gru": pa.array(gru), "out_log": pa.array(cols[5], pa.float64()), "n_out": pa.array(cols[6], pa.int64()), "rare": pa.array(cols[7], pa.list_(pa.binary()))}
            uid += n
            return pa.RecordBatch.from_pydict(out)

        pending, documents, held_tokens = [], [], 0
        for batch in batches:
            for d, h, text in zip(batch["doc_id"].to_pylist(), batch["held_out"].to_pylist(), utf8(batch["text"])):
                words = tokens_of(text)
                at = np.fromiter(map(place, words, repeat(len(known))), np.int32, len(words))
                tokens, found = np.take(held_ids, at), np.take(held_logs, at)
                out = tokens == unk
                rare = [words[k] for k in np.flatnonzero(at == len(known)).tolist()]
                # words that are not held count as unseen until the join finds them
                pending.append((d, h, len(words), len(words) - len(rare), float(found.sum()), float(found[out].sum()), int(out.sum()), rare))
                documents.append(tokens)
                held_tokens += len(tokens)
                if held_tokens > 1_500_000:
                    yield done(pending, documents)
                    pending, documents, held_tokens = [], [], 0
        if pending:
            yield done(pending, documents)

    schema = "uid long, doc_id long, held_out boolean, n_tokens long, n_known long, sum_log double, gru double, out_log double, n_out long, rare array<binary>"
    made = materialize(rows.mapInArrow(scored, schema), "lm-scored")
    # the counts of words that are not held: joined by word
    more = made.select("uid", F.explode("rare").alias("word")).join(lexicon, "word")
    more = more.groupBy("uid").agg(F.count("*").alias("m"), F.sum(F.log10(F.col("n") + SMOOTH) - math.log10(SMOOTH)).alias("gain"))
    out = made.drop("rare").join(more, "uid", "left").withColumns({"m": F.coalesce("m", F.lit(0)), "gain": F.coalesce("gain", F.lit(0.0))})
    return out.select(
        "doc_id", "held_out", "n_tokens", (F.col("n_known") + F.col("m")).alias("n_known"), F.lit(total).cast("long").alias("train_tokens"),
        (F.col("sum_log") + F.col("gain") - F.col("n_tokens") * F.lit(base_log)).alias("base_score"),
        (F.col("gru") + F.col("out_log") + F.col("gain") - F.col("n_out") * F.lit(outside_log)).alias("score"),
    )
