"""The language model: gradients, probabilities that sum to one, a state that is carried, and what it learns from."""

import numpy as np
import pytest
from graphsieve.llm import gru_lm


def model(words=40, classes=5, hidden=4, seed=3):
    rng = np.random.default_rng(seed)
    v = gru_lm.Vocabulary([(b"w%d" % k, int(n)) for k, n in enumerate(sorted(rng.integers(1, 50, 60), reverse=True))], 2000, words, classes)
    m = gru_lm.Gru(v, hidden, seed)
    m.p = {k: x + rng.normal(0, 0.3, x.shape).astype(np.float32) for k, x in m.p.items()}
    return m


def test_probabilities_sum_to_one():
    m = model()
    state = np.random.default_rng(1).uniform(-1, 1, (1, m.h)).astype(np.float32)
    logp, _ = m.output(np.repeat(state, m.v.size, 0), np.arange(m.v.size))
    assert np.exp(logp).sum() == pytest.approx(1, rel=1e-5)
    m.p["wo"] *= 100  # beyond what single precision holds, rows are moved into range
    logp, _ = m.output(np.repeat(state, m.v.size, 0), np.arange(m.v.size))
    assert np.exp(logp.astype(float)).sum() == pytest.approx(1, rel=1e-4)


def test_gradients_against_differences():
    m, rng = model(), np.random.default_rng(2)
    inputs, targets = rng.integers(-1, m.v.size, (6, 3)).astype(np.int32), rng.integers(0, m.v.size, (6, 3)).astype(np.int32)
    fresh, valid = np.zeros((6, 3), bool), np.ones((6, 3), bool)
    fresh[0], fresh[3, 1], valid[5, 2] = True, True, False
    state = rng.uniform(-1, 1, (3, m.h)).astype(np.float32)
    inputs[fresh] = -1
    grads, rows, _ = m.gradients(inputs, fresh, targets, valid, state)

    def loss():
        states, _, _ = m.forward(inputs, fresh, state, False)
        logp, _ = m.output(states.reshape(-1, m.h), targets.ravel())
        return -float((logp.astype(float) * valid.ravel()).sum()) / valid.sum()

    for name in m.NAMES:
        full = np.zeros_like(m.p[name])
        if name == "x":
            full[rows] = grads[name]
        else:
            full = grads[name]
        for at in [tuple(rng.integers(0, n) for n in full.shape) for _ in range(12)]:
            kept, step = m.p[name][at], 2e-2
            m.p[name][at] = kept + step
            up = loss()
            m.p[name][at] = kept - step
            down = loss()
            m.p[name][at] = kept
            assert (up - down) / (2 * step) == pytest.approx(float(full[at]), abs=2e-3), (name, at)


def test_state_is_carried_through_a_document(monkeypatch):
    """Scores are those of one document at a time, one word at a time, whatever the windows, lanes and blocks."""
    m, rng = model(), np.random.default_rng(5)
    documents = [rng.integers(0, m.v.size, n).astype(np.int32) for n in (1, 3, 700, 64, 65, 2, 130)]
    plain = []
    for d in documents:
        state, before, total = np.zeros((1, m.h), np.float32), -1, 0.0
        for w in d:
            states, _, state = m.forward(np.array([[before]]), np.zeros((1, 1), bool), state, False)
            total += float(m.output(states.reshape(-1, m.h), np.array([w]))[0][0])
            before = w
        plain.append(total)
    for block in (4096, 96, 64):
        monkeypatch.setattr(gru_lm.lanes_of, "__defaults__", (block,))
        for lanes, steps in ((256, 64), (3, 16), (1, 7)):
            assert gru_lm.score_documents(m, documents, lanes, steps) == pytest.approx(plain, rel=1e-4)
    assert len(gru_lm.score_documents(m, [])) == 0


def test_memory_of_a_long_document():
    """A text of a million words beside short ones: layout follows lanes and block, not the longest text."""
    documents = [np.zeros(1_000_000, np.int32), *[np.zeros(5, np.int32)] * 300]
    seen = words = 0
    for running, inputs, _, fresh, owner in gru_lm.lanes_of(documents, 256, 64):
        seen = max(seen, inputs.size)
        words += int((owner >= 0).sum())
        assert len(running) <= 256 and fresh.shape == inputs.shape
    assert words == 1_001_500 and seen <= 64 * 256


def test_learning_beats_the_start():
    v = gru_lm.Vocabulary([(b"a", 500), (b"b", 400), (b"c", 300)], 1300, 4, 2)
    ids = [v.ids[w] for w in (b"a", b"b", b"c")]
    documents = [np.array(ids * 30, np.int32) for _ in range(64)]
    m = gru_lm.Gru(v)
    before = gru_lm.score_documents(m, documents).sum()
    assert gru_lm.train_documents(m, documents, 8) == 64 * 90
    assert gru_lm.score_documents(m, documents).sum() > before * 0.7


def test_lm_learns_from_every_document(spark):
    docs = spark.createDataFrame([(k, "the same text " * (k % 5)) for k in range(400)], "doc_id long, text string")
    words = gru_lm.word_counts(docs).collect()
    total = sum(r.n for r in words)
    vocabulary = gru_lm.Vocabulary(sorted(((bytes(r.word), r.n) for r in words), key=lambda x: -x[1]), total)
    _, seen = gru_lm.train(docs, vocabulary, total)
    assert seen == total


def test_parameters_are_averaged_on_the_cluster(spark):
    """More trainers than one: the mean of every part is weighted by the trainers' tokens."""
    rng = np.random.default_rng(7)
    made = [(t, k, n, rng.normal(size=5).astype(np.float32)) for t, n in enumerate((10, 30, 1)) for k in range(3)]
    found = gru_lm._averaged(spark.createDataFrame([(t, k, n, p.tobytes()) for t, k, n, p in made], "trainer int, part int, tokens long, p binary"))
    for k in range(3):
        assert found[k][0] == 41
        np.testing.assert_allclose(found[k][1], sum(n * p for _, j, n, p in made if j == k) / 41, rtol=1e-5)


def test_trainers_share_every_document(spark, monkeypatch):
    monkeypatch.setattr(gru_lm, "TRAINER_TOKENS", 200)
    test_lm_learns_from_every_document(spark)


def test_lm_odd_rows(spark):
    """Null and empty texts are one token, the end; repeated rows and ids count each; other columns are not read; an empty table gives none."""
    rows = [(1, None, "z"), (2, "", "z"), (3, "one two", "z"), (3, "one two", "z"), (None, "one", "z"), (4, "three " * 30_000, "z")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, score string")
    got = gru_lm.lm_scores(docs).collect()
    assert sorted(r.n_tokens for r in got) == [1, 1, 2, 3, 3, 30_001] and all(r.score < 0 for r in got)
    assert gru_lm.lm_scores(docs.limit(0)).collect() == []
