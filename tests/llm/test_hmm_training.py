"""Training of the language model: cuts change nothing, and all text is iterated until the likelihood settles."""

import tracemalloc
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest

from corpusmap.llm import hmm_lm


@pytest.mark.parametrize("segment", [1, 7, 64])
def test_state_is_carried_over_cuts(segment):
    rng = np.random.default_rng(3)
    start, move, emit = rng.dirichlet(np.ones(4)), rng.dirichlet(np.ones(4), 4), rng.dirichlet(np.ones(30), 4).T
    docs = [rng.integers(0, 30, n).astype(np.int32) for n in (1, 7, 8, 63, 64, 65, 500)]
    whole = hmm_lm.expected_counts(docs, [True] * len(docs), start, move, emit)
    got = hmm_lm.document_counts(docs, start, move, emit, segment)
    for a, b in zip(whole, got[:3], strict=True):
        assert np.allclose(a, b, rtol=1e-9, atol=1e-12)
    assert np.isclose(got[3], hmm_lm.forward(docs, start, move, emit).sum())


def test_every_iteration_reads_all_text_until_it_settles(spark, monkeypatch):
    rng = np.random.default_rng(5)
    texts = [" ".join(f"{'ab'[(j // 5) % 2]}{rng.integers(20)}" for j in range(200)) for _ in range(40)] + ["long " * 9000]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    seen, one_pass = [], hmm_lm.train_pass
    monkeypatch.setattr(hmm_lm, "train_pass", lambda t, m, p: (seen.append((t.count(), one_pass(t, m, p))), seen[-1][1])[1])
    model, _ = hmm_lm.train(df, hmm_lm.Params(states=3, heavy_least=3, sample_docs=5, sample_rounds=1))
    gains = np.diff([x for _, x in seen])
    guess, seen = [n for n, _ in seen[:1]], seen[1:]
    gains = gains[1:]
    assert guess[0] < 41 and len(seen) > 2 and {n for n, _ in seen} == {41}
    assert gains[-1] < 1e-3 * model.tokens <= gains[:-1].min()


def _model(states: int = 4, classes: int = 30):
    rng = np.random.default_rng(7)
    return rng, rng.dirichlet(np.ones(states)), rng.dirichlet(np.ones(states), states), rng.dirichlet(np.ones(classes), states).T


def test_scores_hold_the_messages_of_one_step():
    rng, start, move, emit = _model(8)
    docs = [rng.integers(0, 30, 2000).astype(np.int32) for _ in range(200)]
    tracemalloc.start()
    got = hmm_lm.forward(docs, start, move, emit)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 8 * 8 * 400_000  # before: two doubles a state and token
    assert np.isclose(got[:1], hmm_lm.document_counts(docs[:1], start, move, emit, 100_000)[3])


def test_only_stretches_between_two_others_need_matrices(monkeypatch):
    rng, start, move, emit = _model()
    docs = [rng.integers(0, 30, n).astype(np.int32) for n in (10, 17, 32, 33, 40)]
    rows, transfers = [], hmm_lm._transfers
    monkeypatch.setattr(hmm_lm, "_transfers", lambda seqs, left, *a: (rows.append((len(left), len(seqs))), transfers(seqs, left, *a))[1])
    got = hmm_lm.document_counts(docs, start, move, emit, 16)
    assert sum(n for h, n in rows if h > 1) == 2  # of the documents of three stretches
    for a, b in zip(hmm_lm.expected_counts(docs, [True] * 5, start, move, emit), got, strict=False):
        assert np.allclose(a, b, rtol=1e-9, atol=1e-12)


def test_rare_tokens_do_not_vanish_between_scalings():
    rng, start, move, emit = _model()
    emit = emit * 1e-40  # each emission near the end of what four of them leave of a double
    docs = [rng.integers(0, 30, n).astype(np.int32) for n in (1, 2, 3, 4, 5, 9, 40)]
    assert np.allclose(hmm_lm.forward(docs, start, move, emit), [hmm_lm.forward([d], start, move, emit * 1e40)[0] - 40 * len(d) * np.log(10) for d in docs])
    assert np.isclose(hmm_lm.document_counts(docs, start, move, emit, 7)[2].sum(), 64)


def _texts():
    odd = ["", "  ", "\t A\x0bb\x0c ", "a\x1cb \x85 \xa0 c", "É é x", "x" * 64 + " " + "x" * 65 + " " + "Y" * 70, " lead", "trail ", "ab", "xab", "q" * 300 + " ab"]
    rng = np.random.default_rng(11)
    return [t.encode() for t in odd] + [b" \xff\xfe  \xc3 "] + [b" ".join(b"w%d" % i for i in rng.zipf(1.3, n) % 5000) for n in (1, 30, 400, 3000)]


def test_many_texts_become_classes_at_once(monkeypatch):
    texts = _texts()
    tokens = [hmm_lm.tokens_of(t) for t in texts]
    heavy = [hmm_lm.END, b"a", b"w1", b"w2", b"w3", hmm_lm.held_as(b"x" * 65), b"x" * 64]
    index = {t: i for i, t in enumerate(heavy)}
    whole = pa.array([b"before", *texts], type=pa.binary()).slice(1)
    monkeypatch.setattr(hmm_lm, "SLICE", 500)
    runs = list(hmm_lm._runs(whole))
    assert len(runs) > 2 and [i for lo, hi in runs for i in range(lo, hi)] == list(range(len(texts)))
    for lo, hi in [(0, len(texts)), *runs]:
        lens, at, words = hmm_lm.split_all(whole.slice(lo, hi - lo))
        assert lens.tolist() == [len(t) for t in tokens[lo:hi]] and len(set(words.to_pylist())) == len(words)
        assert words.take(pa.array(at)).to_pylist() == [w for t in tokens[lo:hi] for w in t]
        assert hmm_lm.tail_classes(words).tolist() == [hmm_lm.tail_class(w) for w in words.to_pylist()]
        lens, ids, rows, tail = hmm_lm.encode_all(whole.slice(lo, hi - lo), pa.array(heavy, type=pa.binary()))
        want = [hmm_lm.encode(t, index, len(heavy)) for t in texts[lo:hi]]
        assert lens.tolist() == [len(i) for i, _ in want] and ids.tolist() == [c for i, _ in want for c in i.tolist()]
        assert list(zip(rows.tolist(), tail.to_pylist(), strict=True)) == [(k, w) for k, (_, t) in enumerate(want) for w in t]


def test_texts_are_split_without_an_object_a_token(spark, monkeypatch):
    texts = [t.decode(errors="replace") for t in _texts()]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    seen = Counter(w for t in texts for w in [*hmm_lm.tokens_of(t.encode()), hmm_lm.END])

    def one_by_one(*_):
        raise AssertionError("tokens one by one")

    monkeypatch.setattr(hmm_lm, "tokens_of", one_by_one)  # before: the counts and both encodings went through it
    assert {bytes(t): n for t, n in hmm_lm.token_counts(df.selectExpr("cast(text as binary)")).collect()} == seen


def test_what_steps_emit_is_looked_up_for_many_steps_at_once(monkeypatch):
    rng, start, move, emit = _model()
    docs = [rng.integers(0, 30, n).astype(np.int32) for n in (1, 7, 8, 63, 64, 65, 500)]
    want = [hmm_lm.document_counts([d], start, move, emit, 10_000)[3] for d in docs]
    looked, take = [], np.take
    monkeypatch.setattr(np, "take", lambda *a, **k: (looked.append(1), take(*a, **k))[1])
    got = hmm_lm.forward(docs, start, move, emit)
    assert len(looked) < 50  # before: one look-up a step, 500 here
    monkeypatch.setattr(hmm_lm, "STEPS", 9)
    assert np.allclose(got, want) and np.allclose(hmm_lm.forward(docs, start, move, emit), want)
