"""Pairs of terms of which neither alone says anything about the label."""

import numpy as np

from quadinv.llm import toxicity


def drawn(label):
    draw = np.random.default_rng(4)
    a, b = draw.random(2000) < 0.5, draw.random(2000) < 0.5
    noise = draw.integers(100, 400, (2000, 12))
    return [np.unique(np.concatenate(([1] * int(a[k]), [2] * int(b[k]), noise[k])).astype(np.int64)) for k in range(2000)], label(a, b).astype(float)


def test_pair_without_informative_terms():
    """Toxic where exactly one of two terms is there: each is as common in toxic texts as in clean ones."""
    terms, y = drawn(lambda a, b: a ^ b)
    met, bad = toxicity.counted(terms[:1500], y[:1500])
    assert not toxicity.significant(met, bad, y[:1500].mean()).any()
    assert np.flatnonzero(toxicity.paired(terms[:1500], y[:1500], *toxicity.pairable(met, bad, y[:1500].mean()))).tolist() == [1, 2]
    model = toxicity.learn(terms[:1500], y[:1500], epochs=40)
    assert ((model.scores(terms[1500:]) > 0.5) == y[1500:]).mean() > 0.97


def test_no_pair_in_noise():
    terms, _ = drawn(lambda a, b: a)
    y = (np.random.default_rng(8).random(2000) < 0.3).astype(float)
    assert not toxicity.paired(terms, y, *toxicity.pairable(*toxicity.counted(terms, y), y.mean())).any()


def test_fit_sends_chosen_slots_and_learns_the_same(spark, monkeypatch):
    """The machine of fit, which leaves terms out before they are sent, is that of learning from all of them."""
    texts = [f"word{k % 7} common " + ("stupid " if k % 3 == 0 else "kind ") + ("blue" if k % 2 else "green") for k in range(300)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    labels = spark.createDataFrame([(k, int(k % 3 == 0)) for k in range(300)], "doc_id long, toxic int")
    got = toxicity.fit(docs, labels)
    rows = sorted(((float(k % 3 == 0), np.sort(toxicity.Terms().of(t))) for k, t in enumerate(texts)), key=lambda r: r[0])
    whole = toxicity.learn([t for _, t in rows], np.array([y for y, _ in rows]))
    assert (np.flatnonzero(got.weights) == np.flatnonzero(whole.weights)).all() and len(np.flatnonzero(got.weights))
    scores = got.scores([toxicity.Terms().of(t) for t in texts])
    assert ((scores > 0.5) == (np.arange(300) % 3 == 0)).all()
