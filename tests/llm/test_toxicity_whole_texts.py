"""All words of all labelled examples are searched, whether they tell labels apart or not."""

import random

import numpy as np
import pytest

from temporal_rules.llm import toxicity


def test_every_example_and_text_is_searched(spark):
    rng = random.Random(3)
    words = [f"w{rng.randrange(10**6):x}" for _ in range(400)]
    rows = [(i, " ".join(rng.sample(words, 12))) for i in range(60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(60)], "doc_id long, toxic int")
    scorer = toxicity.fit(docs, labels)
    kept = {r.doc_id for r in docs.where(~toxicity.held_out()).select("doc_id").collect()}
    assert set(scorer.ids) == kept
    got = {r.doc_id: r for r in toxicity.score_documents(docs, scorer).collect()}
    for i, r in got.items():
        assert r.evidence
        if i in kept:
            assert r.evidence[0].doc_id == i and r.evidence[0].similarity == pytest.approx(1)


def test_few_labels_still_tell(spark):
    rows = [(i, f"plain{i} text of day {i}" + (" foul" if i % 3 == 0 else "")) for i in range(24)] + [(100, "some foul thing"), (101, "some day thing")]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 3 == 0)) for i in range(24)], "doc_id long, toxic int")
    got = {r.doc_id: r for r in toxicity.score_documents(docs, toxicity.fit(docs, labels)).collect()}
    assert got[100].predicted == 1 and got[101].predicted == 0


def test_batches_and_blocks_are_exact():
    rng = np.random.default_rng(4)
    vectors = []
    for _ in range(900):
        t = np.sort(rng.choice(2_000, rng.integers(1, 60), replace=False) ** 2 // 2_000).astype(np.int32)
        t = np.unique(t)
        w = rng.random(len(t)) + 0.01
        vectors.append((t, w / np.sqrt(w @ w)))
    dense = np.zeros((900, 2_000))
    for i, (t, w) in enumerate(vectors):
        dense[i, t] = w
    index = toxicity.BlockMaxIndex(vectors, block=32, common=40)
    some = vectors[:70]
    skips = [frozenset([i, i + 5]) for i in range(70)]
    for q, skip, got in zip(range(70), skips, index.nearest_of(some, 9, skips)):
        sims = np.round(dense @ dense[q], 12)
        sims[list(skip)] = -1
        want = np.lexsort((np.arange(900), -sims))[:9]
        want = [int(i) for i in want if sims[i] > 0]
        assert [i for _, i in got] == want and [s for s, _ in got] == pytest.approx(sims[want].tolist())


def test_building_an_index_needs_little_besides_it():
    """Every worker of a machine builds one at the same time."""
    import tracemalloc

    rng = np.random.default_rng(4)
    vectors = [(np.sort(rng.choice(60_000, 1000, replace=False)).astype(np.int32), np.full(1000, 1000**-0.5)) for _ in range(2000)]
    index = toxicity.BlockMaxIndex(vectors, common=16)
    tracemalloc.start()
    try:
        index._build()
        peak = tracemalloc.get_traced_memory()[1]
    finally:
        tracemalloc.stop()
    assert peak < 30 * len(index.terms)
    assert [i for _, i in index.nearest(*vectors[5], 1)] == [5]
    assert index.post_start[-1] + (index.matrix > 0).sum() == len(index.terms)


def test_a_model_that_is_let_go_is_freed_at_once():
    """Even where it refers to itself: a worker's next task holds large things too."""
    import weakref

    from temporal_rules.llm import common

    class Model:
        def __init__(self):
            self.me = self

    seen = weakref.ref(common.kept("model", Model))
    common.let_go()
    assert seen() is None


def a_vocabulary(words):
    hashes = np.array([toxicity.xxhash.xxh64_intdigest(w.encode(), 42) for w in words], np.uint64)
    return toxicity.Vocabulary(hashes, np.arange(1, len(words) + 1) / 7)


def test_words_of_texts_searched_together_are_looked_up_together(monkeypatch):
    """Most of a text's words stand in other texts as well: a look-up for each text is most of a score's cost."""
    rng = random.Random(5)
    words = [f"w{i}" for i in range(3_000)]
    texts = [" ".join(rng.choices(words, k=80)) for _ in range(200)]
    vocabulary = a_vocabulary(words)
    vectors = [vocabulary.vector(t) for t in texts[:40]]
    scorer = toxicity.Scorer(vocabulary, list(range(40)), [i % 2 for i in range(40)], vectors, list(range(40)), 3)
    scorer.calibrate(scorer.votes(list(range(40))))
    seen, one = [], toxicity.Vocabulary.numbers
    monkeypatch.setattr(toxicity.Vocabulary, "numbers", lambda self, some: seen.append(len(some)) or one(self, some))
    got = scorer.score(texts)
    assert seen == [len({w for t in texts for w in t.split()})]
    monkeypatch.undo()
    for text, together in zip(texts, got):
        scorer.seen.clear()
        assert scorer.score([text]) == [together]


def test_words_are_those_of_the_pattern():
    import re

    rng = random.Random(6)
    signs = "aZ9_ -.,'\t\n\x00\x1c\x7f\x85 ²ßÉİ́٣’ 　中가\ud800\U0001f600\U0001d7d8"
    texts = ["", None, "_", "plain words, here", *("".join(rng.choices(signs, k=rng.randrange(40))) for _ in range(4_000))]
    want = [re.findall(r"\w+", (t or "").lower().replace("_", " ")) for t in texts]
    assert [[w.decode("utf-8", "surrogatepass") for w in toxicity.terms_of(t)] for t in texts] == want
    every = sorted({w for some in want for w in some})
    known = every[::2]
    vocabulary = a_vocabulary(known)
    number = {w: int(vocabulary.numbers([w.encode()])[0]) for w in known}
    vocabulary.TOGETHER = 500  # many calls, some of one text
    got = vocabulary.vectors(texts)
    assert len(got) == len(texts) and vocabulary.vectors([]) == []
    for some, (terms, weights) in zip(want, got):
        tf = {number[w]: some.count(w) for w in some if w in number}
        raw = np.array([(1 + np.log(tf[t])) * vocabulary.weight[t] for t in sorted(tf)])
        assert terms.tolist() == sorted(tf)
        assert weights == pytest.approx(raw / (np.sqrt(raw @ raw) if len(raw) else 1))
