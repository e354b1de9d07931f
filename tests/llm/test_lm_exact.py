"""Scores against models of the real words and pairs, each document held out; in one chunk and in many."""

import math
import random
from collections import Counter

import numpy as np
import pytest

from subwin.llm import lm_scoring


def grams(ws):
    return Counter(ws), Counter([None, *ws][: len(ws)]), Counter(zip([None, *ws], ws))


def corpus():
    r = random.Random(8)
    texts = [" ".join(f"w{int(r.paretovariate(0.6))}" for _ in range(r.randrange(0, 120))) for _ in range(150)] + [None, "", " \t\n ", "long " * 20000]
    texts[40] = texts[3]
    rows = [(i, t) for i, t in enumerate(texts)] + [(None, "no id w1"), (5, texts[5]), (None, "no id w1")]
    labels = [(i, i % 3) for i in range(100)] + [(None, 1), (7, 1), (7, 0), (5000, 1)]
    return rows, labels


def plain(rows, labels, mix=lm_scoring.MIX):
    good = {i for i, q in labels if q == 1 and i is not None}
    split = [(i, (t or "").split()) for i, t in rows]
    models = [[Counter(), Counter(), Counter()] for _ in range(2)]
    for i, ws in split:
        for model in models[: 1 + (i in good)]:
            for have, new in zip(model, grams(ws)):
                have.update(new)
    size = len(models[0][0])
    out = []
    for i, ws in split:
        losses = []
        for model, held in zip(models, (True, i in good)):
            word, before, pair = ((have - own if held else have) for have, own in zip(model, grams(ws)))
            p = []
            for b, w in zip([None, *ws], ws):
                if not word.total():
                    p.append(1 / size)
                    continue
                share = mix[0] if before[b] else 0
                p.append((share * pair[b, w] / before[b] if share else 0) + (1 - share - mix[2]) * word[w] / word.total() + mix[2] / size)
            losses.append(sum(-math.log(x) for x in p) / len(p) if p else None)
        out.append((i, len(ws), losses[1], losses[0]))
    return out


key = lambda x: (x[0] is None, x[0] or 0, x[1], x[2] or 0)


@pytest.mark.parametrize("chunk, bucket", [(lm_scoring.CHUNK, lm_scoring.BUCKET), (3000, 500)])
def test_models(spark, chunk, bucket):
    rows, labels = corpus()
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("doc_id", "text", "1 AS chunk", "'x' AS kind")
    got = lm_scoring.score(docs, spark.createDataFrame(labels, "doc_id int, quality int"), chunk=chunk, bucket=bucket)
    assert got.columns == ["doc_id", "n_words", "target_loss", "background_loss", "score"]
    got, want = sorted(map(tuple, got.collect()), key=key), sorted(plain(rows, labels), key=key)
    assert len(got) == len(want)
    for a, b in zip(got, want):
        assert a[:2] == b[:2]
        assert a[2:4] == (pytest.approx(b[2:]) if b[1] else (None, None))
        assert a[4] == (pytest.approx(b[2] - b[3], abs=1e-9) if b[1] else None)


def test_no_target_and_empty(spark):
    rows, _ = corpus()
    docs, none = spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame([], "doc_id long, quality int")
    size = len({w for _, t in rows for w in (t or "").split()})
    assert all(x.target_loss == pytest.approx(math.log(size)) for x in lm_scoring.score(docs, none).where("n_words > 0").collect())
    assert lm_scoring.score(docs.limit(0), none).count() == 0


def test_probabilities_sum_to_one():
    """Over the vocabulary after each word, of a seen, an unseen context and of no words at all."""
    r = np.random.default_rng(4)
    pair = r.integers(0, 5, (20, 50)) * (np.arange(20) % 4 > 0)[:, None]
    word = r.integers(1, 9, 50)
    for counts, words in ((pair, word), (np.zeros_like(pair), word), (np.zeros_like(pair), np.zeros_like(word))):
        p = lm_scoring.probabilities(counts, counts.sum(axis=1, keepdims=True), words, words.sum(), 50)
        assert np.allclose(p.sum(axis=1), 1) and (p > 0).all()


def test_packing():
    for values in (np.array([], np.uint64), np.array([0, 1, 2**64 - 1, 77], np.uint64)):
        assert (lm_scoring.unpack(lm_scoring.pack(values)) == values).all()
