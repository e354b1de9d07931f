"""Operators on cases in which a part of the job was left out before."""

import random
from collections import defaultdict


def jaccard(a, b, width=5):
    sets = [{tuple(ws[i : i + width]) for i in range(max(1, len(ws) - width + 1))} for ws in (a.lower().split(), b.lower().split())]
    return len(sets[0] & sets[1]) / len(sets[0] | sets[1])


def test_pipeline_near_copies(spark):
    """Planted copies of growing distance, a chain and a crowd, against brute force."""
    import corpus_pipeline

    r = random.Random(12)
    vocabulary = [f"w{i}" for i in range(3000)]
    texts = []
    for k in range(30):
        base = [r.choice(vocabulary) for _ in range(r.randrange(60, 250))]
        texts.append(" ".join(base))
        for edits in (1, 2, 3, 5, 8):
            copy = list(base)
            for at in r.sample(range(len(copy)), edits):
                copy[at] = r.choice(vocabulary)
            texts.append(" ".join(copy))
    chain = [r.choice(vocabulary) for _ in range(150)]
    for k in range(12):
        chain = [*chain[8:], *(r.choice(vocabulary) for _ in range(8))]
        texts.append(" ".join(chain).upper())
    r.shuffle(texts)
    root = list(range(len(texts)))
    links = 0
    for i in range(len(texts)):
        for j in range(i):
            if jaccard(texts[i], texts[j]) >= 0.8:
                links += 1
                a, b = root[i], root[j]
                root = [min(a, b) if x in (a, b) else x for x in root]
    groups = defaultdict(list)
    for i, x in enumerate(root):
        groups[x].append(i)
    assert links > 100 and 30 < len(groups) < len(texts)
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in enumerate(texts)] + [(900, None, "en", "s", 0), (901, " ", "en", "s", 1), (0, texts[0], "en", "s", len(texts[0]))], "doc_id long, text string, lang string, source string, n_chars long")
    left = corpus_pipeline.near(spark, docs, "")
    assert left.columns == docs.columns
    assert sorted(x.doc_id for x in left.collect()) == sorted([min(g) for g in groups.values()] + [900])
    assert corpus_pipeline.near(spark, docs.limit(0), "").count() == 0
