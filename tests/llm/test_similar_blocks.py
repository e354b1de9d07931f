"""Members outside a band's largest component, in blocks, against all pairs."""

import random

import numpy as np

from subwin.llm import similar_dedup as near
from subwin.llm.simhash_dedup import shingles
from subwin.storage import Scratch


def crowd(n=90):
    """Copies of one text with up to a third of it changed in runs: some alike by 0.8, most not."""
    r = random.Random(5)
    base = [f"w{r.randrange(2000)}" for _ in range(160)]
    found = []
    for _ in range(n):
        copy, at = list(base), r.randrange(160)
        for k in range(r.randrange(2, 50)):
            copy[(at + k) % 160] = f"x{r.randrange(10**6)}"
        found.append(" ".join(copy))
    return found


def links(sets):
    return {(a, b) for a in sets for b in sets if a < b and near.similarity(sets[a], sets[b]) >= near.LEAST}


def test_blocks_lose_no_link(spark):
    texts = crowd()
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    printed = near.sketched(docs).cache()
    rows = printed.collect()
    sets = {x.node: np.unique(shingles(texts[x.doc_id], near.WIDTH)) for x in rows}
    bands = {x.node: set(x.bands) for x in rows}
    want = {(a, b) for a, b in links(sets) if bands[a] & bands[b]}
    assert want == links(sets) and 50 < len(want) < len(rows) * (len(rows) - 1) / 4
    members = printed.selectExpr("node", "node as root", "n", "sig", "posexplode(bands) as (slot, band)")
    bodies = printed.join(docs, "doc_id").select("node", "text")
    for block in (4, 1024):
        got = [(x.a, x.b) for x in near.rest_links(members, bodies, block=block).collect()]
        # the member of the largest component doesn't ask, and all others do
        assert len(got) == len(set(got)) and set(got) == want, block


def test_components_of_a_crowd(spark):
    texts = crowd()
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    scratch = Scratch(spark, "test")
    printed = scratch.save(near.sketched(docs), "printed")
    got = {x.doc_id: x.component_id for x in printed.drop("n").join(near.classes(printed, docs, scratch, block=8), "node").collect()}
    root = list(range(len(texts)))
    for a, b in links({i: np.unique(shingles(t, near.WIDTH)) for i, t in enumerate(texts)}):
        old, new = max(root[a], root[b]), min(root[a], root[b])
        root = [new if x == old else x for x in root]
    assert got == dict(enumerate(root))


def test_overlaps():
    own = np.array([1, 4, 9], np.uint64)
    assert near._overlaps(own, [np.array([0, 4], np.uint64), np.array([9, 10, 11], np.uint64), np.array([1, 4, 9], np.uint64)]).tolist() == [1, 1, 3]
