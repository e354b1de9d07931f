"""The pipeline's near-dedup takes the fingerprints' step as well as the shingles'."""

import corpus_pipeline


def test_fingerprints_take_part(spark, tmp_path):
    """One passage fifty times and ten words of their own: fingerprints, which count repeats, are equal, sets of shingles unlike."""
    often = " ".join(f"w{i}" for i in range(9)) + " "
    texts = [often * 50 + " ".join(f"{own}{i}" for i in range(10)) for own in "ab"] + [" ".join(f"c{i}" for i in range(60))]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    assert sorted(r["doc_id"] for r in corpus_pipeline.near(spark, docs, str(tmp_path)).collect()) == [0, 2]
