"""Findings of the third review: fingerprints in the pipeline, training away from the driver."""

import numpy as np

from privbatch.llm import pu_quality, simhash


def test_keep_one_links_by_fingerprints(spark):
    """Fingerprints at 3 differing bits link whatever the Jaccard similarity; other texts are linked as before."""
    words = [" ".join(["one two three"] * 60 + [f"{c}{k}" for k in range(20)]) for c in "ab"]
    a, b = (simhash.fingerprint_of(t, 3) for t in words)
    assert int(a ^ b).bit_count() <= 3
    sets = [{tuple(t.split()[i : i + 3]) for i in range(198)} for t in words]
    assert len(sets[0] & sets[1]) < 0.8 * len(sets[0] | sets[1])
    docs = spark.createDataFrame([(1, words[0]), (2, words[1]), (3, "something else altogether in here")], "doc_id long, text string")
    assert {r["doc_id"] for r in simhash.keep_one(docs, width=3).collect()} == {1, 3}


def test_op3_trains_in_a_task(spark, monkeypatch):
    """No vector comes to the driver and nothing is trained there."""
    rows = [(i, "good plain words of a text" if i % 2 else "#|%$ 99 ## $$ |%", i % 2) for i in range(120)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, quality int")

    def here(*_, **__):
        raise AssertionError("trained on the driver")

    monkeypatch.setattr(pu_quality, "train", here)
    monkeypatch.setattr(pu_quality, "class_prior", here)
    model = pu_quality.fit(docs, docs)
    assert model(np.stack([pu_quality.features(rows[1][1])]))[0] > model(np.stack([pu_quality.features(rows[0][1])]))[0]
