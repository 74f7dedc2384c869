"""Work done once: op1 numbers a text once for training and scoring and sums by row what goes back to the embeddings; op9 normalises a line once a scan."""

import numpy as np

from privbatch.llm import line_dedup, masked_lm


def test_masked_lm_numbers_texts_once(spark, monkeypatch):
    texts = ["the cat, the dog and the " + "y" * 80, "x" * 70 + " never seen the cat", "", None, "The CAT"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    calls, plain = [], masked_lm.encoded
    monkeypatch.setattr(masked_lm, "encoded", lambda *a: calls.append(a) or plain(*a))
    got = {r["doc_id"]: r for r in masked_lm.digest(docs).collect()}
    assert len(calls) == 1 and [got[k]["n_tokens"] for k in range(5)] == [8, 5, 0, 0, 2]
    assert got[2]["log_likelihood"] == got[3]["log_likelihood"] == 0 and got[3]["per_token"] is None
    vocab = masked_lm.vocabulary(docs)
    rows = plain(docs, vocab).orderBy("doc_id").collect()
    for r, text in zip(rows, texts, strict=True):
        assert masked_lm._numbers(r["ids"]).tolist() == vocab.encode(masked_lm.tokens_of(text)).tolist()


def test_step_sums_by_row():
    """A step changes the embeddings as sums over every single context do, at the ends of texts too."""
    draw = np.random.default_rng(3)
    vocab = masked_lm.Vocabulary([(f"w{k}".encode(), 900 - k) for k in range(900)], 500, None)
    texts = [draw.integers(0, masked_lm.VOCAB, n).astype(np.int32) for n in (1, 2, 0, 3, 200)]
    ids, ctx = np.concatenate(texts), np.concatenate([masked_lm.contexts(t) for t in texts], axis=1)
    back = draw.normal(size=(masked_lm.WIDTH, len(ids)))
    want = np.zeros((2 * masked_lm.REACH * (masked_lm.VOCAB + 1), masked_lm.WIDTH))
    for t in range(len(ids)):
        want[ctx[:, t]] += back[:, t]
    assert np.allclose(masked_lm._summed(ctx, back), want, atol=1e-5)
    first = masked_lm.start(vocab)
    learner = masked_lm.Learner(first)
    learner.step(ids, ctx)
    changed = np.flatnonzero((learner.weights[0] != first[0]).any(axis=1))
    assert set(changed) == set(ctx.ravel())


def test_lines_are_normalised_once(spark):
    docs = spark.createDataFrame([(1, "A  b\n \t \nc D"), (2, None), (3, "")], "doc_id long, text string")
    lines = line_dedup.lines_of(docs)
    assert sorted((r["doc_id"], r["pos"], r["line"]) for r in lines.collect()) == [(1, 0, "a b"), (1, 2, "c d")]
    for df in (lines, line_dedup.texts_of(lines), lines.select("doc_id", "of", "pos", "h")):
        assert df._jdf.queryExecution().optimizedPlan().toString().count("regexp_replace") == 1
