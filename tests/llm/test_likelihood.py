"""Likelihoods of op1: cheaper steps give the values of the plain ones."""

import re

import numpy as np

from privbatch.llm import masked_lm


def test_tokens_equal_the_pattern():
    plain = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
    for text in ("".join(map(chr, range(300))) * 2, "A-b__c\x00d\x7fe\x1cf    9é!!\ud800x", "", None):
        want = re.findall(rb"[0-9a-z\x80-\xff]+|[!-/:-@\[-`{-~]", (text or "").encode("utf-8", "surrogatepass").translate(plain))
        assert masked_lm.tokens_of(text) == want


def test_likelihoods_equal_the_softmax():
    """The network's values by class and position, worked out token by token; a step follows their gradient."""
    vocab = masked_lm.Vocabulary([(f"w{k}".encode(), 900 - k) for k in range(900)], 500, None)
    ids = vocab.encode([f"w{k * k % 1100}".encode() for k in range(300)] + [b"y" * 100])
    assert vocab.encode([b"w7", b"zzz"]).tolist() == [7, vocab.encode([b"zzz"])[0]] and ids[-1] >= masked_lm.VOCAB - masked_lm.RARE
    learner = masked_lm.Learner(masked_lm.start(vocab))
    ctx = masked_lm.contexts(ids)
    embed, a, b, c, d = learner.weights
    soft = lambda z, k: z[k] - np.log(np.exp(z).sum())
    want = []
    for t, i in enumerate(ids):
        h = np.tanh(embed[ctx[:, t]].sum(axis=0))
        g, w = divmod(int(i), masked_lm.IN_CLASS)
        want.append(soft(h @ a + b, g) + soft(h @ c[g] + d[g], w))
    first = masked_lm.log_probs(learner.weights, ids, ctx)
    assert np.allclose(first, want, atol=1e-4)
    for _ in range(20):
        learner.step(ids, ctx)
    assert masked_lm.log_probs(learner.weights, ids, ctx).sum() > first.sum()
