"""Work that is not done for what cannot need it: tokens known to the tasks are not joined, lines without candidates get no bit maps."""

import random

import pytest
from pyspark.sql import functions as F

from privbatch.llm import line_dedup, masked_lm
from privbatch.llm.common import Scratch


def test_masked_lm_known_tokens_are_not_joined(spark, monkeypatch):
    words = [f"w{k}" for k in range(1200) for _ in range(3 + (1200 - k) // 100)]
    random.Random(5).shuffle(words)
    texts = [" ".join(words[at : at + 400]) for at in range(0, len(words), 400)] + ["x" * 70 + " w1199 w1199 never", None]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    joined, plain = [], masked_lm._in_bucket
    monkeypatch.setattr(masked_lm, "_in_bucket", lambda vocab, rare: joined.append(rare.count()) or plain(vocab, rare))

    def scored() -> dict:
        vocab = masked_lm.vocabulary(docs)
        return {r["doc_id"]: r["log_likelihood"] for r in masked_lm.score(docs, vocab, masked_lm.start(vocab)).collect()}

    some = scored()
    monkeypatch.setattr(masked_lm, "KNOWN", 0)
    none = scored()
    assert some == pytest.approx(none, rel=1e-9) and joined[0] == 1 < 200 < joined[1]  # the long token alone is looked up by its key


def test_line_dedup_bit_maps_of_candidates_only(spark, monkeypatch):
    draw = random.Random(3)
    lines = ["".join(draw.choices("abcdefgh ", k=120)).strip() for _ in range(20)]
    lines.append(lines[0][:-1] + "z")
    texts = spark.createDataFrame(list(enumerate(lines)), "h long, line string")
    scratch = Scratch(spark, "few")
    signed = scratch.keep(texts.join(line_dedup.signatures(texts), "h"))
    own = {r["h"]: r["bands"] for r in signed.collect()}
    shared = next(x for x, y in zip(own[0], own[20], strict=True) if x == y)
    lists = spark.createDataFrame([(shared, h, h) for h in range(21)], "band long, h long, root long")
    mapped, plain = [], line_dedup._by_eights
    monkeypatch.setattr(line_dedup, "_by_eights", lambda rows, *more, **named: mapped.append(rows.select("h").distinct().count()) or plain(rows, *more, **named))
    pairs = line_dedup._across(scratch, lists, signed, 0.8, line_dedup.GRAMS).collect()
    assert [(r["a"], r["b"]) for r in pairs] == [(0, 20)] and mapped == [2]
    # within one component there is nothing to look for
    one = lists.withColumn("root", F.lit(0).cast("long"))
    assert line_dedup._with_candidates(scratch, one, signed).count() == 0
    scratch.clear()
