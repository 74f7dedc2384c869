"""Findings of the fourth review: shuffle files that stayed, rounds that were not needed, bins in groups."""

import time

import pytest
from pyspark.sql import functions as F

from privbatch.llm import line_dedup
from privbatch.llm.common import Scratch, components


def test_release_lets_shuffle_files_go(spark):
    """The last job's shuffle files go too, though no later job has taken its place in the driver."""
    held = lambda: spark.sparkContext._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllFiles().size()
    scratch = Scratch(spark, "release")
    scratch.release()
    time.sleep(1)
    before = held()
    scratch.keep(spark.range(100_000).repartition(8, "id").groupBy(F.col("id") % 1000).count())
    assert held() > before
    scratch.release()
    for _ in range(50):
        if held() <= before:
            return
        time.sleep(0.1)
    pytest.fail(f"{held()} files are left of {before} before")


def test_components_end_with_the_stars(spark):
    """Links that are stars already need no round; a path still ends in its smallest node."""
    scratch = Scratch(spark, "stars")
    got = components(scratch, spark.createDataFrame([(1, 2), (3, 1), (7, 5), (7, 7)], "a long, b long"))
    assert scratch.n == 1 and sorted(map(tuple, got.collect())) == [(1, 1), (2, 1), (3, 1), (5, 5), (7, 5)]
    path = components(scratch, spark.createDataFrame([(k, k + 1) for k in range(40)], "a long, b long"))
    assert sorted(map(tuple, path.collect())) == [(k, 0) for k in range(41)]


def test_bins_and_bit_maps_by_eights(spark):
    """Merged values lie at their places, and a place without a value is null."""
    rows = [(h, p, h * 1000 + p * 7 + t) for h in (1, 2) for p in range(0, 64, h * 3) for t in (5, 0)]
    out = line_dedup._by_eights(spark.createDataFrame(rows, "h long, p int, x long"), "p", F.min, "x", 64).collect()
    assert {r["h"]: r["m"] for r in out} == {h: [h * 1000 + p * 7 if p % (h * 3) == 0 else None for p in range(64)] for h in (1, 2)}
