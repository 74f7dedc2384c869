"""Exact inner-product search over vectors grouped by length.

Rows are sorted by length and cut into buckets.  For a query q with a known lower bound t on its
k-th best score, a bucket whose longest vector is l can hold a result only if t / (|q| l), the
local cosine threshold, is at most one.  A bucket that passes is searched in the way its threshold
suggests: a high one leaves a narrow band around the query's strongest coordinates, so rows outside
it go (coordinate pruning); a low one only bounds the rows' own length, so the tail of the sorted
bucket goes (length pruning).  What remains is verified by exact integer products.

Bounds t come from one bucket of the longest vectors.  Queries go in groups of ``GROUP`` that are
broadcast one group at a time, so what is broadcast does not grow with the table.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch

BUCKET = 4096
GROUP = 16384
NARROW = 0.6
FOCUS = 3


def usable(vector: Column) -> Column:
    """True for a vector that is not null and whose components are all finite."""
    finite = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf")))
    return vector.isNotNull() & F.forall(vector.cast("array<double>"), finite)


def integers(vector: Column) -> Column:
    return F.transform(vector.cast("array<double>"), lambda x: F.floor(x * 256).cast("long"))


def _matrix(rows: list[np.ndarray], width: int) -> np.ndarray:
    out = np.zeros((len(rows), width), np.int64)
    for i, r in enumerate(rows):
        out[i, : len(r)] = r
    return out


def products(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Exact a b^T of integer matrices; in floating point only where that is exact."""
    width = max(a.shape[1], b.shape[1])
    a = np.pad(a, ((0, 0), (0, width - a.shape[1])))
    b = np.pad(b, ((0, 0), (0, width - b.shape[1])))
    most = float(np.abs(a).max(initial=0)) * float(np.abs(b).max(initial=0)) * max(1, width)
    if most < 2**52:
        return (a.astype(np.float64) @ b.astype(np.float64).T).astype(np.int64)
    return a @ b.T


def best(scores: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Places of the k best: falling score, then rising id."""
    if len(scores) > 4 * k:
        edge = np.partition(scores, len(scores) - k)[len(scores) - k]
        near = np.flatnonzero(scores >= edge)
        return near[np.lexsort((ids[near], -scores[near]))][:k]
    return np.lexsort((ids, -scores))[:k]


class Bucket:
    """Rows sorted by falling length, and their unit vectors."""

    def __init__(self, ids: np.ndarray, rows: np.ndarray):
        length = np.sqrt((rows.astype(np.float64) ** 2).sum(axis=1))
        order = np.argsort(-length, kind="stable")
        self.ids, self.rows, self.length = ids[order], rows[order], length[order]
        self.flat = self.rows.astype(np.float64)
        self.most = float(np.abs(self.flat).max(initial=0)) * max(1, rows.shape[1])
        self.unit = self.flat / np.maximum(self.length, 1e-300)[:, None]

    def scores(self, query: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Exact products of the query with the rows at these places."""
        width = min(len(query), self.rows.shape[1])
        query = query[:width]
        if self.most * float(np.abs(query).max(initial=0)) >= 2**52:
            return self.rows[at, :width] @ query
        flat = self.flat[:, :width]
        every = flat @ query.astype(np.float64) if 2 * len(at) > len(flat) else None
        return (flat[at] @ query.astype(np.float64) if every is None else every[at]).astype(np.int64)

    def reachable(self, query: np.ndarray, norm: float, bound: float) -> np.ndarray:
        """Places of the rows that may score ``bound`` or more with the query."""
        n = len(self.ids)
        if bound <= 0 or norm == 0:
            return np.arange(n) if bound <= 0 else np.arange(0)
        slack = 1 - 1e-9
        if norm * self.length[0] < bound * slack:
            return np.arange(0)
        reach = int(np.searchsorted(-self.length, -(bound * slack / norm), side="right"))
        local = min(1.0, bound * slack / (norm * self.length[0]))
        if local < NARROW:
            return np.arange(reach)
        keep = np.ones(reach, bool)
        unit = query / norm
        for f in np.argsort(-np.abs(unit))[:FOCUS]:
            if f < self.unit.shape[1]:
                spread = np.sqrt(max(0.0, (1 - local * local) * (1 - unit[f] ** 2))) + 1e-9
                keep &= np.abs(self.unit[:reach, f] - local * unit[f]) <= spread + (1 - local) * abs(unit[f])
        return np.flatnonzero(keep)


def layout(vectors: DataFrame, bucket: int = BUCKET, distinct: bool = False) -> DataFrame:
    """Buckets of usable rows of similar length: longest, n, width, ids and matrix as bytes; if distinct, one row an id."""
    own = vectors.where(usable(F.col("embedding")) & F.col("vec_id").isNotNull())
    own = own.select(F.col("vec_id").cast("long").alias("vec_id"), integers(F.col("embedding")).alias("v"))
    if distinct:
        own = own.groupBy("vec_id").agg(F.min("v").alias("v"))
    square = F.aggregate("v", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))
    own = own.withColumn("square", square)
    parts = max(1, -(-vectors.count() // bucket))
    dealt = own.repartitionByRange(parts, F.desc("square"), "vec_id").sortWithinPartitions(F.desc("square"), "vec_id")

    def cut(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in batches:
            for at in range(0, len(pdf), bucket):
                part = pdf.iloc[at : at + bucket]
                rows = list(part["v"])
                m = _matrix(rows, max(map(len, rows)))
                yield pd.DataFrame({"longest": [float(part["square"].max())], "n": [len(part)], "width": [m.shape[1]], "ids": [part["vec_id"].to_numpy(np.int64).tobytes()], "rows": [m.tobytes()]})

    return dealt.mapInPandas(cut, "longest double, n int, width int, ids binary, rows binary")


def _open(row) -> tuple[np.ndarray, np.ndarray]:
    return np.frombuffer(row["ids"], np.int64), np.frombuffer(row["rows"], np.int64).reshape(row["n"], row["width"])


def search(vectors: DataFrame, every: int, k: int = 5, bucket: int = BUCKET, group: int = GROUP) -> DataFrame:
    """The k highest scores of each query over all other rows: query_id, rank, vec_id, score.

    Queries are the rows whose vec_id is divisible by ``every``; a query's own vec_id is no
    candidate (nor a repeated row with that id); of repeated query rows that are usable the one
    with the smallest vector asks.  Components become floor(256 x).  Vectors that
    are null or hold a null or non-finite component take no part, nor do rows without an id.
    Shorter vectors count as padded with zeros.  Ties go to the smaller vec_id; repeated
    candidate rows each count.  Fewer candidates than k give fewer rows; an empty table none.
    """
    spark = vectors.sparkSession
    scratch = Scratch(spark, "topk")
    buckets = scratch.keep(layout(vectors, bucket))
    seed_row = buckets.orderBy(F.desc("longest")).limit(1).collect()
    queries = layout(vectors.where(F.col("vec_id") % every == 0), min(bucket, group), distinct=True)
    seed = Bucket(*_open(seed_row[0])) if seed_row else None
    schema = "query_id long, vec_id long, score long"
    found: list[DataFrame] = []

    def flush(blocks: list[tuple[np.ndarray, np.ndarray]]) -> None:
        width = max(m.shape[1] for _, m in blocks)
        ids = np.concatenate([i for i, _ in blocks])
        rows = np.concatenate([np.pad(m, ((0, 0), (0, width - m.shape[1]))) for _, m in blocks])
        bounds = np.full(len(ids), np.iinfo(np.int64).min)
        for a in range(0, len(ids), 512):
            scores = products(rows[a : a + 512], seed.rows)
            scores[ids[a : a + 512, None] == seed.ids[None, :]] = np.iinfo(np.int64).min
            if scores.shape[1] >= k:
                bounds[a : a + 512] = np.partition(scores, scores.shape[1] - k, axis=1)[:, scores.shape[1] - k]
        held = spark.sparkContext.broadcast((ids, rows, np.sqrt((rows.astype(np.float64) ** 2).sum(axis=1)), bounds))

        def scan(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            q_ids, q_rows, norms, least = held.value
            for pdf in batches:
                for row in pdf.to_dict("records"):
                    own = Bucket(*_open(row))
                    out = []
                    for i in range(len(q_ids)):
                        at = own.reachable(q_rows[i], norms[i], float(least[i]))
                        if not len(at):
                            continue
                        scores = own.scores(q_rows[i], at)
                        good = (scores >= least[i]) & (own.ids[at] != q_ids[i])
                        at, scores = at[good], scores[good]
                        top = best(scores, own.ids[at], k)
                        out.append((np.full(len(top), q_ids[i]), own.ids[at[top]], scores[top]))
                    if out:
                        a, b, c = (np.concatenate(x) for x in zip(*out, strict=True))
                        yield pd.DataFrame({"query_id": a, "vec_id": b, "score": c})

        found.append(buckets.repartition(min(4096, max(1, n_buckets))).mapInPandas(scan, schema))
        if len(found) > 1:
            found[-1] = scratch.keep(found[-1])
            held.unpersist()

    n_buckets = buckets.count()
    blocks: list[tuple[np.ndarray, np.ndarray]] = []
    for row in queries.toLocalIterator():
        blocks.append(_open(row))
        if sum(len(i) for i, _ in blocks) >= group:
            flush(blocks)
            blocks = []
    if blocks:
        flush(blocks)
    if not found:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    out = found[0]
    for more in found[1:]:
        out = out.unionByName(more)
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return out.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def digest(vectors: DataFrame) -> DataFrame:
    return search(vectors, every=50, k=5)


ORACLE = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS e
  FROM embeddings
  WHERE vec_id IS NOT NULL AND embedding IS NOT NULL
    AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT q.vec_id AS query_id, c.vec_id AS vec_id,
         CAST(list_sum(list_transform(list_zip(q.e, c.e), lambda p: p[1] * p[2])) AS BIGINT) AS score
  FROM v q JOIN v c ON q.vec_id % 50 = 0 AND c.vec_id <> q.vec_id
), r AS (
  SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score FROM s
)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""
