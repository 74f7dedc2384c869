"""Least squares for strategies with a known shape, without the cells ever meeting in one place.

``fit_tree`` for full trees of counts, ``fit_factors`` for products of small strategies, and
``fit_with_inverse`` where the inverse of A'A is at hand from the search.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.noise import gauss_sigma, gaussian
from ..plans.strategy import l2
from ..plans.workload import DENSE_LIMIT

# ---- trees ----------------------------------------------------------------------------------------


def tree_height(n: int, fanout: int = 2) -> int:
    """Levels below the root of the full tree over n cells."""
    k = 0
    while fanout**k < n:
        k += 1
    if fanout < 2 or fanout**k != n:
        raise ValueError(f"{n} cells are no power of {fanout}: pad with public empty cells")
    return k


def _ancestors(k: int, fanout: int, own: bool) -> Column:
    """(up, node): the numbers of the nodes over column cell_id, level by level from the root; up is the distance from the leaf."""
    at = [
        F.struct(F.lit(up).alias("up"), (F.lit((fanout ** (k - up) - 1) // (fanout - 1)) + F.expr(f"cell_id div {fanout**up}")).alias("node"))
        for up in range(0 if own else 1, k + 1)
    ]
    return F.inline(F.array(*at))


def tree_counts(cells: DataFrame, value: str, n: int, fanout: int = 2) -> DataFrame:
    """(query_id, answer) of all nodes of the tree: each task sums what it holds before it shuffles."""
    rows = cells.select(F.col(value).alias("v"), _ancestors(tree_height(n, fanout), fanout, True))
    return rows.groupBy(F.col("node").alias("query_id")).agg(F.sum("v").alias("answer"))


def measure_tree(cells: DataFrame, value: str, n: int, eps: float, delta: float, seed: int, fanout: int = 2, secret: Column | None = None) -> DataFrame:
    """(query_id, noisy): a record is counted once on every level, which gives the sensitivity."""
    sigma = gauss_sigma(float(np.sqrt(tree_height(n, fanout) + 1)), eps, delta)
    return tree_counts(cells, value, n, fanout).select("query_id", (F.col("answer") + F.lit(sigma) * gaussian(seed, F.col("query_id"), secret)).alias("noisy"))


def fit_tree(measured: DataFrame, n: int, fanout: int = 2) -> DataFrame:
    """(cell_id, est): least squares for a full tree whose nodes were all measured alike.

    The best estimate of a node from itself and what lies below is a weighted sum over its subtree
    with weights that depend on heights alone, so the upward pass is one aggregation over pairs of
    node and ancestor.  A leaf then takes from each node above it, halved with every level (for two
    branches), what the node's own estimate has over the sum of its children's.  Two
    exchanges of n log n rows in all, whatever the height.
    """
    k, f = tree_height(n, fanout), fanout
    first = [(f**level - 1) // (f - 1) for level in range(k + 2)]
    level = F.lit(0)
    for j in range(1, k + 1):
        level = level + (F.col("query_id") >= first[j]).cast("int")
    start = F.element_at(F.array(*[F.lit(x).cast("long") for x in first]), F.col("level") + 1)
    nodes = measured.withColumn("level", level).withColumn("at", F.col("query_id") - start)
    weight = F.pow(F.lit(float(f)), F.lit(k) - F.col("level"))  # of a node of this height
    above = F.transform(
        F.sequence(F.lit(1), F.col("level")),
        lambda up: F.struct(
            (F.floor((F.pow(F.lit(float(f)), F.col("level") - up) - 1) / (f - 1) + 0.5).cast("long") + F.floor(F.col("at") / F.pow(F.lit(float(f)), up)).cast("long")).alias("node")
        ),
    )
    below = nodes.where("level > 0").select((weight * F.col("noisy")).alias("w"), F.inline(above))
    below = below.groupBy(F.col("node").alias("query_id")).agg(F.sum("w").alias("below"))
    size = F.pow(F.lit(float(f)), F.lit(k + 1) - F.col("level"))  # f to the height, counted from one at the leaves
    over = (f - 1) * (size / f * F.col("noisy") / (size - 1) + F.col("below") * (1 / (size - 1) - 1 / (size / f - 1)))
    gaps = nodes.where(F.col("level") < k).join(below, "query_id").select(F.col("query_id").alias("node"), over.alias("gap"))
    leaves = nodes.where(F.col("level") == k).select(F.col("at").alias("cell_id"), "noisy")
    taken = leaves.select("cell_id", _ancestors(k, f, False)).join(gaps, "node")
    taken = taken.groupBy("cell_id").agg(F.sum(F.col("gap") / F.pow(F.lit(float(f)), F.col("up"))).alias("taken"))
    return leaves.join(taken, "cell_id", "left").select("cell_id", (F.col("noisy") + F.coalesce("taken", F.lit(0.0))).alias("est"))


# ---- products -------------------------------------------------------------------------------------


def _entries(spark: SparkSession, m: np.ndarray) -> DataFrame:
    """(c, r, v) of a matrix of bounded size, by column."""
    if m.size > DENSE_LIMIT**2:
        raise ValueError(f"a factor of {m.size} entries is beyond {DENSE_LIMIT**2}")
    r, c = np.nonzero(m)
    return spark.createDataFrame(pa.table({"c": c.astype(np.int64), "r": r.astype(np.int64), "v": m[r, c]}))


def apply_factors(df: DataFrame, factors: list[np.ndarray]) -> DataFrame:
    """(id, value) of the product of the factors applied to a vector (id, value) over their columns.

    One axis after the other: a join with the factor's entries, whose size is checked, and an
    aggregation, so the product matrix is never made.
    """
    dims = [f.shape[1] for f in factors]
    for k, factor in enumerate(factors):
        inner, d = int(np.prod(dims[k + 1 :], dtype=np.int64)), dims[k]
        coords = df.select(F.expr(f"id div {inner * d}").alias("outer"), F.expr(f"(id div {inner}) % {d}").alias("c"), F.expr(f"id % {inner}").alias("inner"), "value")
        joined = coords.join(F.broadcast(_entries(df.sparkSession, factor)), "c")
        dims[k] = factor.shape[0]
        number = (F.col("outer") * dims[k] + F.col("r")) * inner + F.col("inner")
        df = joined.groupBy(number.alias("id")).agg(F.sum(F.col("v") * F.col("value")).alias("value"))
    return df


def release_factors(cells: DataFrame, factors: list[np.ndarray], eps: float, delta: float, seed: int, secret: Column | None = None) -> DataFrame:
    """(cell_id, est) under the product of small strategies; its sensitivity is the product of theirs."""
    sens = float(np.prod([l2(f) for f in factors]))
    true = apply_factors(cells.select(F.col("cell_id").alias("id"), F.col("cnt").cast("double").alias("value")), factors)
    noisy = true.select("id", (F.col("value") + F.lit(gauss_sigma(sens, eps, delta)) * gaussian(seed, F.col("id"), secret)).alias("value"))
    return fit_factors(noisy, factors)


def fit_factors(noisy: DataFrame, factors: list[np.ndarray]) -> DataFrame:
    """(cell_id, est) from noisy answers (id, value): the pseudo-inverse of a product is that of its factors."""
    return apply_factors(noisy, [np.linalg.pinv(f) for f in factors]).select(F.col("id").alias("cell_id"), F.col("value").alias("est"))


# ---- with a known inverse -------------------------------------------------------------------------


def fit_with_inverse(rows: DataFrame, measured: DataFrame, inverse: np.ndarray) -> DataFrame:
    """(cell_id, est) = (A'A)^-1 A'y: a join with aggregation for A'y, and one for the inverse."""
    aty = rows.join(measured, "query_id").groupBy(F.col("cell_id").alias("c")).agg(F.sum(F.col("coef") * F.col("noisy")).alias("u"))
    joined = _entries(measured.sparkSession, inverse).join(aty, "c")
    return joined.groupBy(F.col("r").alias("cell_id")).agg(F.sum(F.col("v") * F.col("u")).alias("est"))
