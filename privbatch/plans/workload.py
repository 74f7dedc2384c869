"""Workloads: query rows as DataFrames, and Gram matrices and spectra without any rows."""

from __future__ import annotations

from functools import reduce
from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

DENSE_LIMIT = 4096


# ---- rows -------------------------------------------------------------------------------------


def range_boxes(spark: SparkSession, dims: tuple[int, ...]) -> DataFrame:
    """(query_id, lo0, hi0, ...) of all ranges; generated lazily from per-axis intervals."""
    out = None
    for k, d in enumerate(dims):
        lo = spark.range(d).select(F.col("id").alias(f"lo{k}"))
        axis = lo.select(f"lo{k}", F.explode(F.sequence(F.col(f"lo{k}"), F.lit(d - 1).cast("long"))).alias(f"hi{k}"))
        out = axis if out is None else out.crossJoin(axis)
    number = F.lit(0).cast("long")
    for k, d in enumerate(dims):
        number = (number * d + F.col(f"lo{k}")) * d + F.col(f"hi{k}")
    return out.select(number.alias("query_id"), *out.columns)


def box_rows(boxes: DataFrame, dims: tuple[int, ...]) -> DataFrame:
    """(query_id, cell_id, coef) of boxes."""
    out = boxes
    for k in range(len(dims)):
        out = out.withColumn(f"c{k}", F.explode(F.sequence(F.col(f"lo{k}"), F.col(f"hi{k}"))))
    cell = reduce(lambda a, k: a * dims[k] + F.col(f"c{k}"), range(len(dims)), F.lit(0).cast("long"))
    return out.select("query_id", cell.alias("cell_id"), F.lit(1.0).alias("coef"))


def predicate_rows(spark: SparkSession, n: int) -> DataFrame:
    """All 2^n predicates over n cells; query_id is the mask."""
    if n > 16:
        raise ValueError("rows of all predicates need n <= 16; the Gram matrix has a closed form for any n")
    masks = spark.range(2**n).select(F.col("id").alias("query_id"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long"))).alias("cell_id"))
    return masks.where(F.expr("shiftright(query_id, cast(cell_id as int)) & 1") == 1).withColumn("coef", F.lit(1.0))


def marginal_rows(spark: SparkSession, dims: tuple[int, ...], subsets: list[tuple[int, ...]]) -> DataFrame:
    """Rows of the marginals of the given attribute subsets."""
    n = int(np.prod(dims))
    cells = spark.range(n).select(F.col("id").alias("cell_id"))
    strides = [int(np.prod(dims[k + 1 :])) for k in range(len(dims))]
    first, out = 0, []
    for s in subsets:
        number = F.lit(0).cast("long")
        for k in s:
            number = number * dims[k] + F.expr(f"(cell_id div {strides[k]}) % {dims[k]}")
        out.append(cells.select((number + first).alias("query_id"), "cell_id", F.lit(1.0).alias("coef")))
        first += int(np.prod([dims[k] for k in s], dtype=np.int64))
    return reduce(DataFrame.unionByName, out)


def cube_subsets(k: int, most: int | None = None) -> list[tuple[int, ...]]:
    return [s for r in range((k if most is None else most) + 1) for s in combinations(range(k), r)]


def sample(boxes: DataFrame, m: int, seed: int, dims: tuple[int, ...], method: str = "uniform", rate: float | None = None, outer: bool = True) -> DataFrame:
    """m distinct boxes; biased ones have weight exp(rate distance of the box's centre from the domain's centre).

    A weighted draw without replacement: the m smallest exponential keys, -ln(u) / weight.
    """
    from ..functions.noise import uniform

    key = -F.log(uniform(seed, F.col("query_id")))
    if method == "biased":
        away = sum((F.abs((F.col(f"lo{k}") + F.col(f"hi{k}")) / 2 - (d - 1) / 2) / (d / 2) for k, d in enumerate(dims)), F.lit(0.0)) / len(dims)
        key = key * F.exp(F.lit((-1 if outer else 1) * (4.0 if rate is None else rate)) * away)
    return boxes.withColumn("key", key).orderBy("key", "query_id").limit(m).drop("key")


def coverage(dims: tuple[int, ...]) -> F.Column:
    """Share of the cells in a box."""
    volume = reduce(lambda a, k: a * (F.col(f"hi{k}") - F.col(f"lo{k}") + 1), range(len(dims)), F.lit(1).cast("long"))
    return volume / F.lit(float(np.prod(dims)))


def gram_of_rows(rows: DataFrame) -> DataFrame:
    """(i, j, v), i <= j, of explicit rows by one self-join."""
    other = rows.select("query_id", F.col("cell_id").alias("j"), F.col("coef").alias("d"))
    both = rows.join(other, "query_id").where("cell_id <= j")
    return both.groupBy(F.col("cell_id").alias("i"), "j").agg(F.sum(F.col("coef") * F.col("d")).alias("v"))


def equivalent(a: np.ndarray, b: np.ndarray, tol: float = 1e-9) -> bool:
    """Two workloads with the same Gram matrix have the same bound and the same best strategies."""
    return a.shape == b.shape and bool(np.allclose(a, b, rtol=tol, atol=tol))


# ---- Gram matrices and spectra in closed form ---------------------------------------------------


def kron(parts: list[np.ndarray]) -> np.ndarray:
    return reduce(np.kron, parts)


def gram_all_range(dims: tuple[int, ...]) -> np.ndarray:
    def axis(n: int) -> np.ndarray:
        i = np.arange(1, n + 1)
        return (np.minimum.outer(i, i) * (n + 1 - np.maximum.outer(i, i))).astype(float)

    return kron([axis(n) for n in dims])


def gram_predicates(n: int) -> np.ndarray:
    return 2.0 ** (n - 2) * (np.eye(n) + np.ones((n, n)))


def gram_marginals(dims: tuple[int, ...], subsets: list[tuple[int, ...]]) -> np.ndarray:
    return sum(kron([np.eye(d) if k in s else np.ones((d, d)) for k, d in enumerate(dims)]) for s in subsets)


def gram_boxes(lo: np.ndarray, hi: np.ndarray, dims: tuple[int, ...]) -> np.ndarray:
    """Gram matrix of explicit boxes (m, k), inclusive."""
    n = int(np.prod(dims))
    g, axes = np.zeros((n, n)), [np.arange(d) for d in dims]
    for a in range(0, len(lo), 512):
        rows = np.ones((min(512, len(lo) - a), 1))
        for k in range(len(dims)):
            inside = (axes[k] >= lo[a : a + 512, k, None]) & (axes[k] <= hi[a : a + 512, k, None])
            rows = (rows[:, :, None] * inside[:, None, :]).reshape(len(rows), -1)
        g += rows.T @ rows
    return g


def gram_of_boxes(boxes: DataFrame, dims: tuple[int, ...]) -> np.ndarray:
    """Gram matrix of a DataFrame of boxes: every task sums its own boxes, so what reaches the driver is a matrix a task at most.

    The matrices are added by row blocks in a shuffle before they are fetched.
    """
    import pandas as pd

    n, names = int(np.prod(dims)), [c for k in range(len(dims)) for c in (f"lo{k}", f"hi{k}")]

    def run(batches):
        own = np.zeros((n, n))
        for pdf in batches:
            at = pdf[names].to_numpy(np.int64)
            own += gram_boxes(at[:, ::2], at[:, 1::2], dims)
        yield pd.DataFrame({"i": np.arange(n), "row": list(own)})

    rows = boxes.select(*names).mapInPandas(run, "i long, row array<double>")
    added = rows.select("i", F.posexplode("row").alias("j", "v")).where("v <> 0").groupBy("i", "j").agg(F.sum("v").alias("v"))
    got, out = added.toArrow(), np.zeros((n, n))
    out[got["i"].to_numpy(), got["j"].to_numpy()] = got["v"].to_numpy()
    return out


def spectrum_all_range(n: int) -> np.ndarray:
    """Eigenvalues of the one-dimensional range Gram matrix: (n+1) times the inverse of the second difference."""
    return (n + 1) / (4 * np.sin(np.arange(1, n + 1) * np.pi / (2 * (n + 1))) ** 2)

