"""Releases: measure a strategy with calibrated noise, fit the cells, answer the workload on the fit.

Only functions whose name begins with ``exact_`` return true answers; they are for tests.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.noise import gauss_sigma, gaussian, laplace, laplace_scale
from ..plans.strategy import l1, l2
from ..plans.workload import DENSE_LIMIT


def rows_frame(spark: SparkSession, a: np.ndarray) -> DataFrame:
    """(query_id, cell_id, coef) of a dense matrix of bounded size."""
    q, c = np.nonzero(a)
    return spark.createDataFrame(pa.table({"query_id": q.astype(np.int64), "cell_id": c.astype(np.int64), "coef": a[q, c].astype(float)}))


def sensitivities(rows: DataFrame) -> DataFrame:
    """(l1, l2): the largest column norms of the rows, which is what one record can change."""
    column = rows.groupBy("cell_id").agg(F.sum(F.abs("coef")).alias("a"), F.sum(F.col("coef") * F.col("coef")).alias("b"))
    return column.agg(F.max("a").alias("l1"), F.sqrt(F.max("b")).alias("l2"))


def exact_sensitivity(rows: DataFrame, n: int) -> DataFrame:
    """(l1, l2) by trying every neighbour: the answers before and after one record less in each cell; for tests on few cells."""
    cells = rows.sparkSession.range(n).select(F.col("id").alias("removed"))
    queries = rows.groupBy("query_id").agg(F.map_from_entries(F.collect_list(F.struct("cell_id", "coef"))).alias("row"))
    moved = F.coalesce(F.col("row")[F.col("removed")], F.lit(0.0))
    each = cells.join(queries).groupBy("removed").agg(F.sum(F.abs(moved)).alias("a"), F.sum(moved * moved).alias("b"))
    return each.agg(F.max("a").alias("l1"), F.sqrt(F.max("b")).alias("l2"))


def sensitivity_boxes(boxes: DataFrame, dims: tuple[int, ...], coef: str = "coef") -> DataFrame:
    """(l1, l2) of weighted boxes (lo0, hi0, ..., coef) without their cells: corners, then running sums over the domain."""
    from functools import reduce

    from .cells import densify, prefix_sums

    corners = []
    for mask in range(2 ** len(dims)):
        at, inside, sign = F.lit(0).cast("long"), F.lit(True), 1
        for k, d in enumerate(dims):
            behind = bool(mask >> k & 1)
            c = F.col(f"hi{k}") + 1 if behind else F.col(f"lo{k}")
            at, inside, sign = at * d + c, inside & (c < d), -sign if behind else sign
        corners.append(F.struct(F.when(inside, at).alias("cell_id"), F.lit(float(sign)).alias("sign")))
    rows = boxes.select(F.col(coef).alias("w"), F.inline(F.array(*corners))).where("cell_id IS NOT NULL")
    n = reduce(lambda a, b: a * b, dims, 1)
    out = []
    for name, weight in (("l1", F.abs("w")), ("l2", F.col("w") * F.col("w"))):
        steps = rows.groupBy("cell_id").agg(F.sum(F.col("sign") * weight).alias("cnt"))
        full = densify(steps, n).select("cell_id", F.col("cnt").cast("double").alias("cnt"))
        top = prefix_sums(full, "cnt", dims).agg(F.max("total").alias(name))
        out.append(top if name == "l1" else top.select(F.sqrt("l2").alias("l2")))
    return out[0].join(out[1])


def exact_answers(rows: DataFrame, cells: DataFrame) -> DataFrame:
    return rows.join(cells, "cell_id").groupBy("query_id").agg(F.sum(F.col("coef") * F.col("cnt")).alias("answer"))


def gaussian_answers(rows: DataFrame, cells: DataFrame, sens: float, eps: float, delta: float, seed: int, secret: Column | None = None) -> DataFrame:
    """(query_id, noisy) under (eps, delta); ``sens`` is the rows' L2 sensitivity."""
    noise = F.lit(gauss_sigma(sens, eps, delta)) * gaussian(seed, F.col("query_id"), secret)
    return exact_answers(rows, cells).select("query_id", (F.col("answer") + noise).alias("noisy"))


def laplace_answers(rows: DataFrame, cells: DataFrame, sens: float, eps: float, seed: int, secret: Column | None = None) -> DataFrame:
    """(query_id, noisy) under eps alone; ``sens`` is the rows' L1 sensitivity."""
    noise = F.lit(laplace_scale(sens, eps)) * laplace(seed, F.col("query_id"), secret)
    return exact_answers(rows, cells).select("query_id", (F.col("answer") + noise).alias("noisy"))


def fit_dense(measured: DataFrame, a: np.ndarray) -> DataFrame:
    """(cell_id, est): least squares on the driver, for at most ``DENSE_LIMIT`` cells."""
    if a.shape[1] > DENSE_LIMIT:
        raise ValueError(f"{a.shape[1]} cells exceed {DENSE_LIMIT}: use fit_haar, fit_cg, a product or a separated strategy")
    y = np.zeros(len(a))
    for r in measured.collect():
        y[r["query_id"]] = r["noisy"]
    x = np.linalg.lstsq(a, y, rcond=None)[0]
    return measured.sparkSession.createDataFrame([(i, float(v)) for i, v in enumerate(x)], "cell_id long, est double")


def haar_rows(spark: SparkSession, n: int) -> DataFrame:
    """The Haar strategy over n = 2^k cells as rows (query_id, cell_id, coef), generated, never collected."""
    k = n.bit_length() - 1
    cell = spark.range(n).select(F.col("id").alias("cell_id"), F.explode(F.sequence(F.lit(0), F.lit(k))).alias("level"))
    # The support of a row of level l > 0 is n / 2^(l-1); level 0 is the total.
    out = cell.withColumn("w", F.expr(f"if(level = 0, {n}L, shiftright({n}L, level - 1))"))
    number = F.expr("if(level = 0, 0L, shiftleft(1L, level - 1) + cell_id div w)")
    sign = F.when((F.col("level") > 0) & (F.expr("(cell_id % w) * 2 >= w")), -1.0).otherwise(1.0)
    return out.select(number.alias("query_id"), "cell_id", sign.alias("coef"), "w")


def fit_haar(measured: DataFrame, n: int) -> DataFrame:
    """Least squares for the Haar strategy: its rows are orthogonal, so each adds its noisy answer over its squared length."""
    rows = haar_rows(measured.sparkSession, n)
    return rows.join(measured, "query_id").groupBy("cell_id").agg(F.sum(F.col("coef") * F.col("noisy") / F.col("w")).alias("est"))


def fit_cg(rows: DataFrame, measured: DataFrame, scratch_cut, tol: float = 1e-10, max_steps: int = 200) -> DataFrame:
    """Conjugate gradients on the normal equations: two joins with aggregation a step, for many cells.

    ``scratch_cut`` writes a table and reads it back (it cuts the lineage every step).
    """

    def apply(v: DataFrame) -> DataFrame:
        u = rows.join(v, "cell_id").groupBy("query_id").agg(F.sum(F.col("coef") * F.col("p")).alias("u"))
        return rows.join(u, "query_id").groupBy("cell_id").agg(F.sum(F.col("coef") * F.col("u")).alias("q"))

    r = rows.join(measured, "query_id").groupBy("cell_id").agg(F.sum(F.col("coef") * F.col("noisy")).alias("r"))
    state = scratch_cut(r.select("cell_id", F.lit(0.0).alias("x"), "r", F.col("r").alias("p")))
    rho = first = state.agg(F.sum(F.col("r") * F.col("r"))).first()[0] or 0.0
    for _ in range(max_steps):
        if rho <= tol * tol * first or rho == 0:
            break
        both = scratch_cut(state.join(apply(state.select("cell_id", "p")), "cell_id"))
        alpha = rho / both.agg(F.sum(F.col("p") * F.col("q"))).first()[0]
        moved = both.select("cell_id", (F.col("x") + alpha * F.col("p")).alias("x"), (F.col("r") - alpha * F.col("q")).alias("r"), "p")
        new = moved.agg(F.sum(F.col("r") * F.col("r"))).first()[0]
        state = scratch_cut(moved.select("cell_id", "x", "r", (F.col("r") + F.lit(new / rho) * F.col("p")).alias("p")))
        rho = new
    return state.select("cell_id", F.col("x").alias("est"))


def release(cells: DataFrame, a: np.ndarray, eps: float, delta: float | None, seed: int, secret: Column | None = None) -> DataFrame:
    """(cell_id, est) under a dense strategy; delta None means eps alone (Laplace, L1)."""
    rows = rows_frame(cells.sparkSession, a)
    if delta is None:
        measured = laplace_answers(rows, cells, l1(a), eps, seed, secret)
    else:
        measured = gaussian_answers(rows, cells, l2(a), eps, delta, seed, secret)
    return fit_dense(measured, a)


def release_direct(cells: DataFrame, w: np.ndarray, a: np.ndarray, eps: float, delta: float, seed: int) -> DataFrame:
    """(query_id, answer) in closed form: the true answers plus W A^+ applied to the strategy's noise; the check of ``release``."""
    spread = w @ np.linalg.pinv(a)
    spark = cells.sparkSession
    noise = F.lit(gauss_sigma(l2(a), eps, delta)) * gaussian(seed, F.col("cell_id"))
    moved = rows_frame(spark, spread).groupBy("query_id").agg(F.sum(F.col("coef") * noise).alias("noise"))
    true = exact_answers(rows_frame(spark, w), cells)
    return true.join(moved, "query_id", "left").select("query_id", (F.col("answer") + F.coalesce("noise", F.lit(0.0))).alias("answer"))


def release_haar(cells: DataFrame, n: int, eps: float, delta: float, seed: int, secret: Column | None = None) -> DataFrame:
    """The same for the Haar strategy, without a driver round trip."""
    rows = haar_rows(cells.sparkSession, n).select("query_id", "cell_id", "coef")
    sens = float(np.sqrt(n.bit_length()))
    return fit_haar(gaussian_answers(rows, cells, sens, eps, delta, seed, secret), n)
