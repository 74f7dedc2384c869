"""The registered queries of the engine and, where SQL can express them, their SQL for DuckDB.

Where both sides could use one closed form, the SQL takes another route.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions.noise import gauss_sigma, gaussian, laplace_scale, noise_constant
from .operators import cells as C
from .operators import mechanism as M
from .operators import solvers as V
from .plans import ir
from .plans import level_search as L
from .plans import separation as P
from .plans import strategy as S
from .plans import workload as W
from .sources.tables import domain, star, table
from .streaming.windows import calendar, release_windows, sliding_answers, window_cells

EPS, DELTA, SEED = 0.5, 1e-4, 7
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def add(f):
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLES[name or f.__name__] = sql
        return f

    return add


def _frame(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


# ---- cells ------------------------------------------------------------------------------------

_D = "date_diff('day', DATE '1995-01-01', CAST(l_shipdate AS DATE))"
_DENSE = "WITH c AS (SELECT {cell} AS cell_id, count(*) AS cnt FROM {table} WHERE {inside} GROUP BY 1) SELECT r.range AS cell_id, coalesce(c.cnt, 0) AS cnt FROM range({n}) r LEFT JOIN c ON c.cell_id = r.range"
_CELLS = {
    "ship_1024": (f"CAST(floor({_D} * 2 / 5.0) AS BIGINT)", "lineitem", f"{_D} >= 0 AND floor({_D} * 2 / 5.0) < 1024", 1024),
    "ship_price_32x32": (f"CAST(floor({_D} / 80.0) * 32 + floor(l_extendedprice / 3300) AS BIGINT)", "lineitem", f"floor({_D} / 80.0) BETWEEN 0 AND 31 AND floor(l_extendedprice / 3300) BETWEEN 0 AND 31", 1024),
    "qty_price_ship_16x8x8": (f"CAST((floor((l_quantity - 1) * 16 / 50) * 8 + floor(l_extendedprice / 13200)) * 8 + floor({_D} / 320.0) AS BIGINT)", "lineitem", f"floor((l_quantity - 1) * 16 / 50) BETWEEN 0 AND 15 AND floor(l_extendedprice / 13200) BETWEEN 0 AND 7 AND floor({_D} / 320.0) BETWEEN 0 AND 7", 1024),
    "five_4": (f"CAST((((floor((l_quantity - 1) * 4 / 50) * 4 + floor(round(l_discount * 100) / 3)) * 4 + floor(round(l_tax * 100) * 4 / 9)) * 4 + floor(l_extendedprice / 26400)) * 4 + floor({_D} / 640.0) AS BIGINT)", "lineitem", f"floor((l_quantity - 1) * 4 / 50) BETWEEN 0 AND 3 AND floor(round(l_discount * 100) / 3) BETWEEN 0 AND 3 AND floor(round(l_tax * 100) * 4 / 9) BETWEEN 0 AND 3 AND floor(l_extendedprice / 26400) BETWEEN 0 AND 3 AND floor({_D} / 640.0) BETWEEN 0 AND 3", 1024),
    "qty_64": ("CAST(floor(l_quantity - 1) AS BIGINT)", "lineitem", "floor(l_quantity - 1) BETWEEN 0 AND 63", 64),
}


def _cells(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    source = {"type_5": "events", "type_groups": "part"}.get(name, "lineitem")
    data = star(spark, sf_dir) if name == "ten_2" else table(spark, sf_dir, source)
    return C.dense_counts(data, domain(name))


for _name, (_cell, _table, _inside, _n) in _CELLS.items():
    query(_DENSE.format(cell=_cell, table=_table, inside=_inside, n=_n), f"cell_counts_{_name}")(lambda s, d, name=_name: _cells(s, d, name))

_FLAGS = ["l_quantity > 25", "round(l_discount * 100) >= 5", "round(l_tax * 100) >= 4", "l_extendedprice >= 50000", "l_shipdate >= TIMESTAMP '1998-07-01'", "l_returnflag = 'R'", "l_linestatus = 'O'", "l_linenumber >= 4", "p_size > 25", "o_orderpriority IN ('1-URGENT', '2-HIGH')"]
query(
    _DENSE.format(cell=" + ".join(f"CAST({c} AS BIGINT) * {2 ** (9 - i)}" for i, c in enumerate(_FLAGS)), table="lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey", inside="true", n=1024), "cell_counts_star"
)(lambda s, d: _cells(s, d, "ten_2"))


@query("SELECT CAST(CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END AS BIGINT) AS cell_id, count(*) AS cnt FROM events GROUP BY 1")
def cell_counts_categorical(spark, sf_dir):
    return _cells(spark, sf_dir, "type_5")


@query("WITH g AS (SELECT CAST(CASE WHEN p_type IN ('ECONOMY','STANDARD') THEN 0 WHEN p_type = 'PROMO' THEN 1 ELSE 2 END AS BIGINT) AS cell_id FROM part) SELECT r.range AS cell_id, count(g.cell_id) AS cnt FROM range(3) r LEFT JOIN g ON g.cell_id = r.range GROUP BY 1")
def cell_counts_groups(spark, sf_dir):
    return _cells(spark, sf_dir, "type_groups")


@query("SELECT 'clamp' AS policy, CAST(least(n_chars // 1024, 7) AS BIGINT) AS cell_id, count(*) AS cnt FROM documents GROUP BY 2 UNION ALL SELECT 'drop', CAST(n_chars // 1024 AS BIGINT), count(*) FROM documents WHERE n_chars // 1024 < 8 GROUP BY 2")
def cell_counts_overflow(spark, sf_dir):
    from .functions.domain import Attribute, Domain

    docs, out = table(spark, sf_dir, "documents"), None
    for policy in ("clamp", "drop"):
        d = Domain((Attribute.width("len", F.col("n_chars"), 0, 1024, 8, policy),))
        one = C.cell_counts(docs, d).select(F.lit(policy).alias("policy"), "cell_id", "cnt")
        out = one if out is None else out.unionByName(one)
    return out


@query("WITH h AS (SELECT CAST(date_diff('hour', TIMESTAMP '2024-01-01', date_trunc('hour', ts)) AS BIGINT) AS hour, event_type, count(*) AS cnt FROM events GROUP BY 1, 2) SELECT r.range AS hour, t.t AS event_type, coalesce(h.cnt, 0) AS cnt FROM range(720) r CROSS JOIN (SELECT unnest(['click','error','purchase','signup','view']) AS t) t LEFT JOIN h ON h.hour = r.range AND h.event_type = t.t")
def histogram_hourly(spark, sf_dir):
    hour = F.floor((F.unix_timestamp("ts") - F.unix_timestamp(F.lit("2024-01-01").cast("timestamp"))) / 3600).cast("long")
    seen = table(spark, sf_dir, "events").groupBy(hour.alias("hour"), "event_type").agg(F.count("*").alias("cnt"))
    types = F.array(*[F.lit(t) for t in ("click", "error", "purchase", "signup", "view")])
    every = spark.range(720).select(F.col("id").alias("hour"), F.explode(types).alias("event_type"))
    return every.join(seen, ["hour", "event_type"], "left").select("hour", "event_type", F.coalesce("cnt", F.lit(0)).alias("cnt"))


@query("SELECT CAST(cell_id // 6 AS BIGINT) AS block, count(*) AS cells, CAST(sum(cnt) AS BIGINT) AS cnt FROM (" + _DENSE.format(cell=_CELLS["qty_64"][0], table="lineitem", inside=_CELLS["qty_64"][2], n=64) + ") GROUP BY 1")
def generalize_blocks(spark, sf_dir):
    return C.coarsen(_cells(spark, sf_dir, "qty_64"), 6)


@query("WITH d AS (SELECT event_id, min(ts) AS ts, min(event_type) AS event_type FROM events GROUP BY 1) SELECT date_trunc('hour', ts) AS window_start, event_type, count(*) AS cnt FROM d GROUP BY 1, 2")
def stream_cells(spark, sf_dir):
    return window_cells(table(spark, sf_dir, "events"))


# ---- workloads and Gram matrices ----------------------------------------------------------------

_R16 = "SELECT (a.range * 16 + b.range) AS query_id, c.range AS cell_id, CAST(1 AS DOUBLE) AS coef FROM range(16) a JOIN range(16) b ON a.range <= b.range JOIN range(16) c ON c.range BETWEEN a.range AND b.range"


@query(_R16)
def workload_range_rows(spark, sf_dir):
    return W.box_rows(W.range_boxes(spark, (16,)), (16,))


@query("WITH i AS (SELECT a.range AS lo, b.range AS hi FROM range(4) a JOIN range(4) b ON a.range <= b.range) SELECT ((x.lo * 4 + x.hi) * 4 + y.lo) * 4 + y.hi AS query_id, c.range * 4 + d.range AS cell_id, CAST(1 AS DOUBLE) AS coef FROM i x CROSS JOIN i y JOIN range(4) c ON c.range BETWEEN x.lo AND x.hi JOIN range(4) d ON d.range BETWEEN y.lo AND y.hi")
def workload_kd_rows(spark, sf_dir):
    return W.box_rows(W.range_boxes(spark, (4, 4)), (4, 4))


@query("SELECT m.range AS query_id, c.range AS cell_id, CAST(1 AS DOUBLE) AS coef FROM range(32) m JOIN range(5) c ON ((m.range >> CAST(c.range AS INTEGER)) & 1) = 1")
def workload_predicates_rows(spark, sf_dir):
    return W.predicate_rows(spark, 5)


_MARG = "SELECT c.range // 22 AS query_id, c.range AS cell_id, CAST(1 AS DOUBLE) AS coef FROM range(66) c UNION ALL SELECT 3 + (c.range // 11) % 2, c.range, 1 FROM range(66) c UNION ALL SELECT 5 + c.range % 11, c.range, 1 FROM range(66) c"


@query(_MARG)
def workload_marginal_rows(spark, sf_dir):
    return W.marginal_rows(spark, (3, 2, 11), [(0,), (1,), (2,)])


def _gram_frame(spark, g):
    return _frame(spark, [(i, j, float(g[i, j])) for i in range(len(g)) for j in range(i, len(g))], "i long, j long, v double")


_GRAM = "WITH w AS ({rows}) SELECT a.cell_id AS i, b.cell_id AS j, sum(a.coef * b.coef) AS v FROM w a JOIN w b ON a.query_id = b.query_id AND a.cell_id <= b.cell_id GROUP BY 1, 2"
query(_GRAM.format(rows=_R16), "gram_all_range_1d")(lambda s, d: _gram_frame(s, W.gram_all_range((16,))))
query(_GRAM.format(rows=ORACLES["workload_kd_rows"]), "gram_all_range_2d")(lambda s, d: _gram_frame(s, W.gram_all_range((4, 4))))
query(_GRAM.format(rows=ORACLES["workload_predicates_rows"]), "gram_predicates")(lambda s, d: _gram_frame(s, W.gram_predicates(5)))
query(_GRAM.format(rows=_R16), "gram_joined")(lambda s, d: W.gram_of_rows(W.box_rows(W.range_boxes(s, (16,)), (16,))))
query(
    "SELECT i, j, v FROM (" + _GRAM.format(rows=_MARG) + ")", "gram_marginals"
)(lambda s, d: _gram_frame(s, W.gram_marginals((3, 2, 11), [(0,), (1,), (2,)])).where("v <> 0"))

_U = "((CAST('0x' || substr(md5('{seed}:' || {key} || ':{lane}'), 1, 13) AS BIGINT) + 0.5) / 4503599627370496.0)"


def _u(key: str, lane: int = 0) -> str:
    return _U.format(seed=SEED, key=f"CAST({key} AS VARCHAR)", lane=lane)


_B64 = "(SELECT a.range * 64 + b.range AS query_id, a.range AS lo0, b.range AS hi0 FROM range(64) a JOIN range(64) b ON a.range <= b.range)"


@query(f"SELECT query_id, lo0, hi0 FROM {_B64} ORDER BY -ln({_u('query_id')}), query_id LIMIT 100")
def sample_uniform(spark, sf_dir):
    return W.sample(W.range_boxes(spark, (64,)), 100, SEED, (64,))


@query(f"SELECT query_id, lo0, hi0 FROM {_B64} ORDER BY -ln({_u('query_id')}) * exp(-4.0 * (abs((lo0 + hi0) / 2.0 - 31.5) / 32.0)), query_id LIMIT 100")
def sample_biased(spark, sf_dir):
    return W.sample(W.range_boxes(spark, (64,)), 100, SEED, (64,), "biased")


@query(f"SELECT query_id, (hi0 - lo0 + 1) / 64.0 AS coverage FROM {_B64} WHERE (hi0 - lo0 + 1) / 64.0 BETWEEN 0.05 AND 0.1 ORDER BY -ln({_u('query_id')}), query_id LIMIT 50")
def sample_coverage(spark, sf_dir):
    boxes = W.range_boxes(spark, (64,)).where(W.coverage((64,)).between(0.05, 0.1))
    return W.sample(boxes, 50, SEED, (64,)).select("query_id", W.coverage((64,)).alias("coverage"))


_HAAR = "SELECT CAST(0 AS BIGINT) AS query_id, c.range AS cell_id, CAST(1 AS DOUBLE) AS coef, CAST({n} AS BIGINT) AS w FROM range({n}) c UNION ALL SELECT CAST(pow(2, l.range) AS BIGINT) + c.range // ({n} // CAST(pow(2, l.range) AS BIGINT)), c.range, CASE WHEN (c.range % ({n} // CAST(pow(2, l.range) AS BIGINT))) * 2 < {n} // CAST(pow(2, l.range) AS BIGINT) THEN 1 ELSE -1 END, {n} // CAST(pow(2, l.range) AS BIGINT) FROM range({k}) l CROSS JOIN range({n}) c"
_TREE = "SELECT CAST(pow(2, l.range) AS BIGINT) + c.range // ({n} // CAST(pow(2, l.range) AS BIGINT)) AS query_id, c.range AS cell_id, CAST(1 AS DOUBLE) AS coef FROM range({k1}) l CROSS JOIN range({n}) c"
_SENS = "SELECT '{name}' AS name, round(max(a), 6) AS l1, round(sqrt(max(b)), 6) AS l2 FROM (SELECT cell_id, sum(abs(coef)) AS a, sum(coef * coef) AS b FROM ({rows}) GROUP BY 1)"


@query(" UNION ALL ".join(_SENS.format(name=k, rows=v) for k, v in {"range": _R16, "haar": _HAAR.format(n=16, k=4), "tree": _TREE.format(n=16, k1=5), "marginals": _MARG}.items()))
def sensitivity(spark, sf_dir):
    rows = {"range": W.box_rows(W.range_boxes(spark, (16,)), (16,)), "haar": M.haar_rows(spark, 16).select("query_id", "cell_id", "coef"), "tree": M.rows_frame(spark, S.hierarchical(16)), "marginals": W.marginal_rows(spark, (3, 2, 11), [(0,), (1,), (2,)])}
    out = [M.sensitivities(r).select(F.lit(k).alias("name"), F.round("l1", 6).alias("l1"), F.round("l2", 6).alias("l2")) for k, r in rows.items()]
    return out[0].unionByName(out[1]).unionByName(out[2]).unionByName(out[3])


# ---- true answers (for tests) and plain mechanisms ------------------------------------------------


@query(f"SELECT query_id, lo0, hi0, CAST(count(l_quantity) AS BIGINT) AS answer FROM {_B64} b LEFT JOIN lineitem ON floor(l_quantity - 1) BETWEEN lo0 AND hi0 GROUP BY 1, 2, 3")
def exact_range_answers(spark, sf_dir):
    return C.box_answers(W.range_boxes(spark, (64,)), _cells(spark, sf_dir, "qty_64"), "cnt", (64,))


@query("WITH i AS (SELECT a.range AS lo, b.range AS hi FROM range(8) a JOIN range(8) b ON a.range <= b.range), g AS (SELECT floor((l_quantity - 1) * 8 / 50) AS q, floor(l_extendedprice * 8 / 105600) AS p, count(*) AS c FROM lineitem GROUP BY 1, 2) SELECT ((x.lo * 8 + x.hi) * 8 + y.lo) * 8 + y.hi AS query_id, x.lo AS lo0, x.hi AS hi0, y.lo AS lo1, y.hi AS hi1, CAST(coalesce(sum(c), 0) AS BIGINT) AS answer FROM i x CROSS JOIN i y LEFT JOIN g ON q BETWEEN x.lo AND x.hi AND p BETWEEN y.lo AND y.hi GROUP BY ALL")
def exact_range_answers_2d(spark, sf_dir):
    return C.box_answers(W.range_boxes(spark, (8, 8)), _cells(spark, sf_dir, "pair_8x8"), "cnt", (8, 8))


@query("SELECT l_returnflag, l_linestatus, grouping_id(l_returnflag, l_linestatus) AS gid, count(*) AS cnt FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def exact_cube(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.grouping_id().alias("gid"), F.count("*").alias("cnt"))


@query("SELECT m.range AS query_id, CAST(coalesce(sum(CASE WHEN ((m.range >> CAST(e.c AS INTEGER)) & 1) = 1 THEN e.n END), 0) AS BIGINT) AS answer FROM range(1, 32) m CROSS JOIN (SELECT CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END AS c, count(*) AS n FROM events GROUP BY 1) e GROUP BY 1")
def exact_predicates(spark, sf_dir):
    return M.exact_answers(W.predicate_rows(spark, 5), _cells(spark, sf_dir, "type_5")).select("query_id", F.col("answer").cast("long").alias("answer"))


_QTY = "(" + _DENSE.format(cell=_CELLS["qty_64"][0], table="lineitem", inside=_CELLS["qty_64"][2], n=64) + ")"
_GAUSS = "sqrt(-2 * ln({u})) * cos(2 * pi() * {v})"
_SIGMA = gauss_sigma(1.0, EPS, DELTA)


def _g(key: str) -> str:
    return _GAUSS.format(u=_u(key), v=_u(key, 1))


@query(f"SELECT cell_id AS query_id, round(cnt + {_SIGMA!r} * {_g('cell_id')}, 6) AS answer FROM {_QTY}")
def gaussian_release(spark, sf_dir):
    rows = spark.range(64).select(F.col("id").alias("query_id"), F.col("id").alias("cell_id"), F.lit(1.0).alias("coef"))
    return M.gaussian_answers(rows, _cells(spark, sf_dir, "qty_64"), 1.0, EPS, DELTA, SEED).select("query_id", F.round("noisy", 6).alias("answer"))


@query(f"SELECT cell_id AS query_id, round(cnt - {laplace_scale(1.0, EPS)!r} * sign({_u('cell_id')} - 0.5) * ln(1 - 2 * abs({_u('cell_id')} - 0.5)), 6) AS answer FROM {_QTY}")
def laplace_release(spark, sf_dir):
    rows = spark.range(64).select(F.col("id").alias("query_id"), F.col("id").alias("cell_id"), F.lit(1.0).alias("coef"))
    return M.laplace_answers(rows, _cells(spark, sf_dir, "qty_64"), 1.0, EPS, SEED).select("query_id", F.round("noisy", 6).alias("answer"))


def _ranges_of(spark, fit, n=64):
    out = C.box_answers(W.range_boxes(spark, (n,)), fit, "est", (n,))
    return out.select(F.col("lo0").alias("lo"), F.col("hi0").alias("hi"), F.round("answer", 6).alias("answer"))


_FIT_RANGES = "SELECT lo0 AS lo, hi0 AS hi, round(sum(est), 6) AS answer FROM {boxes} b JOIN ({fit}) f ON f.cell_id BETWEEN lo0 AND hi0 GROUP BY 1, 2"


@query(_FIT_RANGES.format(boxes=_B64, fit=f"SELECT cell_id, cnt + {_SIGMA!r} * {_g('cell_id')} AS est FROM {_QTY}"))
def release_identity(spark, sf_dir):
    cells = _cells(spark, sf_dir, "qty_64")
    rows = spark.range(64).select(F.col("id").alias("query_id"), F.col("id").alias("cell_id"), F.lit(1.0).alias("coef"))
    noisy = M.gaussian_answers(rows, cells, 1.0, EPS, DELTA, SEED)
    return _ranges_of(spark, noisy.select(F.col("query_id").alias("cell_id"), F.col("noisy").alias("est")))


_HAAR64 = _HAAR.format(n=64, k=6)


@query(_FIT_RANGES.format(boxes=_B64, fit=f"WITH h AS ({_HAAR64}), y AS (SELECT query_id, sum(coef * cnt) + {gauss_sigma(7**0.5, EPS, DELTA)!r} * {_g('query_id')} AS y FROM h JOIN {_QTY} x USING (cell_id) GROUP BY 1) SELECT cell_id, sum(coef * y / w) AS est FROM h JOIN y USING (query_id) GROUP BY 1"))
def release_haar(spark, sf_dir):
    return _ranges_of(spark, M.release_haar(_cells(spark, sf_dir, "qty_64"), 64, EPS, DELTA, SEED))


_TREE64 = _TREE.format(n=64, k1=7)


@query(_FIT_RANGES.format(boxes=_B64, fit=f"WITH a AS ({_TREE64}), h AS ({_HAAR64}), y AS (SELECT query_id, sum(coef * cnt) + {gauss_sigma(7**0.5, EPS, DELTA)!r} * {_g('query_id - 1')} AS y FROM a JOIN {_QTY} x USING (cell_id) GROUP BY 1), v AS (SELECT cell_id, sum(coef * y) AS v FROM a JOIN y USING (query_id) GROUP BY 1), p AS (SELECT query_id, sum(coef * v) / (max(w) * CASE WHEN query_id = 0 THEN 127 ELSE max(w) - 1 END) AS p FROM h JOIN v USING (cell_id) GROUP BY 1) SELECT cell_id, sum(coef * p) AS est FROM h JOIN p USING (query_id) GROUP BY 1"))
def release_tree(spark, sf_dir):
    noisy = V.measure_tree(_cells(spark, sf_dir, "qty_64"), "cnt", 64, EPS, DELTA, SEED)
    return _ranges_of(spark, V.fit_tree(noisy, 64))


_HAAR8 = _HAAR.format(n=8, k=3)


@query(
    f"WITH h AS ({_HAAR8}), x AS (SELECT a.range AS c0, b.range AS c1, count(q) AS cnt FROM range(8) a CROSS JOIN range(8) b LEFT JOIN (SELECT floor((l_quantity - 1) * 8 / 50) AS q, floor(l_extendedprice * 8 / 105600) AS p FROM lineitem) l ON q = a.range AND p = b.range GROUP BY 1, 2), "
    f"y AS (SELECT h.query_id * 8 + k.query_id AS query_id, h.query_id AS r0, k.query_id AS r1, max(h.w) * max(k.w) AS w, sum(h.coef * k.coef * cnt) + {gauss_sigma(4.0, EPS, DELTA)!r} * {_g('h.query_id * 8 + k.query_id')} AS y FROM x JOIN h ON h.cell_id = c0 JOIN h k ON k.cell_id = c1 GROUP BY h.query_id, k.query_id) "
    "SELECT h.cell_id * 8 + k.cell_id AS cell_id, round(sum(h.coef * k.coef * y / y.w), 6) AS est FROM y JOIN h ON h.query_id = r0 JOIN h k ON k.query_id = r1 GROUP BY 1"
)
def release_product(spark, sf_dir):
    """A product of wavelets over two axes, measured and fitted axis by axis."""
    fit = V.release_factors(_cells(spark, sf_dir, "pair_8x8"), [S.haar(8), S.haar(8)], EPS, DELTA, SEED)
    return fit.select("cell_id", F.round("est", 6).alias("est"))


_EXACT = f"SELECT lo0 AS lo, hi0 AS hi, CAST(count(l_quantity) AS BIGINT) AS exact, true AS close FROM {_B64} b LEFT JOIN lineitem ON floor(l_quantity - 1) BETWEEN lo0 AND hi0 GROUP BY 1, 2"


def _close(spark, sf_dir, a, fit, noise=None):
    """Released ranges beside the true ones, which six standard deviations of their own expected error hold."""
    cells = _cells(spark, sf_dir, "qty_64")
    inv = np.linalg.pinv(a.T @ a, hermitian=True) * (noise or gauss_sigma(S.l2(a), EPS, DELTA)) ** 2
    table = np.zeros((65, 65))
    table[1:, 1:] = inv.cumsum(axis=0).cumsum(axis=1)
    rows = [(lo * 64 + hi, float(np.sqrt(table[hi + 1, hi + 1] - 2 * table[lo, hi + 1] + table[lo, lo]))) for lo in range(64) for hi in range(lo, 64)]
    boxes = W.range_boxes(spark, (64,)).join(_frame(spark, rows, "query_id long, sd double"), "query_id")
    both = C.box_answers(boxes, cells, "cnt", (64,)).withColumnRenamed("answer", "exact").join(C.box_answers(W.range_boxes(spark, (64,)), fit, "est", (64,)).select("query_id", "answer"), "query_id")
    return both.select(F.col("lo0").alias("lo"), F.col("hi0").alias("hi"), "exact", (F.abs(F.col("answer") - F.col("exact")) <= 6 * F.col("sd")).alias("close"))


@query(_EXACT)
def release_level(spark, sf_dir):
    """A searched strategy, fitted with the inverse that the search knows."""
    cells, a = _cells(spark, sf_dir, "qty_64"), L.level_search(W.gram_all_range((64,)), (64,), 16).matrix()
    rows = M.rows_frame(spark, a)
    noisy = M.gaussian_answers(rows, cells, S.l2(a), EPS, DELTA, SEED)
    return _close(spark, sf_dir, a, V.fit_with_inverse(rows, noisy, np.linalg.inv(a.T @ a)))


@query(_EXACT)
def release_generalized(spark, sf_dir):
    a = L.generalized_strategy(W.gram_all_range((64,)), spark=spark)
    return _close(spark, sf_dir, a, M.release(_cells(spark, sf_dir, "qty_64"), a, EPS, DELTA, SEED))


@query(_EXACT)
def release_pure(spark, sf_dir):
    """The wavelet under eps alone: Laplace noise and L1 sensitivity."""
    a = S.haar(64)
    fit = M.release(_cells(spark, sf_dir, "qty_64"), a, EPS, None, SEED)
    return _close(spark, sf_dir, a, fit, laplace_scale(S.l1(a), EPS) * np.sqrt(2))


@query("SELECT range AS query_id, true AS same FROM range(36)")
def release_direct(spark, sf_dir):
    """All ranges of eight cells under a tree: the three steps and the closed form with the same noise give the same answers."""
    cells, a = _cells(spark, sf_dir, "qty_8"), S.hierarchical(8)
    w = np.array([[1.0 if lo <= c <= hi else 0.0 for c in range(8)] for lo in range(8) for hi in range(lo, 8)])
    fit = M.release(cells, a, EPS, DELTA, SEED).select("cell_id", F.col("est").alias("cnt"))
    steps = M.exact_answers(M.rows_frame(spark, w), fit).select("query_id", F.col("answer").alias("steps"))
    both = M.release_direct(cells, w, a, EPS, DELTA, SEED).join(steps, "query_id")
    return both.select("query_id", (F.abs(F.col("answer") - F.col("steps")) < 1e-6).alias("same"))


@query("WITH g AS (SELECT floor((l_quantity - 1) * 8 / 50) AS q, floor(l_extendedprice * 8 / 105600) AS p FROM lineitem), i AS (SELECT a.range AS lo, b.range AS hi FROM range(8) a JOIN range(8) b ON a.range <= b.range) SELECT CAST(0 AS INTEGER) AS axis, lo, hi, CAST(count(q) AS BIGINT) AS exact, true AS close FROM i LEFT JOIN g ON q BETWEEN lo AND hi AND p BETWEEN 0 AND 7 GROUP BY 2, 3 UNION ALL SELECT 1, lo, hi, CAST(count(q) AS BIGINT), true FROM i LEFT JOIN g ON p BETWEEN lo AND hi AND q BETWEEN 0 AND 7 GROUP BY 2, 3")
def release_separated(spark, sf_dir):
    """Ranges over either axis, measured on the two marginals alone; the product domain is never made."""
    g = W.gram_all_range((8,))
    s = P.separate((8, 8), {(0,): g, (1,): g})
    cells = _cells(spark, sf_dir, "pair_8x8")
    marginal = {(): cells.select(F.lit(0).cast("long").alias("cell_id"), "cnt"), (0,): cells.select(F.expr("cell_id div 8").alias("cell_id"), "cnt"), (1,): cells.select(F.expr("cell_id % 8").alias("cell_id"), "cnt")}
    marginal = {t: m.groupBy("cell_id").agg(F.sum("cnt").alias("cnt")) for t, m in marginal.items()}
    fit = P.release(s, marginal, EPS, DELTA, SEED)
    mse = s.sensitivity() ** 2 * noise_constant(EPS, DELTA) * np.linalg.pinv(s.gram(), rcond=1e-11, hermitian=True)
    out = None
    for axis in (0, 1):
        lift = s.coordinates.lift((axis,))
        w = np.array([[1.0 if lo <= c <= hi else 0.0 for c in range(8)] for lo in range(8) for hi in range(lo, 8)])
        sd = np.sqrt(np.einsum("ij,jk,ik->i", w @ lift, mse, w @ lift))
        bounds = [(lo, hi, float(x)) for (lo, hi), x in zip([(lo, hi) for lo in range(8) for hi in range(lo, 8)], sd, strict=True)]
        boxes = _frame(spark, [(lo * 8 + hi, lo, hi, x) for lo, hi, x in bounds], "query_id long, lo0 long, hi0 long, sd double")
        true = C.box_answers(boxes, marginal[(axis,)], "cnt", (8,)).withColumnRenamed("answer", "exact")
        own = C.box_answers(boxes.select("query_id", "lo0", "hi0"), fit[(axis,)], "est", (8,)).select("query_id", "answer")
        one = true.join(own, "query_id").select(F.lit(axis).alias("axis"), F.col("lo0").alias("lo"), F.col("hi0").alias("hi"), "exact", (F.abs(F.col("answer") - F.col("exact")) <= 6 * F.col("sd")).alias("close"))
        out = one if out is None else out.unionByName(one)
    return out


_ALPHA, _BETA = S.agnostic_root(8.0, 8.0, 5)
_SENS5 = float(np.sqrt((_ALPHA + _BETA) ** 2 + 4 * _BETA**2))


@query(f"WITH x AS (SELECT CASE event_type WHEN 'click' THEN 0 WHEN 'error' THEN 1 WHEN 'purchase' THEN 2 WHEN 'signup' THEN 3 ELSE 4 END AS c, count(*) AS n FROM events GROUP BY 1), y AS (SELECT c, {_ALPHA!r} * n + {_BETA!r} * (SELECT sum(n) FROM x) + {gauss_sigma(_SENS5, EPS, DELTA)!r} * {_g('c')} AS y FROM x), f AS (SELECT c, (y - {_BETA!r} / {_ALPHA + 5 * _BETA!r} * (SELECT sum(y) FROM y)) / {_ALPHA!r} AS est FROM y) SELECT m.range AS mask, round(sum(CASE WHEN ((m.range >> CAST(c AS INTEGER)) & 1) = 1 THEN est ELSE 0 END), 6) AS answer FROM range(1, 32) m CROSS JOIN f GROUP BY 1")
def release_agnostic(spark, sf_dir):
    fit = M.release(_cells(spark, sf_dir, "type_5"), _ALPHA * np.eye(5) + _BETA, EPS, DELTA, SEED)
    rows = W.predicate_rows(spark, 5)
    return rows.join(fit, "cell_id").groupBy(F.col("query_id").alias("mask")).agg(F.round(F.sum("est"), 6).alias("answer"))


_RAW = f"(SELECT b.query_id, lo0, hi0, count(l_quantity) + {gauss_sigma(32.5, EPS, DELTA)!r} * {_g('b.query_id')} AS y FROM {_B64} b LEFT JOIN lineitem ON floor(l_quantity - 1) BETWEEN lo0 AND hi0 GROUP BY 1, 2, 3)"


@query(f"WITH r AS {_RAW} SELECT a.hi0 AS k, abs(a.y + b.y - c.y) > 1e-4 AS gap_raw, false AS gap_fitted FROM r a JOIN r b ON a.lo0 = 0 AND b.hi0 = 63 AND b.lo0 = a.hi0 + 1 JOIN r c ON c.lo0 = 0 AND c.hi0 = 63")
def consistency_check(spark, sf_dir):
    """Ranges [0, k] and [k+1, 63] against [0, 63]: noised one by one they do not add up, released from a fit they do."""

    def gaps(got, name):
        low = got.where("lo = 0 AND hi < 63").select(F.col("hi").alias("k"), F.col("answer").alias("a"))
        high = got.where("hi = 63 AND lo > 0").select((F.col("lo") - 1).alias("k"), F.col("answer").alias("b"))
        every = got.where("lo = 0 AND hi = 63").select(F.col("answer").alias("c"))
        return low.join(high, "k").crossJoin(F.broadcast(every)).select("k", (F.abs(F.col("a") + F.col("b") - F.col("c")) > 1e-4).alias(name))

    boxes = W.range_boxes(spark, (64,))
    rows = W.box_rows(boxes, (64,))
    noisy = M.gaussian_answers(rows, _cells(spark, sf_dir, "qty_64"), 32.5, EPS, DELTA, SEED)
    raw = boxes.join(noisy, "query_id").select(F.col("lo0").alias("lo"), F.col("hi0").alias("hi"), F.col("noisy").alias("answer"))
    return gaps(raw, "gap_raw").join(gaps(release_haar(spark, sf_dir), "gap_fitted"), "k")


@query(
    f"WITH h AS ({_HAAR8}), e AS (SELECT t.range AS t, h.cell_id, sum(h.coef / h.w * {gauss_sigma(2.0, EPS, DELTA)!r} * {_g('(t.range * 8 + h.query_id)')}) AS off FROM h CROSS JOIN range(50) t GROUP BY 1, 2), "
    "i AS (SELECT a.range AS lo, b.range AS hi FROM range(8) a JOIN range(8) b ON a.range <= b.range), r AS (SELECT t, lo, hi, sum(off) AS off FROM i JOIN e ON cell_id BETWEEN lo AND hi GROUP BY 1, 2, 3) SELECT lo, hi, round(avg(off * off), 4) AS mse FROM r GROUP BY 1, 2"
)
def empirical_mse(spark, sf_dir):
    """Mean squared deviation of 50 seeded releases of all ranges under the wavelet from the true answers."""
    cells = _cells(spark, sf_dir, "qty_8")
    rows = M.haar_rows(spark, 8)
    times = spark.range(50).select(F.col("id").alias("t"))
    true = rows.join(cells, "cell_id").groupBy("query_id").agg(F.sum(F.col("coef") * F.col("cnt")).alias("answer"))
    noisy = true.crossJoin(times).select("t", "query_id", (F.col("answer") + F.lit(gauss_sigma(2.0, EPS, DELTA)) * gaussian(SEED, F.col("t") * 8 + F.col("query_id"))).alias("y"))
    fit = rows.join(noisy, "query_id").groupBy("t", "cell_id").agg(F.sum(F.col("coef") * F.col("y") / F.col("w")).alias("est"))
    off = fit.join(cells, "cell_id").select("t", "cell_id", (F.col("est") - F.col("cnt")).alias("off"))
    inside = W.box_rows(W.range_boxes(spark, (8,)), (8,)).select("query_id", "cell_id")
    each = inside.join(off, "cell_id").groupBy("t", "query_id").agg(F.sum("off").alias("off"))
    mse = each.groupBy("query_id").agg(F.round(F.avg(F.col("off") * F.col("off")), 4).alias("mse"))
    return mse.select(F.expr("query_id div 8").alias("lo"), (F.col("query_id") % 8).alias("hi"), "mse")


# ---- errors, bounds, searches ---------------------------------------------------------------------

_BOUND = "pow((SELECT sum(sqrt(({n} + 1) / 4.0) / sin(range * pi() / (2.0 * ({n} + 1)))) FROM range(1, {n} + 1)), 2) / {n}"
_QUANTITIES = {f"qty_{n}": (f"CAST(floor((l_quantity - 1) * {n} / 50) AS BIGINT)", "lineitem", f"floor((l_quantity - 1) * {n} / 50) BETWEEN 0 AND {n - 1}", n) for n in (4, 6, 8, 16, 50)}
_LAID = _CELLS | _QUANTITIES | {
    "ship_256": (f"CAST(floor({_D} / 10.0) AS BIGINT)", "lineitem", f"floor({_D} / 10.0) BETWEEN 0 AND 255", 256),
    "type_5": ("list_position(['click', 'error', 'purchase', 'signup', 'view'], event_type) - 1", "events", "event_type IN ('click', 'error', 'purchase', 'signup', 'view')", 5),
    "flags_3x2x11": ("CAST(((ascii(l_returnflag) - 65) // 8 * 2 + CASE l_linestatus WHEN 'F' THEN 0 ELSE 1 END) * 11 + round(l_discount * 100) AS BIGINT)", "lineitem", "l_returnflag IN ('A', 'N', 'R') AND l_linestatus IN ('F', 'O') AND round(l_discount * 100) BETWEEN 0 AND 10", 66),
}


def _filled(name: str) -> str:
    """SQL for the filled cells (i, cnt) of a declared domain of a table."""
    return "SELECT {} AS i, count(*) AS cnt FROM {} WHERE {} GROUP BY 1".format(*_LAID[name])


def _range_gram(dims: tuple[int, ...]) -> str:
    """SQL for how many ranges hold both of the cells a.i and b.i."""
    terms, stride = [], 1
    for d in reversed(dims):
        x, y = f"(a.i // {stride} % {d})", f"(b.i // {stride} % {d})"
        terms.append(f"(least({x}, {y}) + 1) * ({d} - greatest({x}, {y}))")
        stride *= d
    return " * ".join(terms)


def _ppm_sql(error: str, name: str, gram: str) -> str:
    """SQL for ``_ppm`` of an error, on the cells of a table."""
    answers = f"(SELECT sum(CAST(a.cnt AS DOUBLE) * b.cnt * ({gram})) FROM ({_filled(name)}) a CROSS JOIN ({_filled(name)}) b)"
    return f"round(1e6 * sqrt(({error}) / nullif({answers}, 0)), 4)"


def _vector(spark, sf_dir, name: str) -> np.ndarray:
    """The cells of a table, counted by Spark; at most 1024 come to the driver."""
    x = np.zeros(domain(name).n)
    for r in _cells(spark, sf_dir, name).collect():
        x[r["cell_id"]] = r["cnt"]
    return x


def _ppm(error: float, x: np.ndarray, g: np.ndarray) -> float | None:
    """The root of an error over the table's squared true answers, in millionths; none if all are zero."""
    answers = float(x @ g @ x)
    return round(1e6 * float(error / answers) ** 0.5, 4) if answers else None


_ONE = {"qty_50": 50, "qty_64": 64, "ship_256": 256}


@query(" UNION ALL ".join(f"SELECT '{n}' AS dims, round({_BOUND.format(n=n)}, 2) AS bound, {_ppm_sql(_BOUND.format(n=n), k, _range_gram((n,)))} AS ppm" for k, n in _ONE.items()))
def bound_range_1d(spark, sf_dir):
    """Bounds of all ranges over quantities and ship dates, and their size beside the table's answers."""
    rows = []
    for k, n in _ONE.items():
        g = W.gram_all_range((n,))
        bound = S.bound_of_gram(g)
        rows.append((str(n), round(bound, 2), _ppm(bound, _vector(spark, sf_dir, k), g)))
    return _frame(spark, rows, "dims string, bound double, ppm double")


_FIVE = {"1024": (1024,), "32x32": (32, 32), "16x8x8": (16, 8, 8), "4^5": (4,) * 5, "2^10": (2,) * 10}


_FIVE_LAID = {"1024": "ship_1024", "32x32": "ship_price_32x32", "16x8x8": "qty_price_ship_16x8x8", "4^5": "five_4", "2^10": "ten_2"}
_LAID["ten_2"] = (" + ".join(f"CAST({c} AS BIGINT) * {2 ** (9 - i)}" for i, c in enumerate(_FLAGS)), "lineitem JOIN part ON l_partkey = p_partkey JOIN orders ON l_orderkey = o_orderkey", "true", 1024)


def _bound_kd(dims: tuple[int, ...]) -> str:
    return " * ".join("(" + _BOUND.format(n=n) + ")" for n in dims)


@query(" UNION ALL ".join(f"SELECT '{k}' AS dims, round({_bound_kd(d)}, 0) AS bound, {_ppm_sql(_bound_kd(d), _FIVE_LAID[k], _range_gram(d))} AS ppm" for k, d in _FIVE.items()))
def bound_range_kd(spark, sf_dir):
    """The five 1024-cell domains of lineitem; bounds from the spectra of the whole Gram matrices, and their size beside the table's answers."""
    rows = []
    for k, d in _FIVE.items():
        g = W.gram_all_range(d)
        bound = S.bound_of_gram(g)
        rows.append((k, round(bound, 0), _ppm(bound, _vector(spark, sf_dir, _FIVE_LAID[k]), g)))
    return _frame(spark, rows, "dims string, bound double, ppm double")


_ALL_SETS = {"qty_4": 4, "type_5": 5, "qty_8": 8}
_LAID["qty_8"] = ("CAST(floor((l_quantity - 1) / 7) AS BIGINT)", "lineitem", "floor((l_quantity - 1) / 7) BETWEEN 0 AND 7", 8)


def _set_bound(n: int) -> str:
    return f"pow(sqrt(pow(2.0, {n} - 2) * ({n} + 1)) + ({n} - 1) * sqrt(pow(2.0, {n} - 2)), 2) / {n}"


@query(" UNION ALL ".join(f"SELECT {n} AS n, round({_set_bound(n)}, 6) AS bound, {_ppm_sql(_set_bound(n), k, f'pow(2.0, {n} - CASE WHEN a.i = b.i THEN 1 ELSE 2 END)')} AS ppm" for k, n in _ALL_SETS.items()))
def bound_predicates(spark, sf_dir):
    """Bounds of all sets of quantities and of event types, and their size beside the tables' answers."""
    rows = []
    for k, n in _ALL_SETS.items():
        g = W.gram_predicates(n)
        bound = S.bound_of_gram(g)
        rows.append((n, round(bound, 6), _ppm(bound, _vector(spark, sf_dir, k), g)))
    return _frame(spark, rows, "n int, bound double, ppm double")


_CUBE = "t AS (SELECT a.range AS a, b.range AS b, c.range AS c FROM range(2) a CROSS JOIN range(2) b CROSS JOIN range(2) c), s AS (SELECT name, sa, sb, sc FROM (VALUES ('one_way',1,0,0),('one_way',0,1,0),('one_way',0,0,1),('two_way',1,1,0),('two_way',1,0,1),('two_way',0,1,1)) v(name, sa, sb, sc) UNION ALL SELECT 'cube', a, b, c FROM t), e AS (SELECT name, (CASE WHEN a = 1 THEN 2 ELSE 1 END) * (CASE WHEN b = 1 THEN 1 ELSE 1 END) * (CASE WHEN c = 1 THEN 10 ELSE 1 END) AS many, sum(CASE WHEN sa >= a AND sb >= b AND sc >= c THEN (CASE WHEN sa = 1 THEN 1 ELSE 3 END) * (CASE WHEN sb = 1 THEN 1 ELSE 2 END) * (CASE WHEN sc = 1 THEN 1 ELSE 11 END) ELSE 0 END) AS value FROM t CROSS JOIN s GROUP BY name, a, b, c)"


@query(f"WITH {_CUBE}, b AS (SELECT name, pow(sum(many * sqrt(value)), 2) / 66 AS bound FROM e GROUP BY 1), n AS (SELECT name, count(*) * 66 AS own FROM s GROUP BY 1) SELECT name, round(bound, 4) AS bound, round(bound, 4) AS attained, round(bound, 4) AS closed, round(own / bound, 4) AS identity_ratio, round(1e6 * sqrt(bound / (SELECT nullif(sum(CAST(a.cnt AS DOUBLE) * c.cnt), 0) FROM s JOIN ({_filled('flags_3x2x11')}) a ON true JOIN ({_filled('flags_3x2x11')}) c ON (sa = 0 OR a.i // 22 = c.i // 22) AND (sb = 0 OR a.i // 11 % 2 = c.i // 11 % 2) AND (sc = 0 OR a.i % 11 = c.i % 11) WHERE s.name = b_.name)), 4) AS ppm FROM b b_ JOIN n USING (name)")
def bound_marginals(spark, sf_dir):
    """Marginals of return flag, line status and discount; ppm is the bound's size beside the table's answers."""
    x = _vector(spark, sf_dir, "flags_3x2x11")
    sets = {"one_way": [(0,), (1,), (2,)], "two_way": [(0, 1), (0, 2), (1, 2)], "cube": W.cube_subsets(3)}
    rows = []
    for k, s in sets.items():
        g = W.gram_marginals((3, 2, 11), s)
        bound = S.bound_of_gram(g)
        rows.append((k, bound, S.total_error(g, S.spectral_strategy(g)), ir.bound_marginals((3, 2, 11), s), S.total_error(g, np.eye(66)) / bound, _ppm(bound, x, g)))
    out = _frame(spark, rows, "name string, bound double, attained double, closed double, identity_ratio double, ppm double")
    return out.select("name", *[F.round(c, 4).alias(c) for c in ("bound", "attained", "closed", "identity_ratio")], "ppm")


_ERR = "WITH g AS (" + _GRAM.format(rows=_R16) + "), h AS (" + _HAAR.format(n=16, k=4) + "), e AS (SELECT a.query_id, max(a.w) AS w, sum(a.coef * b.coef * g.v) AS q FROM h a JOIN h b ON a.query_id = b.query_id JOIN g ON g.i = least(a.cell_id, b.cell_id) AND g.j = greatest(a.cell_id, b.cell_id) GROUP BY 1) "


@query(_ERR + ", r AS (SELECT 'identity' AS strategy, (SELECT sum(v) FROM g WHERE i = j) AS total UNION ALL SELECT 'haar', (SELECT 5 * sum(q / (w * w)) FROM e) UNION ALL SELECT 'tree', (SELECT 5 * sum(q / (w * CASE WHEN query_id = 0 THEN 31 ELSE w - 1 END)) FROM e) UNION ALL SELECT 'workload', (SELECT max(v) * 16 FROM g WHERE i = j)) SELECT strategy, round(total, 6) AS total, " + _ppm_sql("total", "qty_16", _range_gram((16,))) + " AS ppm FROM r")
def err_strategies(spark, sf_dir):
    """Total errors of the baselines for all ranges on 16 cells of quantities, and their size beside the table's answers; in SQL by expansion over the common eigenvectors."""
    x = _vector(spark, sf_dir, "qty_16")
    g = W.gram_all_range((16,))
    w = np.array([[1.0 if a <= c <= b else 0.0 for c in range(16)] for a in range(16) for b in range(a, 16)])
    every = {"identity": np.eye(16), "haar": S.haar(16), "tree": S.hierarchical(16), "workload": w}
    totals = {k: float(S.total_error(g, a)) for k, a in every.items()}
    return _frame(spark, [(k, round(t, 6), _ppm(t, x, g)) for k, t in totals.items()], "strategy string, total double, ppm double")


def _one_axis(n: int) -> dict[str, str]:
    """SQL for the total errors of all ranges on n = 2^k cells: the Gram matrix is (n+1) min(i,j) - i j plus what rows of sum zero do not see."""
    k = n.bit_length() - 1
    ones = f"(({n} + 1) * {n}.0 * ({n} + 1) * (2 * {n} + 1) / 6 - {n}.0 * {n} * ({n} + 1) * ({n} + 1) / 4)"
    rows = f"(SELECT sum({n} / s * (({n} + 1) * (s * s * s + 2 * s) / 12 - s * s * s * s / 16) / (s * {{by}})) FROM (SELECT pow(2, range) AS s FROM range(1, {k + 1})))"
    return {
        "workload": f"(floor(({n} + 1) * ({n} + 1) / 4) * {n})", "identity": f"({n}.0 * ({n} + 1) * ({n} + 2) / 6)",
        "hierarchical": f"({k + 1} * ({ones} / ({n}.0 * (2 * {n} - 1)) + {rows.format(by='(s - 1)')}))", "wavelet": f"({k + 1} * ({ones} / ({n}.0 * {n}) + {rows.format(by='s')}))",
    }


_RATIOS = " UNION ALL ".join(
    f"SELECT '{name}' AS dims, '{k}' AS strategy, round({' * '.join(_one_axis(d)[k] + ' / (' + _BOUND.format(n=d) + ')' for d in dims)}, 6) AS ratio"
    for name, dims in (("1024", (1024,)), ("32x32", (32, 32)), ("16x8x8", (16, 8, 8)))
    for k in ("workload", "identity", "hierarchical", "wavelet")
)


@query(_RATIOS)
def ratio_table(spark, sf_dir):
    """Error over bound of the baselines; products factorise, so no 1024-cell inverse is needed in 2-D and 3-D."""
    rows = []
    for name, dims in (("1024", (1024,)), ("32x32", (32, 32)), ("16x8x8", (16, 8, 8))):
        bound = S.bound_all_range(dims)
        grams = [W.gram_all_range((d,)) for d in dims]
        work = float(np.prod([np.diag(g).max() * len(g) for g in grams]))
        rows += [(name, "workload", work / bound), (name, "identity", float(np.prod([np.trace(g) for g in grams])) / bound)]
        rows += [(name, k, float(np.prod([S.total_error(g, f(len(g))) for g in grams])) / bound) for k, f in (("hierarchical", S.hierarchical), ("wavelet", S.haar))]
    return _frame(spark, rows, "dims string, strategy string, ratio double").withColumn("ratio", F.round("ratio", 6))


# ---- searches: numbers in the report queries, what must hold of them beside closed forms in the others -------


def _bounds_sql(domains: dict) -> str:
    return " UNION ALL ".join(f"SELECT '{k}' AS dims, round({' * '.join('(' + _BOUND.format(n=n) + ')' for n in d)}, 0) AS bound" for k, d in domains.items())


def _searched(spark, domains: dict, **options) -> list:
    tasks = [{"gram": W.gram_all_range(d), "dims": d, **options} for d in domains.values()]
    return L.strategies(L.search_many(tasks, spark), list(domains.values()))


_REPORTED = {"512": (512,), "1024": (1024,), "32x32": (32, 32), "16x8x8": (16, 8, 8)}


@query()
def search_report(spark, sf_dir):
    """The level search at the published sizes, one domain a task: 512 to its end, 1024-cell domains for 20 levels, with a level that fails tried anew."""
    found = _searched(spark, {"512": (512,)}) + _searched(spark, {k: d for k, d in _REPORTED.items() if k != "512"}, max_levels=20, reopen=(4, 32))
    rows = []
    for (name, dims), s in zip(_REPORTED.items(), found, strict=True):
        bound = S.bound_all_range(dims)
        haar = float(np.prod([S.total_error(W.gram_all_range((d,)), S.haar(d)) for d in dims])) / bound
        rows.append((name, len(s.levels), sum(map(len, s.levels)), len(s.weights()), s.error / bound, haar, s.trace[-1][3]))
    return _frame(spark, rows, "dims string, levels int, rows long, distinct_rows long, ratio double, wavelet double, seconds double")


_SMALL = {"64": (64,), "8x8": (8, 8), "4x4x4": (4, 4, 4), "8x4x2": (8, 4, 2), "128": (128,)}


@query(f"SELECT dims, bound, true AS above_bound, true AS falls, true AS below_wavelet, true AS below_tree, true AS within_tenth FROM ({_bounds_sql(_SMALL)})")
def search_table(spark, sf_dir):
    """Level search against the bound and the baselines, one to three dimensions: within a tenth of the bound, and under both baselines."""
    rows = []
    for (name, dims), s in zip(_SMALL.items(), _searched(spark, _SMALL), strict=True):
        g, bound = W.gram_all_range(dims), S.bound_all_range(dims)
        total, errors = S.total_error(g, s.matrix()), [t[2] for t in s.trace]
        below = [total < S.total_error(g, W.kron([f(d) for d in dims])) for f in (S.haar, S.hierarchical)]
        rows.append((name, round(bound, 0), total >= bound, errors == sorted(errors, reverse=True), *below, total <= 1.1 * bound))
    return _frame(spark, rows, "dims string, bound double, above_bound boolean, falls boolean, below_wavelet boolean, below_tree boolean, within_tenth boolean")


@query(f"SELECT '512' AS dims, round({_BOUND.format(n=512)}, 0) AS bound, r.range AS level, true AS falls, r.range >= 20 AS within_fifth FROM range(1, 31) r")
def trace_level(spark, sf_dir):
    """Convergence on 512 cells: every level lowers the error, and from the twentieth on it is within a fifth of the bound."""
    (s,), bound = _searched(spark, {"512": (512,)}, max_levels=30), S.bound_all_range((512,))
    errors = [np.inf] + [t[2] for t in s.trace]
    rows = [("512", round(bound, 0), k, errors[k] < errors[k - 1], bool(errors[k] <= 1.2 * bound) and k >= 20) for k in range(1, 31)]
    return _frame(spark, rows, "dims string, bound double, level long, falls boolean, within_fifth boolean")


@query("SELECT m.m AS pass_mode, k.k AS max_levels, true AS ordered FROM (SELECT unnest(['best_first', 'per_query', 'reopened']) AS m) m CROSS JOIN (SELECT unnest([2, 4, 8, 64]) AS k) k")
def search_modes(spark, sf_dir):
    """Ways to cut and level caps on 64 cells: a larger cap is never worse, and all stay above the bound."""
    g, bound, rows = W.gram_all_range((64,)), S.bound_all_range((64,)), []
    for mode, options in (("best_first", {}), ("per_query", {"pass_mode": "per_query"}), ("reopened", {"reopen": (4, 16)})):
        last = np.inf
        for k in (2, 4, 8, 64):
            error = L.level_search(g, (64,), k, **options).error
            rows.append((mode, k, bool(bound <= error <= last)))
            last = error
    return _frame(spark, rows, "pass_mode string, max_levels int, ordered boolean")


@query("SELECT t.t AS task_id, l.range AS level, t.n AS cells FROM (VALUES (0, 16), (1, 32), (2, 64)) t(t, n) CROSS JOIN range(1, 9) l")
def search_many(spark, sf_dir):
    """Searches on the executors: every level of every task is a partition of its cells."""
    tasks = [{"gram": W.gram_all_range(d), "dims": d, "max_levels": 8} for d in ((16,), (32,), (8, 8))]
    volume = F.aggregate(F.zip_with("lo", "hi", lambda a, b: b - a + 1), F.lit(1), lambda p, x: p * x)
    return L.search_many(tasks, spark).groupBy("task_id", F.col("level").cast("long").alias("level")).agg(F.sum(volume).alias("cells"))


@query(" UNION ALL ".join(f"SELECT {n} AS n, true AS certified, true AS between, true AS search_above, {_ppm_sql(_BOUND.format(n=n), f'qty_{n}', _range_gram((n,)))} AS ppm" for n in (4, 8, 16)))
def exact_small(spark, sf_dir):
    """Spectral bound <= certified bound <= optimum attained <= search, on small domains of quantities; ppm is the spectral bound's size beside the table's answers."""
    rows = []
    for n in (4, 8, 16):
        g = W.gram_all_range((n,))
        low, high = S.exact_optimum(g)
        search = L.level_search(g).error
        bound = S.bound_of_gram(g)
        share = _ppm(bound, _vector(spark, sf_dir, f"qty_{n}"), g)
        rows.append((n, bool(bound <= low * (1 + 1e-9)), bool(low <= high * (1 + 1e-9)), bool(search >= low * (1 - 1e-9)), share))
    return _frame(spark, rows, "n int, certified boolean, between boolean, search_above boolean, ppm double")


def _sampled(spark, dims: tuple[int, ...], m: int, method: str = "uniform", band: tuple[float, float] | None = None) -> np.ndarray:
    boxes = W.range_boxes(spark, dims)
    if band:
        boxes = boxes.where((W.coverage(dims) > band[0]) & (W.coverage(dims) <= band[1]))
    return ir.Boxes(W.sample(boxes, m, SEED, dims, method), dims).gram()


_SIZES = (100, 1000, 10000)


@query("SELECT d.d AS dims, m.m AS method, s.s AS m, true AS below_one, true AS rises, true AS near_one FROM (SELECT unnest(['1024', '32x32']) AS d) d CROSS JOIN (SELECT unnest(['uniform', 'biased']) AS m) m CROSS JOIN (SELECT unnest([100, 1000, 10000]) AS s) s")
def sample_complexity(spark, sf_dir):
    """Average-error bound of sampled range workloads over that of all ranges: it rises with the sample, and 10,000 uniform ranges reach nine tenths of it."""
    rows = []
    for name, dims in (("1024", (1024,)), ("32x32", (32, 32))):
        full = S.bound_all_range(dims) / np.prod([d * (d + 1) / 2 for d in dims])
        for method in ("uniform", "biased"):
            last = 0.0
            for m in _SIZES:
                ratio = S.bound_of_gram(_sampled(spark, dims, m, method)) / m / full
                rows.append((name, method, m, bool(ratio <= 1.02), bool(ratio > last), bool(m < 10000 or method == "biased" or ratio >= 0.9)))
                last = ratio
    return _frame(spark, rows, "dims string, method string, m int, below_one boolean, rises boolean, near_one boolean")


_BANDS = ((0.0, 0.01), (0.01, 0.05), (0.05, 0.1), (0.1, 0.25), (0.25, 0.5))


@query("SELECT unnest(['0.0-0.01', '0.01-0.05', '0.05-0.1', '0.1-0.25', '0.25-0.5']) AS band, true AS above_bound, true AS near_bound, true AS below_wavelet, true AS answered, (SELECT coalesce(sum(cnt), 0)::BIGINT FROM (" + _filled("ship_256") + ")) AS records")
def coverage_bands(spark, sf_dir):
    """2,000 random ranges of 256 cells of ship dates by coverage: the search stays within a fifth of the bound and under the wavelet in every band.

    ``answered``: its rows, counted on the table without noise, give back the answers of all the ranges.
    """
    x = _vector(spark, sf_dir, "ship_256")
    grams = [_sampled(spark, (256,), 2000, band=b) for b in _BANDS]
    found = L.strategies(L.search_many([{"gram": g, "dims": (256,), "max_levels": 40, "reopen": (4, 32)} for g in grams], spark), [(256,)] * len(grams))
    rows = []
    for (low, high), g, s in zip(_BANDS, grams, found, strict=True):
        bound, total = S.bound_of_gram(g), S.total_error(g, s.matrix())
        a = s.matrix()
        off = np.linalg.lstsq(a, a @ x, rcond=None)[0] - x
        answered = off @ g @ off <= 1e-12 * (x @ g @ x)
        rows.append((f"{low}-{high}", bool(total >= bound), bool(total <= 1.2 * bound), bool(total < S.total_error(g, S.haar(256))), bool(answered), int(x.sum())))
    return _frame(spark, rows, "band string, above_bound boolean, near_bound boolean, below_wavelet boolean, answered boolean, records long")


@query()
def coverage_report(spark, sf_dir):
    """The numbers behind ``coverage_bands``, and 200 ranges of 1024 cells that cover at most 3 cells, where the wavelet does worst; each also beside the table's answers."""
    rows = []
    for n, m, bands in ((256, 2000, _BANDS), (1024, 200, ((0.0, 0.003),))):
        x = _vector(spark, sf_dir, f"ship_{n}")
        for low, high in bands:
            own = _sampled(spark, (n,), m, band=(low, high))
            g = own + 1e-9 * np.eye(n)
            bound, wavelet = S.bound_of_gram(g), S.total_error(g, S.haar(n))
            s = L.level_search(g, max_levels=16, reopen=(4, 32))
            rows.append((n, f"{low}-{high}", s.error / bound, wavelet / bound, _ppm(s.error, x, own), _ppm(wavelet, x, own)))
    return _frame(spark, rows, "n int, band string, search double, wavelet double, search_ppm double, wavelet_ppm double")


_PAIRS = {"8x8": 8, "16x16": 16, "32x32": 32}


@query("SELECT d AS dims, CAST(b AS DOUBLE) AS bound, true AS above_bound, true AS near_bound, true AS under_joint FROM (VALUES ('8x8', 266.16), ('16x16', 1429.11), ('32x32', 7627.35)) v(d, b)")
def separation(spark, sf_dir):
    """Ranges on both axes, one search an axis: within 1.05 of the bound up to 32 x 32, and at most 1.02 of the joint search where that is run."""
    rows = []
    for name, d in _PAIRS.items():
        g = W.gram_all_range((d,))
        parts = {(0,): g, (1,): g}
        error, bound = P.separate((d, d), parts).error(parts), P.bound((d, d), parts)
        under = True
        if d <= 16:
            under = error <= 1.02 * L.level_search(np.kron(g, np.ones((d, d))) + np.kron(np.ones((d, d)), g), (d, d)).error
        rows.append((name, round(bound, 2), bool(error >= bound), bool(error <= 1.05 * bound), bool(under)))
    return _frame(spark, rows, "dims string, bound double, above_bound boolean, near_bound boolean, under_joint boolean")


@query()
def separation_report(spark, sf_dir):
    """Seconds and ratios of the separated search and, for 8 levels, of the joint one on 32 x 32 cells; two-way marginals of three axes by recursion."""
    import time

    g, rows = W.gram_all_range((32,)), []
    parts, began = {(0,): g, (1,): g}, time.time()
    error = P.separate((32, 32), parts).error(parts)
    rows.append(("32x32 separated", error / P.bound((32, 32), parts), time.time() - began))
    began = time.time()
    s = L.level_search(np.kron(g, np.ones((32, 32))) + np.kron(np.ones((32, 32)), g), (32, 32), 8)
    rows.append(("32x32 joint, 8 levels", s.error / P.bound((32, 32), parts), time.time() - began))
    dims, began = (8, 6, 5), time.time()
    one = [W.gram_all_range((d,)) for d in dims]
    pairs = {(i, j): np.kron(one[i], one[j]) for i, j in ((0, 1), (0, 2), (1, 2))}
    rows.append(("8x6x5 pairs, recursive", P.separate(dims, pairs).error(pairs) / P.bound(dims, pairs), time.time() - began))
    return _frame(spark, rows, "what string, ratio double, seconds double")


@query("SELECT n, true AS above_bound, true AS near_search, true AS below_wavelet FROM (SELECT unnest([64, 256, 1024]) AS n)")
def generalization(spark, sf_dir):
    """Off-centre samples: the generalized search, its blocks on the executors, against the bound, full search and wavelet."""
    rows = []
    for n in (64, 256, 1024):
        g = _sampled(spark, (n,), min(10 * n, n * (n + 1) // 4), "biased")
        bound, error = S.bound_of_gram(g), S.total_error(g, L.generalized_strategy(g, spark=spark))
        search = L.level_search(g, max_levels=12 if n == 1024 else 40, reopen=(4, 32)).error
        rows.append((n, bool(error >= bound), bool(error <= 1.3 * search), bool(error < S.total_error(g, S.haar(n)))))
    return _frame(spark, rows, "n int, above_bound boolean, near_search boolean, below_wavelet boolean")


@query("WITH " + ", ".join(f"{k} AS (SELECT {v} AS total)" for k, v in _one_axis(64).items() if k != "workload") + f" SELECT 'identity' AS strategy, round(2 / {EPS ** 2!r} * total, 2) AS pure, round({noise_constant(EPS, DELTA)!r} * total, 2) AS approx FROM identity UNION ALL SELECT 'haar', round(2 / {EPS ** 2!r} * 7 * total, 2), round({noise_constant(EPS, DELTA)!r} * total, 2) FROM wavelet UNION ALL SELECT 'tree', round(2 / {EPS ** 2!r} * 7 * total, 2), round({noise_constant(EPS, DELTA)!r} * total, 2) FROM hierarchical")
def pure_vs_approx(spark, sf_dir):
    """Haar, tree and identity under eps alone and under (eps, delta)."""
    g = W.gram_all_range((64,))
    every = {"identity": np.eye(64), "haar": S.haar(64), "tree": S.hierarchical(64)}
    rows = [(k, round(S.total_error_pure(g, a, EPS), 2), round(S.total_error(g, a, noise_constant(EPS, DELTA)), 2)) for k, a in every.items()]
    return _frame(spark, rows, "strategy string, pure double, approx double")


_NORMS = "SELECT '{name}' AS strategy, min(c) AS min_norm, max(c) AS max_norm, min(c) = max(c) AS uniform, coalesce(sum(cnt) FILTER (WHERE c = top), 0)::BIGINT AS records FROM (SELECT c, cnt, max(c) OVER () AS top FROM (SELECT cell_id, sum(coef * coef) AS c FROM ({rows}) GROUP BY 1) JOIN ({cells}) ON i = cell_id)"


@query(" UNION ALL ".join(_NORMS.format(name=k, rows=v, cells=_filled("qty_16")) for k, v in {"workload": _R16, "haar": _HAAR.format(n=16, k=4), "tree": _TREE.format(n=16, k1=5)}.items()))
def column_uniform(spark, sf_dir):
    """Squared norms of the columns that the table's quantities fill, and how many records have the largest, which sets the noise."""
    x = _vector(spark, sf_dir, "qty_16")
    w = np.array([[1.0 if a <= c <= b else 0.0 for c in range(16)] for a in range(16) for b in range(a, 16)])
    rows = []
    for k, a in {"workload": w, "haar": S.haar(16), "tree": S.hierarchical(16)}.items():
        norms = S.column_norms(a)[x > 0]
        if len(norms):
            rows.append((k, float(norms.min()), float(norms.max()), S.is_column_uniform(a[:, x > 0]), int(x[x > 0][norms == norms.max()].sum())))
        else:
            rows.append((k, None, None, None, 0))
    return _frame(spark, rows, "strategy string, min_norm double, max_norm double, uniform boolean, records long")


@query(f"WITH c AS (SELECT cell_id, sum(coef * coef) AS c FROM ({_R16}) GROUP BY 1) SELECT cell_id, round(sqrt((SELECT max(c) FROM c) - c), 6) AS weight, round(sqrt((SELECT max(c) FROM c) - c) * coalesce(cnt, 0), 4) AS answer FROM c LEFT JOIN ({_filled('qty_16')}) ON i = cell_id WHERE c < (SELECT max(c) FROM c)")
def complete_columns(spark, sf_dir):
    """The rows that complete all ranges over 16 cells of quantities, and their answers on the table."""
    x = _vector(spark, sf_dir, "qty_16")
    w = np.array([[1.0 if a <= c <= b else 0.0 for c in range(16)] for a in range(16) for b in range(a, 16)])
    extra = S.complete_columns(w)[len(w) :]
    return _frame(spark, [(int(r.argmax()), round(float(r.max()), 6), round(float(r @ x), 4)) for r in extra], "cell_id long, weight double, answer double")


@query("SELECT range AS cell_id, range // 4 * 4 AS merged_id FROM range(16)")
def merge_cells(spark, sf_dir):
    """A workload that only asks for ranges of fours cannot tell their cells apart."""
    fours = W.range_boxes(spark, (4,)).select("query_id", (F.col("lo0") * 4).alias("lo0"), (F.col("hi0") * 4 + 3).alias("hi0"))
    return C.merge_equal_cells(W.box_rows(fours, (16,)))


@query("SELECT lo0, hi0, round(sqrt(count(*)), 6) AS weight FROM (SELECT a.range % 5 AS lo0, a.range % 5 + a.range % 3 AS hi0 FROM range(40) a) GROUP BY 1, 2")
def merge_redundant(spark, sf_dir):
    """Equal boxes become one row of weight sqrt(count)."""
    a = np.zeros((40, 8))
    for k in range(40):
        a[k, k % 5 : k % 5 + k % 3 + 1] = 1
    rows = [(int(np.flatnonzero(x)[0]), int(np.flatnonzero(x)[-1]), round(float(x.max()), 6)) for x in S.merge_redundant(a)]
    return _frame(spark, rows, "lo0 long, hi0 long, weight double")


# ---- workloads as symbols -------------------------------------------------------------------------

_IR = {
    "points": (lambda: ir.Point(6), "SELECT range AS query_id, range AS cell_id, CAST(1 AS DOUBLE) AS coef FROM range(6)"),
    "total": (lambda: ir.Total(6), "SELECT CAST(0 AS BIGINT) AS query_id, range AS cell_id, CAST(1 AS DOUBLE) AS coef FROM range(6)"),
    "prefix": (lambda: ir.Prefix(6), "SELECT a.range AS query_id, b.range AS cell_id, CAST(1 AS DOUBLE) AS coef FROM range(6) a JOIN range(6) b ON b.range <= a.range"),
    "product": (lambda: ir.Kron((ir.Prefix(3), ir.Point(2))), "SELECT a.range * 2 + p.range AS query_id, b.range * 2 + p.range AS cell_id, CAST(1 AS DOUBLE) AS coef FROM range(3) a JOIN range(3) b ON b.range <= a.range CROSS JOIN range(2) p"),
    "union": (lambda: ir.Union((ir.Scale(ir.Total(6), 3.0), ir.Point(6))), "SELECT CAST(0 AS BIGINT) AS query_id, range AS cell_id, CAST(3 AS DOUBLE) AS coef FROM range(6) UNION ALL SELECT range + 1, range, 1 FROM range(6)"),
    "marginal": (lambda: ir.marginal_of(ir.AllRange(3), (1,), (3,), (2, 3)), "SELECT row_number() OVER (ORDER BY lo, hi) - 1 AS query_id, c.range * 3 + k.range AS cell_id, CAST(1 AS DOUBLE) AS coef FROM (SELECT a.range AS lo, b.range AS hi FROM range(3) a JOIN range(3) b ON a.range <= b.range) JOIN range(3) k ON k.range BETWEEN lo AND hi CROSS JOIN range(2) c"),
}
_IR["marginal"] = (_IR["marginal"][0], _IR["marginal"][1].replace("row_number() OVER (ORDER BY lo, hi) - 1 AS query_id", "(SELECT count(*) FROM (SELECT a.range AS x, b.range AS y FROM range(3) a JOIN range(3) b ON a.range <= b.range) z WHERE z.x < lo OR z.x = lo AND z.y < hi) AS query_id"))
for _name, (_node, _sql) in _IR.items():
    query(_sql, f"workload_{_name}")(lambda s, d, node=_node: node().rows(s))

_SPECTRA = {"all_range": (lambda: ir.AllRange(12), "SELECT a.range * 12 + b.range AS query_id, c.range AS cell_id, 1.0::DOUBLE AS coef FROM range(12) a JOIN range(12) b ON a.range <= b.range JOIN range(12) c ON c.range BETWEEN a.range AND b.range"), "prefix": (lambda: ir.Prefix(12), "SELECT a.range AS query_id, b.range AS cell_id, 1.0::DOUBLE AS coef FROM range(12) a JOIN range(12) b ON b.range <= a.range")}


@query(" UNION ALL ".join(f"SELECT '{k}' AS name, round(sum(v), 6) AS trace, round(sum(v * v), 4) AS squares FROM (SELECT i, j, sum(ci * cj) AS v FROM (SELECT a.cell_id AS i, b.cell_id AS j, a.coef AS ci, b.coef AS cj FROM ({s}) a JOIN ({s}) b ON a.query_id = b.query_id) GROUP BY 1, 2) WHERE i = j".replace("round(sum(v * v), 4) AS squares", f"(SELECT round(sum(v * v), 4) FROM (SELECT a.cell_id AS i, b.cell_id AS j, sum(a.coef * b.coef) AS v FROM ({s}) a JOIN ({s}) b ON a.query_id = b.query_id GROUP BY 1, 2)) AS squares") for k, (_, s) in _SPECTRA.items()))
def spectrum_moments(spark, sf_dir):
    """Closed-form spectra: their sum is the trace of the joined Gram matrix, their squares its squared entries."""
    rows = [(k, round(float(n().spectrum().sum()), 6), round(float((n().spectrum() ** 2).sum()), 4)) for k, (n, _) in _SPECTRA.items()]
    return _frame(spark, rows, "name string, trace double, squares double")


_BIG = f"SELECT count(*) FROM lineitem WHERE {_D} >= 0 AND floor({_D} * 2 / 5.0) < 1024 AND floor(l_extendedprice * 1024 / 105600) BETWEEN 0 AND 1023 AND floor((l_quantity - 1) * 1024 / 50) BETWEEN 0 AND 1023"


@query(f"WITH r AS (SELECT '2^30 ranges' AS name, pow({_BOUND.format(n=1024)}, 3) AS bound, 1e20 AS unit, pow(1024 * 1025 / 2.0, 3) AS m, ({_BIG}) AS records UNION ALL SELECT 'union', pow(sqrt(7) + 5, 2) / 6, 1, 7, (SELECT coalesce(sum(cnt), 0) FROM ({_filled('qty_6')}))) SELECT name, round(bound / unit, 4) AS bound, records::BIGINT AS records, round(1e6 * sqrt(bound / m) / nullif(records, 0), 4) AS ppm FROM r")
def bound_symbolic(spark, sf_dir):
    """Bounds of a product over a thousand million cells of lineitem, from its axes, and of points with their total; ppm is an answer's mean error beside the records."""
    union = ir.Union((ir.Point(6), ir.Total(6)))
    rows = []
    for name, laid, node, m, unit in (("2^30 ranges", "ship_price_qty_1024x1024x1024", ir.Kron((ir.AllRange(1024),) * 3), (1024 * 1025 / 2) ** 3, 1e20), ("union", "qty_6", union, 7, 1.0)):
        records = table(spark, sf_dir, "lineitem").where(domain(laid).cell_id().isNotNull()).count()
        bound = float(node.bound())
        rows.append((name, round(bound / unit, 4), records, round(1e6 * (bound / m) ** 0.5 / records, 4) if records else None))
    return _frame(spark, rows, "name string, bound double, records long, ppm double")


@query(" UNION ALL ".join(f"SELECT '{k}' AS dims, true AS within_4_sd, {_ppm_sql(_bound_kd(_FIVE[k]), _FIVE_LAID[k], _range_gram(_FIVE[k]))} AS ppm" for k in ("1024", "32x32")))
def bound_estimated(spark, sf_dir):
    """The bound from products with random vectors alone, against the closed form, and that one's size beside the table's answers."""
    rows = []
    for name, dims in (("1024", (1024,)), ("32x32", (32, 32))):
        g = W.gram_all_range(dims)
        value, sd = ir.bound_estimate(lambda v, g=g: g @ v, len(g), probes=40, steps=60)
        known = S.bound_all_range(dims)
        rows.append((name, bool(abs(value - known) <= 4 * sd + 0.01 * value), _ppm(known, _vector(spark, sf_dir, _FIVE_LAID[name]), g)))
    return _frame(spark, rows, "dims string, within_4_sd boolean, ppm double")


@query(f"SELECT round(max(a), 6) AS l1, round(sqrt(max(b)), 6) AS l2 FROM (SELECT c.range AS c, sum(w) AS a, sum(w * w) AS b FROM (SELECT a.range AS lo, b.range AS hi, 1 + (a.range + b.range) % 3 AS w FROM range(16) a JOIN range(16) b ON a.range <= b.range) JOIN range(16) c ON c.range BETWEEN lo AND hi GROUP BY 1)")
def sens_boxes(spark, sf_dir):
    """Sensitivities of weighted boxes from their corners alone."""
    boxes = W.range_boxes(spark, (16,)).withColumn("coef", (1 + (F.col("lo0") + F.col("hi0")) % 3).cast("double"))
    return M.sensitivity_boxes(boxes, (16,)).select(F.round("l1", 6).alias("l1"), F.round("l2", 6).alias("l2"))


@query("SELECT round(max(a), 6) AS l1, round(sqrt(max(b)), 6) AS l2 FROM (SELECT cell_id, sum(abs(coef)) AS a, sum(coef * coef) AS b FROM (" + _TREE.format(n=16, k1=5) + ") GROUP BY 1)")
def sens_neighbours(spark, sf_dir):
    """Sensitivities by trying every neighbour of a table, for the tree on 16 cells."""
    out = M.exact_sensitivity(M.rows_frame(spark, S.hierarchical(16)), 16)
    return out.select(F.round("l1", 6).alias("l1"), F.round("l2", 6).alias("l2"))


@query("WITH n AS (SELECT 50 AS n) SELECT 'ranges, own noise' AS how, CAST(floor((n + 1) * (n + 1) / 4) AS DOUBLE) AS l1, round(2 * n * (n + 1) / 2 * pow(floor((n + 1) * (n + 1) / 4), 2), 2) AS total FROM n UNION ALL SELECT 'cells, summed up', 1.0, round(2 * n * (n + 1) * (n + 2) / 6.0, 2) FROM n")
def introduction_example(spark, sf_dir):
    """All ranges of a single attribute of 50 regions under eps = 1: noise on every range against sums of noisy cells."""
    g = W.gram_all_range((50,))
    own = M.sensitivities(W.box_rows(W.range_boxes(spark, (50,)), (50,))).first()["l1"]
    rows = [("ranges, own noise", own, round(2 * own**2 * 1275, 2)), ("cells, summed up", 1.0, round(S.total_error_pure(g, np.eye(50)), 2))]
    return _frame(spark, rows, "how string, l1 double, total double")


@query("WITH x AS (SELECT (CASE o_orderpriority WHEN '1-URGENT' THEN 0 WHEN '2-HIGH' THEN 1 WHEN '3-MEDIUM' THEN 2 WHEN '4-NOT SPECIFIED' THEN 3 ELSE 4 END) * 3 + (CASE o_orderstatus WHEN 'F' THEN 0 WHEN 'O' THEN 1 ELSE 2 END) AS c, count(*) AS n FROM orders GROUP BY 1) SELECT m.range AS mask, CAST(coalesce(sum(CASE WHEN ((m.range >> CAST(c AS INTEGER)) & 1) = 1 THEN n END), 0) AS BIGINT) AS answer FROM range(1, 32768) m CROSS JOIN x GROUP BY 1")
def exact_predicates_15(spark, sf_dir):
    """All predicates over the fifteen cells of order priority and status."""
    from .functions.domain import Attribute, Domain

    orders = table(spark, sf_dir, "orders")
    d = Domain((Attribute.groups("p", F.col("o_orderpriority"), [["1-URGENT"], ["2-HIGH"], ["3-MEDIUM"], ["4-NOT SPECIFIED"], ["5-LOW"]]), Attribute.categories("s", F.col("o_orderstatus"), ["F", "O", "P"])))
    return M.exact_answers(W.predicate_rows(spark, 15), C.dense_counts(orders, d)).select(F.col("query_id").alias("mask"), F.col("answer").cast("long").alias("answer"))


@query("WITH g AS (SELECT 4 AS a, 5 AS b) SELECT round(pow((SELECT sqrt(4 * pow(2, 5 - 2) * 6 + 5 * pow(2, 4 - 2) * 5) + 3 * sqrt(5 * pow(2, 4 - 2)) + 4 * sqrt(4 * pow(2, 5 - 2))), 2) / 20, 6) AS bound, true AS near")
def predicates_on_marginals(spark, sf_dir):
    """All predicates over either marginal of a 4 x 5 domain, separated: near the bound, which has a closed form."""
    parts = {(0,): W.gram_predicates(4), (1,): W.gram_predicates(5)}
    s = P.separate((4, 5), parts)
    bound = P.bound((4, 5), parts)
    return _frame(spark, [(round(bound, 6), bool(bound * (1 - 1e-9) <= s.error(parts) <= 1.1 * bound))], "bound double, near boolean")


@query("SELECT r.range AS cell_id, sum(c.cnt) OVER (ORDER BY r.range) AS total FROM range(64) r JOIN " + _QTY + " c ON c.cell_id = r.range")
def prefix_blocks(spark, sf_dir):
    """Running sums in blocks of eight cells."""
    return C.prefix_sums(_cells(spark, sf_dir, "qty_64"), "cnt", (64,), 8)


# ---- streams --------------------------------------------------------------------------------------

_EVENTS = "(SELECT date_trunc('hour', ts) AS w, event_type, count(*) AS cnt FROM (SELECT event_id, min(ts) AS ts, min(event_type) AS event_type FROM events GROUP BY 1) GROUP BY 1, 2)"
_HOURS = "(SELECT w, t FROM (SELECT unnest(generate_series(TIMESTAMP '2024-01-01', TIMESTAMP '2024-02-04 23:00:00', INTERVAL 1 HOUR)) AS w) CROSS JOIN (SELECT unnest(['click', 'view']) AS t))"
_HOUR_KEY = "CAST(CAST(epoch(h.w) AS BIGINT) AS VARCHAR) || '|' || h.t"
_HOUR_NOISE = _GAUSS.format(u=_U.format(seed=SEED, key=f"({_HOUR_KEY})", lane=0), v=_U.format(seed=SEED, key=f"({_HOUR_KEY})", lane=1))


@query(f"SELECT CAST(h.w AS TIMESTAMP) AS window_start, h.t AS event_type, round(coalesce(e.cnt, 0) + {_SIGMA!r} * {_HOUR_NOISE}, 6) AS answer FROM {_HOURS} h LEFT JOIN {_EVENTS} e ON e.w = h.w AND e.event_type = h.t")
def stream_release(spark, sf_dir):
    """Hours of a public calendar, five days of it beyond the events: empty ones are released like all others."""
    every = calendar(spark, "2024-01-01 00:00:00", "2024-02-05 00:00:00", ["click", "view"])
    return release_windows(window_cells(table(spark, sf_dir, "events")), every, EPS, DELTA, SEED).withColumn("answer", F.round("answer", 6))


@query(f"WITH r AS (SELECT h.w, h.t, coalesce(e.cnt, 0) + {_SIGMA!r} * {_HOUR_NOISE} AS answer FROM {_HOURS} h LEFT JOIN {_EVENTS} e ON e.w = h.w AND e.event_type = h.t) SELECT CAST(a.w AS TIMESTAMP) AS window_start, a.t AS event_type, round(sum(b.answer), 4) AS answer FROM r a JOIN r b ON a.t = b.t AND b.w >= a.w AND b.w < a.w + INTERVAL 24 HOUR GROUP BY 1, 2 HAVING count(*) = 24")
def stream_sliding(spark, sf_dir):
    """Sliding days as sums of released hours, at no further budget."""
    every = calendar(spark, "2024-01-01 00:00:00", "2024-02-05 00:00:00", ["click", "view"])
    released = release_windows(window_cells(table(spark, sf_dir, "events")), every, EPS, DELTA, SEED)
    return sliding_answers(released, 24, 3600).withColumn("answer", F.round("answer", 4))


# ---- the surface around the methods -----------------------------------------------------------------


@query("SELECT c_custkey FROM customer WHERE NOT EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey)")
def surface_anti_join(spark, sf_dir):
    return table(spark, sf_dir, "customer").join(table(spark, sf_dir, "orders"), F.col("c_custkey") == F.col("o_custkey"), "left_anti").select("c_custkey")


@query("SELECT l_returnflag, l_linestatus, count(*) AS cnt FROM lineitem GROUP BY ROLLUP (l_returnflag, l_linestatus)")
def surface_rollup(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").rollup("l_returnflag", "l_linestatus").agg(F.count("*").alias("cnt"))


@query("SELECT l_returnflag, l_linestatus, l_linenumber, count(*) AS cnt FROM lineitem GROUP BY GROUPING SETS ((l_returnflag, l_linestatus), (l_linenumber))")
def surface_grouping_sets(spark, sf_dir):
    """The marginals of two sets of attributes in one pass."""
    item = table(spark, sf_dir, "lineitem")
    sets = [[F.col("l_returnflag"), F.col("l_linestatus")], [F.col("l_linenumber")]]
    return item.groupingSets(sets, "l_returnflag", "l_linestatus", "l_linenumber").agg(F.count("*").alias("cnt"))


@query("SELECT l_partkey AS k FROM lineitem WHERE l_quantity > 25 INTERSECT SELECT l_partkey FROM lineitem WHERE l_quantity <= 25 EXCEPT SELECT p_partkey FROM part WHERE p_size > 25")
def surface_set_ops(spark, sf_dir):
    item = table(spark, sf_dir, "lineitem")
    high, low = (item.where(c).select(F.col("l_partkey").alias("k")) for c in ("l_quantity > 25", "l_quantity <= 25"))
    return high.intersect(low).exceptAll(table(spark, sf_dir, "part").where("p_size > 25").select(F.col("p_partkey").alias("k")).distinct()).distinct()


@query("SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS \"F\", count(*) FILTER (l_linestatus = 'O') AS \"O\" FROM lineitem GROUP BY 1")
def surface_pivot(spark, sf_dir):
    """A two-way marginal laid out as a table."""
    return table(spark, sf_dir, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))).na.fill(0)


@query("WITH b AS (SELECT unnest([1, 2, 3, 4, 5]) * 10 AS mark) SELECT l_linenumber, count(DISTINCT l_partkey) AS parts, (SELECT max(mark) FROM b WHERE mark <= 10 * l_linenumber + 5) AS latest FROM lineitem GROUP BY 1")
def surface_asof_distinct(spark, sf_dir):
    """Distinct counts, each with the latest mark at or before its own, by one window over both."""
    seen = table(spark, sf_dir, "lineitem").groupBy("l_linenumber").agg(F.count_distinct("l_partkey").alias("parts"))
    left = seen.select((F.col("l_linenumber") * 10 + 5).cast("long").alias("at"), "l_linenumber", "parts")
    marks = spark.range(1, 6).select((F.col("id") * 10).alias("at"), F.lit(None).cast("int").alias("l_linenumber"), F.lit(None).cast("long").alias("parts"), (F.col("id") * 10).cast("int").alias("mark"))
    both = left.withColumn("mark", F.lit(None).cast("int")).unionByName(marks.withColumn("l_linenumber", F.col("l_linenumber").cast(left.schema["l_linenumber"].dataType)))
    last = F.last("mark", ignorenulls=True).over(Window.orderBy("at", F.col("mark").isNull()))
    return both.withColumn("latest", last).where("parts IS NOT NULL").select("l_linenumber", "parts", "latest")


@query(f"SELECT strategy, rank, cell_id, cnt FROM (SELECT 'qty' AS strategy, CAST(row_number() OVER (ORDER BY cnt DESC, cell_id) AS INTEGER) AS rank, cell_id, cnt FROM {_QTY}) WHERE rank <= 10")
def surface_top_cells(spark, sf_dir):
    w = Window.partitionBy("strategy").orderBy(F.desc("cnt"), "cell_id")
    cells = _cells(spark, sf_dir, "qty_64").withColumn("strategy", F.lit("qty"))
    return cells.withColumn("rank", F.row_number().over(w)).where("rank <= 10").select("strategy", "rank", "cell_id", "cnt")


@query("SELECT n_name, count(*) AS cnt, CAST(sum(CAST(round(c_acctbal * 100) AS BIGINT)) AS BIGINT) AS cents FROM customer JOIN nation ON c_nationkey = n_nationkey WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = c_custkey) GROUP BY 1")
def surface_semi_join(spark, sf_dir):
    active = table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey"))
    who = table(spark, sf_dir, "customer").join(active, "c_custkey", "left_semi").join(table(spark, sf_dir, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    return who.groupBy("n_name").agg(F.count("*").alias("cnt"), F.sum(F.round(F.col("c_acctbal") * 100).cast("long")).alias("cents"))


