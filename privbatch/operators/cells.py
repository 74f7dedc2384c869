"""From a table to its vector of cell counts: the only pass over the data."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.domain import Domain

BLOCK = 4096


def cell_counts(df: DataFrame, domain: Domain) -> DataFrame:
    """(cell_id, cnt) of the occupied cells: partial aggregation, then one exchange of at most n rows a task."""
    return df.select(domain.cell_id().alias("cell_id")).where("cell_id IS NOT NULL").groupBy("cell_id").agg(F.count("*").alias("cnt"))


def densify(counts: DataFrame, n: int) -> DataFrame:
    """All n cells, empty ones with 0; noise must be added to those too."""
    every = counts.sparkSession.range(n).select(F.col("id").alias("cell_id"))
    return every.join(counts, "cell_id", "left").select("cell_id", F.coalesce("cnt", F.lit(0)).alias("cnt"))


def dense_counts(df: DataFrame, domain: Domain) -> DataFrame:
    return densify(cell_counts(df, domain), domain.n)


def coarsen(cells: DataFrame, block: int) -> DataFrame:
    """Blocks of neighbouring cells: (block, cells, cnt)."""
    return cells.groupBy(F.expr(f"cell_id div {int(block)}").alias("block")).agg(F.count("*").alias("cells"), F.sum("cnt").alias("cnt"))


def finest(df: DataFrame, sets: list[str]) -> DataFrame:
    """(values of the attributes, cnt) with one cell for every tuple of the occupied domain; null is a value like any other."""
    return df.groupBy(*sets).agg(F.count("*").alias("cnt"))


def merge_equal_cells(rows: DataFrame) -> DataFrame:
    """(cell_id, merged_id): cells with the same column in the workload rows share a number."""
    column = rows.groupBy("cell_id").agg(F.sort_array(F.collect_list(F.struct("query_id", "coef"))).alias("column"))
    named = column.select("cell_id", F.xxhash64(F.to_json("column")).alias("name"), F.to_json("column").alias("j"))
    first = named.groupBy("name", "j").agg(F.min("cell_id").alias("merged_id"))
    return named.join(first, ["name", "j"]).select("cell_id", "merged_id")


def prefix_sums(cells: DataFrame, value: str, dims: tuple[int, ...], block: int = BLOCK) -> DataFrame:
    """The summed-area table (cell_id, total): one running sum along each axis, split over the other axes' lines.

    A line longer than ``block`` is summed in blocks, a block a window, and the running sum of the
    blocks is added, so a window holds at most the larger of a block and the blocks of a line.
    """
    out = cells.select("cell_id", F.col(value).alias("total"))
    inner = 1
    for d in reversed(dims):
        keys = [F.expr(f"cell_id div {inner * d}").alias("outer"), F.expr(f"cell_id % {inner}").alias("inner")]
        out = out.select("cell_id", "total", *keys, F.expr(f"((cell_id div {inner}) % {d}) div {block}").alias("part"))
        w = Window.partitionBy("outer", "inner", "part").orderBy("cell_id").rowsBetween(Window.unboundedPreceding, 0)
        if d > block:
            parts = out.groupBy("outer", "inner", "part").agg(F.sum("total").alias("own"))
            before = Window.partitionBy("outer", "inner").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
            parts = parts.select("outer", "inner", "part", F.sum("own").over(before).alias("before"))
            out = out.withColumn("total", F.sum("total").over(w)).join(parts, ["outer", "inner", "part"])
            out = out.select("cell_id", F.when(F.col("before").isNull(), F.col("total")).otherwise(F.col("total") + F.col("before")).alias("total"))
        else:
            out = out.select("cell_id", F.sum("total").over(w).alias("total"))
        inner *= d
    return out


def box_answers(boxes: DataFrame, cells: DataFrame, value: str, dims: tuple[int, ...]) -> DataFrame:
    """Answers of axis-aligned boxes (query_id, lo0, hi0, lo1, ...; inclusive) from 2^k corners each.

    Costs n + m 2^k instead of m n; every row of ``boxes`` keeps its columns and gets ``answer``.
    """
    table = prefix_sums(cells, value, dims)
    corners = []
    for mask in range(2 ** len(dims)):
        at, ok, sign = F.lit(0).cast("long"), F.lit(True), 1
        for k, d in enumerate(dims):
            low = bool(mask >> k & 1)
            c = F.col(f"lo{k}") - 1 if low else F.col(f"hi{k}")
            ok, sign, at = ok & (c >= 0), -sign if low else sign, at * d + c
        corners.append(F.struct(F.when(ok, at).alias("cell_id"), F.lit(sign).alias("sign")))
    keys = boxes.select("query_id", F.inline(F.array(*corners))).where("cell_id IS NOT NULL")
    sums = keys.join(table, "cell_id").groupBy("query_id").agg(F.sum(F.col("sign") * F.col("total")).alias("answer"))
    return boxes.join(sums, "query_id")
