"""The given tables and the public domains declared over them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.domain import Attribute as A
from ..functions.domain import Domain

START = "1995-01-01"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def domain(name: str) -> Domain:
    qty, price, ship = F.col("l_quantity"), F.col("l_extendedprice"), F.col("l_shipdate")
    disc, tax = F.round(F.col("l_discount") * 100), F.round(F.col("l_tax") * 100)
    days = lambda k, num, den: A.dates("ship", ship, START, num, den, k)
    q = lambda k: A("qty", F.floor((qty - 1) * k / 50).cast("long"), k)
    p = lambda step, k: A.width("price", price, 0, step, k)
    flags = [
        qty > 25, disc >= 5, tax >= 4, price >= 50000, ship >= F.lit("1998-07-01").cast("timestamp"), F.col("l_returnflag") == "R",
        F.col("l_linestatus") == "O", F.col("l_linenumber") >= 4, F.col("p_size") > 25, F.col("o_orderpriority").isin("1-URGENT", "2-HIGH"),
    ]
    made = {
        "ship_1024": [days(1024, 2, 5)],
        "ship_price_32x32": [days(32, 1, 80), p(3300, 32)],
        "qty_price_ship_16x8x8": [q(16), p(13200, 8), days(8, 1, 320)],
        "five_4": [q(4), A("disc", F.floor(disc / 3).cast("long"), 4), A("tax", F.floor(tax * 4 / 9).cast("long"), 4), p(26400, 4), days(4, 1, 640)],
        "ten_2": [A.flag(f"f{i}", c) for i, c in enumerate(flags)],
        "qty_64": [A.width("qty", qty, 1, 1, 64)],
        "qty_8": [A.width("qty", qty, 1, 7, 8)],
        **{f"qty_{n}": [q(n)] for n in (4, 6, 16, 50)},
        "ship_256": [days(256, 1, 10)],
        "ship_price_qty_1024x1024x1024": [days(1024, 2, 5), A("price", F.floor(price * 1024 / 105600).cast("long"), 1024), q(1024)],
        "flags_3x2x11": [A.categories("flag", F.col("l_returnflag"), ["A", "N", "R"]), A.categories("status", F.col("l_linestatus"), ["F", "O"]), A("disc", disc.cast("long"), 11)],
        "pair_8x8": [q(8), A("price", F.floor(price * 8 / 105600).cast("long"), 8)],
        "type_5": [A.categories("type", F.col("event_type"), ["click", "error", "purchase", "signup", "view"])],
        "type_groups": [A.groups("kind", F.col("p_type"), [["ECONOMY", "STANDARD"], ["PROMO"], ["SMALL", "MEDIUM", "LARGE"]])],
    }
    return Domain(tuple(made[name]))


def star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """lineitem with its part and order: one row per lineitem row, so still one record per protected row."""
    part = table(spark, sf_dir, "part").select("p_partkey", "p_size")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_orderpriority")
    item = table(spark, sf_dir, "lineitem")
    return item.join(part, F.col("l_partkey") == F.col("p_partkey")).join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
