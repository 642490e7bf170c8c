"""Given tables and the fixtures derived from them.

A fixture is a flat DataFrame of integer codes (or one code and one number) with a row key ``rk``
made of integers, so that hash samples do not depend on how a number is printed.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.columns import zero

FLAGS = ("A", "N", "R")
STATUS = ("F", "O", "P")
SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")
PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def load(spark: SparkSession, path: str, fmt: str = "parquet", schema: str | None = None, **options: str) -> DataFrame:
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def save(df: DataFrame, path: str, fmt: str = "parquet", mode: str = "overwrite", by: list[str] | None = None) -> None:
    writer = df.write.format(fmt).mode(mode)
    (writer.partitionBy(*by) if by else writer).save(path)


def coded(c: Column, values: tuple[str, ...]) -> Column:
    """Dictionary code of a small fixed domain; values outside it get the code after the last."""
    out = F.lit(len(values))
    for i, v in enumerate(values):
        out = F.when(c == F.lit(v), F.lit(i)).otherwise(out)
    return out


@dataclass(frozen=True)
class Fixture:
    """Codes ``columns`` with domain sizes ``sizes``; ``target`` names a numeric column where there is one."""

    name: str
    columns: tuple[str, ...]
    sizes: tuple[int, ...]
    build: Callable[[SparkSession, str], DataFrame]
    target: str | None = None

    @property
    def joint_domain(self) -> int:
        n = 1
        for k in self.sizes:
            n *= k
        return n


def lineitem_key() -> Column:
    days = F.datediff(F.col("l_shipdate").cast("date"), F.lit("1970-01-01").cast("date"))
    return F.concat_ws("|", "l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", F.col("l_quantity").cast("int"), F.round(F.col("l_extendedprice") * 100).cast("long"), days)


def _d1(spark: SparkSession, sf_dir: str) -> DataFrame:
    li = table(spark, sf_dir, "lineitem")
    unit = F.floor(F.log(F.col("l_extendedprice") / F.col("l_quantity"))).cast("int") - 3
    return li.select(
        lineitem_key().alias("rk"),
        F.floor((F.col("l_quantity") - 1) / 5).cast("int").alias("qty_band"),
        F.greatest(F.lit(0), F.least(F.lit(7), unit)).alias("unit_band"),
        coded(F.col("l_returnflag"), FLAGS).alias("flag"),
    )


def _indep(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(
        lineitem_key().alias("rk"),
        coded(F.col("l_returnflag"), FLAGS).alias("flag"),
        coded(F.col("l_linestatus"), ("F", "O")).alias("status"),
        (F.col("l_linenumber") - 1).cast("int").alias("line"),
        F.round(F.col("l_discount") * 100 + 0.0).cast("int").alias("disc"),
    )


def _d2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").select(
        lineitem_key().alias("rk"),
        F.floor((F.col("l_quantity") - 1) / 5).cast("int").alias("qty_band"),
        F.log(F.col("l_extendedprice") / F.col("l_quantity")).alias("log_unit"),
    )


def orders_with_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """orders, customer and nation joined; nation has 25 rows, customer's place is left to the optimizer."""
    o, c, n = (table(spark, sf_dir, t) for t in ("orders", "customer", "nation"))
    c = c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey"))
    return o.join(c, F.col("o_custkey") == F.col("c_custkey"))


def _d3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return code_orders(orders_with_nation(spark, sf_dir))


def code_orders(joined: DataFrame, *more: str) -> DataFrame:
    return joined.select(
        F.col("o_orderkey").cast("string").alias("rk"),
        F.col("c_nationkey").cast("int").alias("nation"),
        F.col("n_regionkey").cast("int").alias("region"),
        coded(F.col("c_mktsegment"), SEGMENTS).alias("segment"),
        coded(F.col("o_orderstatus"), STATUS).alias("status"),
        coded(F.col("o_orderpriority"), PRIORITIES).alias("priority"),
        *more,
    )


def _d4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "part").select(F.col("p_partkey").cast("string").alias("rk"), F.floor(F.col("p_partkey") % 1000 / 100).cast("int").alias("key_band"), F.col("p_retailprice").alias("retailprice"))


def _d5(spark: SparkSession, sf_dir: str) -> DataFrame:
    price, disc = F.col("l_extendedprice"), zero(F.col("l_discount"))
    return table(spark, sf_dir, "lineitem").select(
        lineitem_key().alias("rk"),
        F.round(disc * 100).cast("int").alias("disc"),
        F.least(F.lit(9), F.floor((price - 900) / 10410)).cast("int").alias("price_band"),
        F.least(F.lit(9), F.floor(price * (1 - disc) / 10500)).cast("int").alias("rev_band"),
        coded(F.col("l_returnflag"), FLAGS).alias("flag"),
    )


def _d6(spark: SparkSession, sf_dir: str) -> DataFrame:
    low = F.lower(F.col("text"))
    share = lambda s, by, most: F.least(F.lit(most), F.floor(F.regexp_count(low, F.lit(s)) * F.lit(100.0 * by) / F.greatest(F.length("text"), F.lit(1)))).cast("int")
    return table(spark, sf_dir, "documents").select(
        F.col("doc_id").cast("string").alias("rk"), share("th", 1, 5).alias("th"), share("é", 1, 5).alias("e_acute"), share("ü", 2, 3).alias("u_uml"), share("ñ", 1, 3).alias("n_tilde"),
        coded(F.col("lang"), ("de", "en", "es", "fr")).alias("lang"),
    )


def _v1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """First eight embedding positions in eight bands of a fixed width (unit vectors of 64 values)."""
    cells = [F.least(F.lit(7), F.greatest(F.lit(0), F.floor((F.col("embedding")[i] + 0.25) / 0.0625).cast("int"))).alias(f"e{i + 1}") for i in range(8)]
    return table(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("string").alias("rk"), *cells)


def _j1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders with customers and nations: the segment as category, the logarithm of the price as number."""
    return orders_with_nation(spark, sf_dir).select(F.col("o_orderkey").cast("string").alias("rk"), coded(F.col("c_mktsegment"), SEGMENTS).alias("segment"), F.log(F.col("o_totalprice")).alias("log_price"))


def _j2(spark: SparkSession, sf_dir: str) -> DataFrame:
    li, p, s = (table(spark, sf_dir, t) for t in ("lineitem", "part", "supplier"))
    j = li.join(p, F.col("l_partkey") == F.col("p_partkey")).join(s, F.col("l_suppkey") == F.col("s_suppkey"))
    return j.select(
        lineitem_key().alias("rk"), F.least(F.lit(9), F.floor(F.col("p_size") / 5)).cast("int").alias("size_band"), F.col("s_nationkey").cast("int").alias("s_nation"),
        F.floor((F.col("l_quantity") - 1) / 5).cast("int").alias("qty_band"), F.col("l_shipdate"),
    )


INDEP = Fixture("indep", ("flag", "status", "line", "disc"), (3, 2, 7, 11), _indep)
D1 = Fixture("d1", ("qty_band", "unit_band", "flag"), (10, 8, 3), _d1)
D2 = Fixture("d2", ("qty_band",), (10,), _d2, "log_unit")
D3 = Fixture("d3", ("nation", "region", "segment", "status", "priority"), (25, 5, 5, 3, 5), _d3)
D4 = Fixture("d4", ("key_band",), (10,), _d4, "retailprice")
D5 = Fixture("d5", ("disc", "price_band", "rev_band", "flag"), (11, 10, 10, 3), _d5)
D6 = Fixture("d6", ("th", "e_acute", "u_uml", "n_tilde", "lang"), (6, 6, 4, 4, 4), _d6)
V1 = Fixture("v1", tuple(f"e{i}" for i in range(1, 9)), (8,) * 8, _v1)
J1 = Fixture("j1", ("segment",), (5,), _j1, "log_price")
J2 = Fixture("j2", ("size_band", "s_nation", "qty_band"), (11, 25, 10), _j2)
FIXTURES = {f.name: f for f in (INDEP, D1, D2, D3, D4, D5, D6, V1, J1, J2)}


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with a timestamp type that watermarks accept, and the number k from the JSON properties."""
    return table(spark, sf_dir, "events").select(
        "event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", zero(F.col("value")).alias("value"), F.get_json_object("props", "$.k").cast("int").alias("k")
    )
