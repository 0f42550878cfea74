"""Point tables (row_key, x0, x1, ...) of the workloads on the given tables; features are expressions over the sources, so
only their columns are read."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import normal, uniform
from .io import table

LINE_KEY = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_shipdate", "l_extendedprice")


def points(df: DataFrame, key: Column, features: list[Column]) -> DataFrame:
    return df.select(key.cast("string").alias("row_key"), *[f.cast("double").alias(f"x{i}") for i, f in enumerate(features)])


def day(c: str) -> Column:
    return F.datediff(F.col(c).cast("date"), F.lit("1992-01-01").cast("date"))


def code(c: str, size: int = 16) -> Column:
    """A hash bucket of a string, the same in SQL."""
    return F.conv(F.substring(F.md5(F.col(c)), 1, 4), 16, 10).cast("long") % size


def line_key() -> Column:
    return F.concat_ws("|", *[F.col(c).cast("string") for c in LINE_KEY])


def _first(df: DataFrame, key: str, n: int) -> DataFrame:
    return df.withColumn("_h", uniform("shape", F.col(key))).orderBy("_h", key).limit(n)


def rings(spark: SparkSession, sf_dir: str, n: int = 300) -> DataFrame:
    o = _first(table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice"), "o_orderkey", n)
    angle, radius = 2 * math.pi * uniform("ring", F.col("o_orderkey")), F.when(F.col("o_orderkey") % 2 == 0, 1.0).otherwise(0.5)
    wobble = [0.05 * normal("ring", t, F.col("o_orderkey"), F.col("o_totalprice").cast("long")) for t in ("x", "y")]
    return points(o, F.col("o_orderkey"), [radius * F.cos(angle) + wobble[0], radius * F.sin(angle) + wobble[1]])


def spiral(spark: SparkSession, sf_dir: str, n: int = 300) -> DataFrame:
    o = _first(table(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate"), "o_orderkey", n)
    t = (day("o_orderdate") % 1000) / F.lit(1000.0)
    angle, radius = 3 * t + 2 * math.pi / 3 * (F.col("o_orderkey") % 3), 1 + 9 * t
    return points(o, F.col("o_orderkey"), [radius * F.cos(angle), radius * F.sin(angle)])


def moons(spark: SparkSession, sf_dir: str, n: int = 400, noise: float = 0.05) -> DataFrame:
    o = _first(table(spark, sf_dir, "orders").select("o_orderkey"), "o_orderkey", n)
    a, lower = math.pi * uniform("moon", F.col("o_orderkey")), F.col("o_orderkey") % 2 == 1
    x = F.when(lower, 1 - F.cos(a)).otherwise(F.cos(a)) + noise * normal("mx", F.col("o_orderkey"))
    y = F.when(lower, 0.5 - F.sin(a)).otherwise(F.sin(a)) + noise * normal("my", F.col("o_orderkey"))
    return points(o, F.col("o_orderkey"), [x, y])


def blobs(spark: SparkSession, sf_dir: str, n: int = 600, varied: bool = False) -> DataFrame:
    rows = table(spark, sf_dir, "lineitem").select(line_key().alias("key"), "l_returnflag", "l_linestatus")
    rows = _first(rows, "key", n)
    group = F.concat("l_returnflag", "l_linestatus")
    spread = F.lit(0.5) if not varied else 0.3 + uniform("spread", group)
    return points(rows, F.col("key"), [20 * uniform("centre", t, group) + spread * normal("blob", t, F.col("key")) for t in ("x", "y")])


def customer7(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = table(spark, sf_dir, "orders").groupBy("o_custkey").agg(
        F.count(F.lit(1)).alias("n"), F.avg("o_totalprice").alias("a"), F.max("o_totalprice").alias("b"), F.sum("o_totalprice").alias("s"),
        F.datediff(F.max("o_orderdate"), F.min("o_orderdate")).alias("span"),
    )
    c = table(spark, sf_dir, "customer").join(o, F.col("c_custkey") == F.col("o_custkey"), "left")
    return points(c, F.col("c_custkey"), [F.col("c_acctbal"), F.col("c_nationkey"), *[F.coalesce(F.col(x), F.lit(0)) for x in ("n", "a", "b", "s", "span")]])


def part2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return points(table(spark, sf_dir, "part"), F.col("p_partkey"), [F.col("p_size"), F.col("p_retailprice")])


def embeddings(spark: SparkSession, sf_dir: str, dims: int = 22) -> DataFrame:
    return points(table(spark, sf_dir, "embeddings"), F.col("vec_id"), [F.get("embedding", i) for i in range(dims)])


def events4(spark: SparkSession, sf_dir: str) -> DataFrame:
    return points(table(spark, sf_dir, "events"), F.col("event_id"), [F.col("value"), F.hour("ts"), F.get_json_object("props", "$.k").cast("int"), F.col("user_id")])


def orders8(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(
        F.count(F.lit(1)).alias("n"), F.sum("l_quantity").alias("q"), F.avg("l_extendedprice").alias("p"), F.avg("l_discount").alias("dc"), F.avg("l_tax").alias("t"),
        F.datediff(F.max("l_shipdate"), F.min("l_shipdate")).alias("span"),
    )
    o = table(spark, sf_dir, "orders").join(lines, F.col("o_orderkey") == F.col("l_orderkey"), "left")
    return points(o, F.col("o_orderkey"), [F.col("o_totalprice"), day("o_orderdate"), *[F.coalesce(F.col(x), F.lit(0)) for x in ("n", "q", "p", "dc", "t", "span")]])


def line(spark: SparkSession, sf_dir: str, *columns: str) -> DataFrame:
    return points(table(spark, sf_dir, "lineitem"), line_key(), [F.col(c) for c in columns])


def wide23(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Lines with the columns of their order, customer, part, supplier and nation; the last feature is constant."""
    t = lambda name: table(spark, sf_dir, name)
    j = (
        t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
        .join(t("part"), F.col("l_partkey") == F.col("p_partkey")).join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey")).join(t("nation"), F.col("s_nationkey") == F.col("n_nationkey"))
    )
    plain = ["l_quantity", "l_extendedprice", "l_discount", "l_tax", "l_linenumber", "o_totalprice", "c_nationkey", "c_acctbal", "p_size", "p_retailprice", "s_acctbal", "s_nationkey", "n_regionkey"]
    coded = ["l_returnflag", "l_linestatus", "o_orderpriority", "o_orderstatus", "c_mktsegment", "p_brand"]
    return points(j, line_key(), [*[F.col(c) for c in plain], day("l_shipdate"), day("o_orderdate"), *[code(c) for c in coded], F.length("p_type"), F.lit(1)])


def text8(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = table(spark, sf_dir, "documents")
    words = F.split("text", " ")
    n = F.greatest(F.size(words), F.lit(1))
    digits = F.length(F.regexp_replace("text", "[^0-9]", "")) / F.greatest(F.length("text"), F.lit(1))
    copies = d.groupBy(F.md5("text").alias("_md5")).agg(F.count(F.lit(1)).alias("copies"))
    d = d.withColumn("_m", F.md5("text")).join(copies, F.col("_m") == F.col("_md5"))
    return points(d, F.col("doc_id"), [F.col("n_chars"), F.size(words), F.size(F.array_distinct(words)) / n, F.size(F.split("text", "\n")), digits, F.length("text") / n, code("lang"), F.col("copies")])


def pages4(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = table(spark, sf_dir, "pages")
    return points(p, F.col("page_id"), [F.length("html"), F.regexp_count("html", F.lit("<[a-z]")), F.regexp_count("html", F.lit("href=")), F.size(F.split("url", "/"))])


def conversations4(spark: SparkSession, sf_dir: str) -> DataFrame:
    c = table(spark, sf_dir, "conversations").groupBy("conv_id").agg(
        F.count(F.lit(1)).alias("turns"), *[F.sum(F.when(F.col("role") == r, F.length("text")).otherwise(0)).alias(r) for r in ("user", "assistant", "system")]
    )
    return points(c, F.col("conv_id"), [F.col("turns"), F.col("user"), F.col("assistant"), F.col("system")])


def benchmark1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return points(table(spark, sf_dir, "benchmark"), F.col("item_id"), [F.length("text")])


#: id -> (name, dimension, maker)
WORKLOADS: dict[str, tuple[str, int, Callable[[SparkSession, str], DataFrame]]] = {
    "W1": ("rings", 2, rings), "W2": ("spiral", 2, spiral), "W3": ("moons", 2, moons), "W3b": ("moons, more noise", 2, lambda s, d: moons(s, d, noise=0.15)),
    "W4": ("blobs 600", 2, blobs), "W5": ("blobs 1200, varied", 2, lambda s, d: blobs(s, d, 1200, True)), "W6": ("blobs 2100", 2, lambda s, d: blobs(s, d, 2100)),
    "W7": ("customers", 7, customer7), "W8": ("parts", 2, part2), "W9": ("embeddings", 22, embeddings), "W9b": ("embeddings, all", 64, lambda s, d: embeddings(s, d, 64)),
    "W10": ("events", 4, events4), "W11": ("orders", 8, orders8), "W12": ("lines, 3", 3, lambda s, d: line(s, d, "l_quantity", "l_extendedprice", "l_discount")),
    "W13": ("lines, wide", 23, wide23), "W14": ("lines, 2", 2, lambda s, d: line(s, d, "l_quantity", "l_extendedprice")), "W15": ("lines, 3 with tax", 3, lambda s, d: line(s, d, "l_quantity", "l_extendedprice", "l_tax")),
    "W23": ("texts", 8, text8), "W24": ("pages", 4, pages4), "W24b": ("conversations", 4, conversations4), "W24c": ("benchmark", 1, benchmark1),
}


def load(spark: SparkSession, sf_dir: str, workload: str) -> DataFrame:
    return WORKLOADS[workload][2](spark, sf_dir)
