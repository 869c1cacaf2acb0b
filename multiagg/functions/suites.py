"""Scalar functions on the given tables, grouped by kind; all stay in generated code."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def string_suite(part: DataFrame) -> DataFrame:
    return part.select(
        "p_partkey", F.upper("p_name").alias("upper_name"), F.substring("p_brand", 1, 5).alias("head"), F.length("p_name").cast("long").alias("n"), F.concat_ws("-", "p_brand", "p_type").alias("both"),
        F.trim(F.concat(F.lit("  "), "p_type", F.lit(" "))).alias("trimmed"), F.regexp_replace("p_name", "a", "A").alias("replaced"), F.element_at(F.split("p_name", " "), 1).alias("first_word"), F.regexp_extract("p_brand", "([0-9]+)", 1).alias("digits"),
    )


def date_suite(orders: DataFrame) -> DataFrame:
    d = F.col("o_orderdate")
    return orders.select("o_orderkey", F.year(d).cast("long").alias("y"), F.month(d).cast("long").alias("m"), F.date_trunc("month", d).cast("date").cast("string").alias("month_start"), F.datediff(d.cast("date"), F.lit("1992-01-01").cast("date")).cast("long").alias("days"), F.date_add(d.cast("date"), 30).cast("string").alias("due"))


def math_suite(customer: DataFrame) -> DataFrame:
    b = F.col("c_acctbal")
    return customer.select("c_custkey", F.round(b, 0).cast("long").alias("rounded"), F.floor(b / 100).cast("long").alias("band"), F.abs(b).alias("size"), F.round(F.sqrt(F.abs(b)), 6).alias("root"), F.pmod(F.col("c_custkey"), F.lit(7)).alias("rest"), F.round(F.log10(F.abs(b) + 1), 6).alias("log"))


def array_suite(embeddings: DataFrame) -> DataFrame:
    e = F.col("embedding")
    return embeddings.select("vec_id", F.size(e).cast("long").alias("n"), F.element_at(e, 1).cast("double").alias("head"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("n_positive"), F.slice(e, 1, 2).cast("array<double>").getItem(1).alias("second"), F.array_max(e).cast("double").alias("most"))


def map_suite(nation: DataFrame) -> DataFrame:
    m = F.map_from_arrays(F.array(F.lit("key"), F.lit("region")), F.array("n_nationkey", "n_regionkey"))
    return nation.select("n_name", m["region"].cast("long").alias("region"), F.size(F.map_keys(m)).cast("long").alias("n"))


def struct_suite(nation: DataFrame) -> DataFrame:
    packed = nation.select(F.struct("n_nationkey", "n_regionkey").alias("node"), "n_name")
    return packed.groupBy("node").agg(F.count("*").alias("cnt")).select(F.col("node.n_nationkey").cast("long").alias("left_key"), F.col("node.n_regionkey").cast("long").alias("right_key"), "cnt")


def json_suite(events: DataFrame) -> DataFrame:
    return events.select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"), F.from_json("props", "k long")["k"].alias("k2"))


def conditional_suite(orders: DataFrame) -> DataFrame:
    p = F.col("o_totalprice")
    return orders.select("o_orderkey", F.when(p > 200000, "high").when(p > 100000, "mid").otherwise("low").alias("band"), F.coalesce(F.nullif("o_orderstatus", F.lit("F")), F.lit("none")).alias("status"))


def cast_suite(lineitem: DataFrame) -> DataFrame:
    return lineitem.groupBy("l_returnflag").agg(F.sum(F.col("l_quantity").cast("decimal(18,2)")).alias("qty"), F.sum(F.expr("try_cast(l_linestatus AS INT)")).alias("bad"), F.sum(F.col("l_quantity").cast("long")).alias("whole"))


def explode_suite(part: DataFrame) -> DataFrame:
    return part.select("p_partkey", F.posexplode(F.split("p_name", " ")).alias("pos", "word")).groupBy("word").agg(F.count("*").alias("cnt"), F.max("pos").cast("long").alias("last_pos"))
