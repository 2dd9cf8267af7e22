"""Relations of several widths, joined and derived from the given tables for the column experiments."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from depmine.functions.prep import array_to_columns

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def star14(spark, sf_dir) -> DataFrame:
    t = lambda n: table(spark, sf_dir, n)
    joined = t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey"))
    return joined


def wide24(spark, sf_dir) -> DataFrame:
    t = lambda n: table(spark, sf_dir, n)
    nation = t("nation").select(F.col("n_nationkey").alias("_n"), F.col("n_name").alias("s_nation"))
    return (
        t("lineitem")
        .join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey"))
        .drop("o_orderkey")
        .join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
        .drop("c_custkey")
        .join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey"))
        .drop("s_suppkey")
        .join(nation, F.col("s_nationkey") == F.col("_n"))
        .drop("_n")
    )


def wide39(spark, sf_dir) -> DataFrame:
    t = lambda n: table(spark, sf_dir, n)
    region = t("region")
    geo = t("nation").join(region, F.col("n_regionkey") == F.col("r_regionkey"))
    of = lambda p: geo.select(F.col("n_nationkey").alias(f"_{p}"), F.col("n_name").alias(f"{p}_nname"), F.col("n_regionkey").alias(f"{p}_regionkey"), F.col("r_name").alias(f"{p}_region"))
    wide = wide24(spark, sf_dir).join(t("part"), F.col("l_partkey") == F.col("p_partkey")).drop("p_partkey")
    wide = wide.join(of("c"), F.col("c_nationkey") == F.col("_c")).drop("_c").join(of("s"), F.col("s_nationkey") == F.col("_s")).drop("_s", "s_nname")
    dates = {"ship_year": F.year("l_shipdate"), "ship_month": F.month("l_shipdate"), "order_year": F.year("o_orderdate"), "order_month": F.month("o_orderdate"), "order_weekday": F.dayofweek("o_orderdate")}
    return wide.withColumns(dates)


def wide60(spark, sf_dir) -> DataFrame:
    bucket = lambda c, w: F.floor(F.col(c) / w).cast("int")
    return wide39(spark, sf_dir).withColumns(
        {
            "ship_quarter": F.quarter("l_shipdate"), "order_quarter": F.quarter("o_orderdate"), "b_quantity": bucket("l_quantity", 10), "b_price": bucket("l_extendedprice", 10_000),
            "b_discount": bucket("l_discount", 0.05), "b_tax": bucket("l_tax", 0.04), "b_total": bucket("o_totalprice", 50_000), "b_cbal": bucket("c_acctbal", 1_000), "b_sbal": bucket("s_acctbal", 1_000),
            "b_retail": bucket("p_retailprice", 100), "b_size": bucket("p_size", 10), "brand_no": F.regexp_extract("p_brand", r"(\d+)", 1), "name_1": F.split("p_name", " ")[0], "name_2": F.get(F.split("p_name", " "), F.lit(1)),
            "m_order": F.col("l_orderkey") % 7, "m_part": F.col("l_partkey") % 11, "m_supp": F.col("l_suppkey") % 5, "m_cust": F.col("o_custkey") % 13,
            "ship_weekday": F.dayofweek("l_shipdate"), "ship_day": F.dayofmonth("l_shipdate"), "ship_lag": F.datediff("l_shipdate", "o_orderdate"),
        }
    )


def wide109(spark, sf_dir) -> DataFrame:
    flat = array_to_columns(table(spark, sf_dir, "embeddings"), "embedding", 64, "d")
    fine = [F.floor(F.col(f"d{i}") * 40).cast("int").alias(f"d{i}") for i in range(64)]
    coarse = [F.floor(F.col(f"d{i}") * 6).cast("int").alias(f"q{i}") for i in range(43)]
    return flat.select("vec_id", "label", *fine, *coarse)


VIEWS = {"star14": star14, "wide24": wide24, "wide39": wide39, "wide60": wide60, "wide109": wide109}


def relation(spark, sf_dir, name: str) -> DataFrame:
    return VIEWS[name](spark, sf_dir) if name in VIEWS else table(spark, sf_dir, name)
