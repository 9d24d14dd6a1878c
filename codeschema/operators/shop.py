"""The document store that stands in for an application's: collections made from the tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import read_table
from .migrate import Duplication


def customers(spark: SparkSession, d: str, with_arrays: bool = True) -> DataFrame:
    c = read_table(spark, d, "customer").select(F.col("c_custkey").alias("_id"), F.col("c_name").alias("name"), F.col("c_acctbal").alias("acctbal"), F.col("c_mktsegment").alias("mktsegment"), F.col("c_nationkey").alias("nation"))
    if not with_arrays:
        return c
    o = read_table(spark, d, "orders").select(F.col("o_custkey").alias("_id"), "o_orderkey")
    held = o.groupBy("_id").agg(F.sort_array(F.collect_set("o_orderkey")).alias("orders"))
    lines = read_table(spark, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey"), "l_partkey").distinct()
    bought = o.join(lines, "o_orderkey").groupBy("_id").agg(F.sort_array(F.collect_set("l_partkey")).alias("parts"))
    none = F.array().cast("array<bigint>")
    return c.join(held, "_id", "left").join(bought, "_id", "left").withColumn("orders", F.coalesce("orders", none)).withColumn("parts", F.coalesce("parts", none))


def orders(spark: SparkSession, d: str) -> DataFrame:
    o = read_table(spark, d, "orders").select(F.col("o_orderkey").alias("_id"), F.col("o_custkey").alias("customer"), F.col("o_orderstatus").alias("status"), F.col("o_totalprice").alias("totalprice"), F.col("o_orderdate").alias("orderdate"), F.col("o_orderpriority").alias("priority"))
    lines = read_table(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("_id")).agg(F.sort_array(F.collect_set("l_partkey")).alias("items"), F.sort_array(F.collect_set("l_suppkey")).alias("origins"), F.struct(F.count("*").alias("n_lines"), F.sum("l_quantity").alias("total_qty")).alias("summary"))
    none = F.array().cast("array<bigint>")
    return o.join(lines, "_id", "left").withColumn("items", F.coalesce("items", none)).withColumn("origins", F.coalesce("origins", none))


def parts(spark: SparkSession, d: str) -> DataFrame:
    p = read_table(spark, d, "part").select(F.col("p_partkey").alias("_id"), F.col("p_name").alias("name"), F.col("p_brand").alias("brand"), F.col("p_type").alias("type"), F.col("p_size").alias("size"), F.col("p_retailprice").alias("retailprice"))
    lines = read_table(spark, d, "lineitem").groupBy(F.col("l_partkey").alias("_id")).agg(F.sort_array(F.collect_set("l_suppkey")).alias("suppliers"), F.struct(F.count("*").alias("n_lines"), F.sum("l_quantity").alias("total_qty")).alias("summary"))
    return p.join(lines, "_id", "left").withColumn("suppliers", F.coalesce("suppliers", F.array().cast("array<bigint>")))


def suppliers(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "supplier").select(F.col("s_suppkey").alias("_id"), F.col("s_name").alias("name"), F.col("s_acctbal").alias("acctbal"), F.col("s_nationkey").alias("nation"))


def events(spark: SparkSession, d: str) -> DataFrame:
    return read_table(spark, d, "events").select(F.col("event_id").alias("_id"), "ts", F.col("user_id").alias("actor"), F.col("event_type").alias("kind"), "value", F.from_json("props", "k bigint").alias("payload"))


def docs(spark: SparkSession, d: str) -> DataFrame:
    t = read_table(spark, d, "documents").select(F.col("doc_id").alias("_id"), "lang", "source", "n_chars")
    marks = read_table(spark, d, "labels").select(F.col("doc_id").alias("_id"), F.struct("quality", "toxic").alias("label"))
    return t.join(marks, "_id", "left")


COLLECTIONS = {"customers": customers, "orders": orders, "parts": parts, "suppliers": suppliers, "events": events, "docs": docs}

#: The size of the published data set, by what each collection stands for.
PUBLISHED = {"customers": 10, "orders": 20, "parts": 60, "suppliers": 8}


def published(spark: SparkSession, d: str) -> dict[str, DataFrame]:
    """The collections cut to the published sizes by least key; references that lead out of them stay, as dangling ones."""
    return {name: COLLECTIONS[name](spark, d).orderBy("_id").limit(n) for name, n in PUBLISHED.items()}


#: The seven join queries; the sixth has two joins.
JOINS = {
    "j1": Duplication("customers", "orders", "orders", ("orderdate",), "order_orderdate", many=True),
    "j2": Duplication("customers", "parts", "parts", ("name",), "part_name", many=True),
    "j3": Duplication("orders", "customers", "orders", ("name",), "customer_name", reverse=True),
    "j4": Duplication("orders", "parts", "items", ("name",), "part_name", many=True),
    "j5": Duplication("orders", "suppliers", "origins", ("name",), "supplier_name", many=True),
    "j6a": Duplication("parts", "orders", "items", ("priority", "orderdate"), "order_info", many=True, reverse=True),
    "j6b": Duplication("parts", "customers", "parts", ("name",), "customer_name", many=True, reverse=True),
    "j7": Duplication("parts", "suppliers", "suppliers", ("name",), "supplier_name", many=True),
}
