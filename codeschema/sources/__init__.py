"""Readers and writers of tables, programs and models."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def as_files(df: DataFrame) -> DataFrame:
    """Rows (app_id, version, path, content, lang) with the content's hash."""
    return df.select(F.col("app_id").cast("string").alias("app_id"), F.col("version").cast("int").alias("version"), "path", "content", F.sha2("content", 256).alias("sha"), "lang")


def read_sources(spark: SparkSession, path: str, app_id: str = "app", version: int = 1, pattern: str = "*.js") -> DataFrame:
    """Program files below a folder, one row each (whole texts)."""
    raw = spark.read.format("binaryFile").option("pathGlobFilter", pattern).option("recursiveFileLookup", "true").load(path)
    return as_files(raw.select(F.lit(app_id).alias("app_id"), F.lit(version).alias("version"), "path", F.decode("content", "UTF-8").alias("content"), F.lit("js").alias("lang")))


def read_documents(spark: SparkSession, path: str, schema: str | None = None) -> DataFrame:
    """JSON documents of a collection."""
    reader = spark.read.schema(schema) if schema else spark.read
    return reader.json(path)


def write_documents(df: DataFrame, path: str) -> None:
    """A collection as JSON documents, one a line; fields that are null are left out."""
    df.write.mode("overwrite").json(path)


def read_graph(nodes: DataFrame, edges: DataFrame) -> dict[str, DataFrame]:
    """Collections from a property graph: nodes (label, _id, and properties), edges (label, source label, source, target).

    Each node label is a collection; each edge label is an array of references of its source.
    """
    out = {}
    for label in sorted(r[0] for r in nodes.select("label").distinct().collect()):  # a row a kind of node
        frame = nodes.where(F.col("label") == label).drop("label")
        kinds = sorted(r[0] for r in edges.where(F.col("source_label") == label).select("label").distinct().collect())
        for kind in kinds:
            held = edges.where((F.col("source_label") == label) & (F.col("label") == kind)).groupBy(F.col("source").alias("_id")).agg(F.sort_array(F.collect_set("target")).alias(kind))
            frame = frame.join(held, "_id", "left").withColumn(kind, F.coalesce(kind, F.array().cast(dict(held.dtypes)[kind])))
        out[label] = frame
    return out
