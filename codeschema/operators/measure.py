"""Measures: how an inferred schema compares with the intended one, how many operations and joins were found, what runs cost."""

from __future__ import annotations

import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def score_schema(inferred: DataFrame, truth: DataFrame) -> DataFrame:
    """Precision, recall and F1 (to 6 digits) of features by kind and in all (kind ``all``)."""
    pick = lambda s, name: s.select("entity", "feature", "kind").distinct().withColumn(name, F.lit(1))
    both = pick(inferred, "got").join(pick(truth, "due"), ["entity", "feature", "kind"], "full").na.fill(0, ["got", "due"])
    g = both.rollup("kind")
    s = g.agg(F.sum(F.col("got") * F.col("due")).alias("n_right"), F.sum("got").alias("n_found"), F.sum("due").alias("n_true"))
    p, r = F.col("n_right") / F.nullif(F.col("n_found"), F.lit(0)), F.col("n_right") / F.nullif(F.col("n_true"), F.lit(0))
    return s.select(F.coalesce("kind", F.lit("all")).alias("kind"), "n_right", "n_found", "n_true", F.round(p, 6).alias("precision"), F.round(r, 6).alias("recall"), F.round(2 * p * r / F.nullif(p + r, F.lit(0.0)), 6).alias("f1"))


def score_pairs(found: DataFrame, truth: DataFrame, on: list[str]) -> DataFrame:
    """Precision and recall of a set of rows (references, joins, plans)."""
    both = found.select(*on).distinct().withColumn("got", F.lit(1)).join(truth.select(*on).distinct().withColumn("due", F.lit(1)), on, "full").na.fill(0, ["got", "due"])
    s = both.agg(F.coalesce(F.sum(F.col("got") * F.col("due")), F.lit(0)).alias("n_right"), F.coalesce(F.sum("got"), F.lit(0)).alias("n_found"), F.coalesce(F.sum("due"), F.lit(0)).alias("n_true"))
    return s.select("*", F.round(F.col("n_right") / F.nullif(F.col("n_found"), F.lit(0)), 6).alias("precision"), F.round(F.col("n_right") / F.nullif(F.col("n_true"), F.lit(0)), 6).alias("recall"))


def determined_types(schema: DataFrame) -> DataFrame:
    """Of each entity: attributes, and how many have a type that code shows."""
    a = schema.where("kind = 'attribute'")
    return a.groupBy("app_id", "entity").agg(F.count("*").alias("n_attributes"), F.sum((F.col("evidence") != "default").cast("int")).alias("n_determined"))


def lower_bounds(schema: DataFrame, profiled: DataFrame) -> DataFrame:
    """References and aggregates with the lower bound from code (always 0) and from data."""
    s = schema.where("kind in ('reference', 'aggregate')").select("entity", "feature", F.col("lower").alias("code_lower")).distinct()
    return s.join(profiled.select("entity", "feature", F.col("lower").alias("data_lower")), ["entity", "feature"]).withColumn("agree", F.col("code_lower") == F.col("data_lower"))


def code_data_agreement(schema: DataFrame, profiled: DataFrame) -> DataFrame:
    """Features by what shows them: (entity, feature, found, code_type, data_type, agree).

    ``found``: code, data or both.  A default type, a reference's and an aggregate's say nothing of the values, so ``agree`` is
    null there; whole numbers agree with any integer type.
    """
    code = schema.select("entity", "feature", "kind", F.col("type").alias("code_type"), "evidence").distinct()
    data = profiled.select(F.when(F.col("feature").contains("."), F.concat_ws(".", "entity", F.regexp_extract("feature", r"^(.*)\.[^.]+$", 1))).otherwise(F.col("entity")).alias("entity"), F.substring_index("feature", ".", -1).alias("feature"), F.col("type").alias("data_type"))
    both = code.join(data, ["entity", "feature"], "full")
    found = F.when(F.col("code_type").isNull(), "data").when(F.col("data_type").isNull(), "code").otherwise("both")
    number = F.when(F.col("data_type").isin("int", "bigint"), "long").otherwise(F.col("data_type"))
    agree = F.when((found == "both") & (F.col("kind") == "attribute") & (F.col("evidence") == "literal"), F.col("code_type") == number)
    return both.select("entity", "feature", found.alias("found"), "code_type", "data_type", agree.alias("agree"))


def score_rollup(schema: DataFrame, truth: DataFrame) -> DataFrame:
    """How many features are right, found and true, by kind and entity, by kind, and in all (``*``)."""
    pick = lambda s, name: s.select("entity", "feature", "kind").distinct().withColumn(name, F.lit(1))
    both = pick(schema, "got").join(pick(truth, "due"), ["entity", "feature", "kind"], "full").na.fill(0, ["got", "due"])
    g = both.rollup("kind", "entity").agg(F.sum(F.col("got") * F.col("due")).alias("n_right"), F.sum("got").alias("n_found"), F.sum("due").alias("n_true"))
    return g.na.fill("*", ["kind", "entity"])


def corpus_scope(m, ops: DataFrame) -> DataFrame:
    """Files, functions, lines and operations by kind."""
    files = m.files.agg(F.count("*").alias("n_files"), F.sum(F.size(F.split("content", "\n"))).alias("n_lines"))
    units = m.units.where("kind = 'function'").agg(F.count("*").alias("n_functions"))
    kinds = ops.where("not synthetic").agg(F.count("*").alias("n_ops"), *[F.sum((F.col("kind") == k).cast("int")).alias(f"n_{k.lower()}") for k in "RIUD"])
    return files.crossJoin(units).crossJoin(kinds)  # a row each


def measure(run: Callable[[], DataFrame]) -> dict:
    """Seconds, rows and rows a second of a query, counted while it is written nowhere."""
    from pyspark.sql import Observation

    seen, start = Observation("measure"), time.time()
    df = run().observe(seen, F.count(F.lit(1)).alias("rows"))
    df.write.format("noop").mode("overwrite").save()
    took = time.time() - start
    return {"seconds": took, "rows": seen.get["rows"], "rows_per_second": seen.get["rows"] / took}
