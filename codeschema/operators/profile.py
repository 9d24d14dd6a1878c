"""Baselines: schemas from stored data, access points by patterns, entity versions without relationships."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..store import written
from ..functions import stem


def _paths(schema: T.StructType, base: str = "", inside: bool = False) -> list[tuple[str, T.DataType, bool]]:
    out = []
    for f in schema.fields:
        path, kind = f"{base}{f.name}", f.dataType
        out.append((path, kind, inside))
        item = kind.elementType if isinstance(kind, T.ArrayType) else kind
        if isinstance(item, T.StructType):
            out += _paths(item, path + ".", inside or isinstance(kind, T.ArrayType))
    return out


def profile_collection(df: DataFrame, entity: str, exact: bool = True) -> DataFrame:
    """Of each top-level or embedded field: type, how many objects have it, least and most members, distinct values.

    One scan with partial aggregates and sketches; ``exact`` counts distinct values besides, in long form (column, value).
    """
    found = [(p, t) for p, t, inside in _paths(df.schema) if not inside]
    aggs = [F.count("*").alias("n")]
    for i, (p, t) in enumerate(found):
        c = F.col(p)
        aggs += [F.count(c).alias(f"present_{i}")]
        if isinstance(t, T.ArrayType):
            aggs += [F.min(F.size(c)).alias(f"low_{i}"), F.max(F.size(c)).alias(f"high_{i}")]
        elif not isinstance(t, T.StructType):
            aggs += [F.approx_count_distinct(c).alias(f"distinct_{i}")]
    row = df.agg(*aggs)
    rows = []
    for i, (p, t) in enumerate(found):
        array, nested = isinstance(t, T.ArrayType), isinstance(t, T.StructType)
        low = F.when(F.col(f"present_{i}") < F.col("n"), 0).otherwise(F.col(f"low_{i}") if array else F.lit(1))
        rows.append(F.struct(F.lit(entity).alias("entity"), F.lit(p).alias("feature"), F.lit(t.simpleString() if not nested else "struct").alias("type"), F.col("n").alias("n_objects"), F.col(f"present_{i}").alias("n_present"), low.cast("int").alias("lower"), (F.col(f"high_{i}") if array else F.lit(1)).cast("int").alias("upper"), (F.lit(None).cast("long") if array or nested else F.col(f"distinct_{i}")).alias("n_distinct")))
    out = row.select(F.explode(F.array(*rows)).alias("x")).select("x.*")
    plain = [p for p, t in found if not isinstance(t, (T.ArrayType, T.StructType, T.MapType))]
    if not exact or not plain:
        return out
    cells = df.select(F.explode(F.array(*[F.struct(F.lit(p).alias("feature"), F.col(p).cast("string").alias("v")) for p in plain])).alias("c")).select("c.*").where("v is not null")
    counted = cells.distinct().groupBy("feature").agg(F.count("*").alias("exactly"))
    known = F.when(F.col("feature").isin(plain), F.coalesce("exactly", F.lit(0)))
    return out.join(counted, "feature", "left").withColumn("n_distinct", known).select(*out.columns)


def profile_schema(frames: dict[str, DataFrame], exact: bool = True) -> DataFrame:
    return reduce(DataFrame.unionByName, [profile_collection(df, name, exact) for name, df in sorted(frames.items())])


def data_variations(df: DataFrame, json_column: str | None = None) -> DataFrame:
    """Structures that stored objects have: the sorted names of their non-null fields, most frequent first."""
    if json_column:
        names = F.array_sort(F.json_object_keys(json_column))
    else:
        names = F.array_sort(F.filter(F.array(*[F.when(F.col(c).isNotNull(), F.lit(c)) for c in df.columns]), lambda x: x.isNotNull()))
    g = df.select(F.array_join(names, ",").alias("structure")).groupBy("structure").agg(F.count("*").alias("n"))
    return g.withColumn("variation", F.dense_rank().over(W.orderBy(F.desc("n"), "structure")))


def catalog(frames: dict[str, DataFrame]) -> DataFrame:
    """(entity, feature, type, n_present) of every top-level column: a row a column, with how many objects have a value there."""
    parts = []
    for e, df in sorted(frames.items()):
        row = df.agg(*[F.count(F.col(f"`{c}`")).alias(f"present_{i}") for i, c in enumerate(df.columns)])
        cells = [F.struct(F.lit(e).alias("entity"), F.lit(c).alias("feature"), F.lit(t).alias("type"), F.col(f"present_{i}").alias("n_present")) for i, (c, t) in enumerate(df.dtypes)]
        parts.append(row.select(F.inline(F.array(*cells))))
    return written(reduce(DataFrame.unionByName, parts), "catalog")


def references_by_name(columns: DataFrame) -> DataFrame:
    """Candidates for references: a key-like column whose stem is another entity's name (or that entity's key's stem)."""
    keyed = columns.where("type in ('int', 'bigint', 'array<bigint>')").select(F.col("entity").alias("holder"), F.col("feature").alias("field"), stem(F.col("feature")).alias("stem"))
    named = columns.select(F.col("entity").alias("referenced")).distinct().withColumn("stem", stem(F.col("referenced")))
    # Catalog rows only: a few for each table of the store.
    return keyed.join(named, "stem").where("holder <> referenced").select("holder", "field", "referenced")


def inclusion_candidates(frames: dict[str, DataFrame], by_name: bool = False) -> DataFrame:
    """Pairs (holder column, unique column of another table) of which every value occurs in the other.

    Distinct values of all integer columns are gathered once; a pair is kept if the shared values are all of the
    holder's.  Pairs are pruned by types and ranges before values are compared.
    """
    ints = [(e, c) for e, df in sorted(frames.items()) for c, t in df.dtypes if t in ("int", "bigint")]
    values = reduce(DataFrame.unionByName, [frames[e].select(F.lit(f"{e}.{c}").alias("column"), F.col(c).cast("long").alias("v")) for e, c in ints]).where("v is not null")
    distinct = written(values.groupBy("column", "v").agg(F.count("*").alias("n")), "distinct")  # the tables are read once
    stats = distinct.groupBy("column").agg(F.count("*").alias("n_values"), F.max("n").alias("most"), F.min("v").alias("low"), F.max("v").alias("high"))
    unique = stats.where("most = 1").select(F.col("column").alias("key"), F.col("low").alias("key_low"), F.col("high").alias("key_high"))
    pairs = stats.alias("s").join(unique, (F.col("s.low") >= F.col("key_low")) & (F.col("s.high") <= F.col("key_high")) & (F.substring_index("column", ".", 1) != F.substring_index("key", ".", 1))).select("column", "key", "n_values")
    if by_name:
        last = lambda c: F.regexp_extract(c, r"([a-z]+)$", 1)
        pairs = pairs.where(last(F.col("column")) == last(F.col("key")))
    hit = distinct.select("column", "v").join(pairs, "column").join(distinct.select(F.col("column").alias("key"), "v"), ["key", "v"]).groupBy("column", "key", "n_values").agg(F.count("*").alias("n_shared"))
    return hit.where("n_shared = n_values").select(F.col("column").alias("holder"), F.col("key").alias("referenced"), F.col("n_values"))


def detect_access_points(files: DataFrame, calls: tuple[str, ...] = ("findOne", "find", "aggregate", "insertOne", "insertMany", "updateOne", "updateMany", "deleteOne", "deleteMany", "countDocuments")) -> DataFrame:
    """Where a text calls the store, by pattern alone: (app_id, path, line, container, call)."""
    pattern = r"collection\(\s*['\"](\w+)['\"]\s*\)\s*\.\s*(" + "|".join(calls) + r")\s*\("
    lines = files.select("app_id", "version", "path", F.posexplode(F.split("content", "\n")).alias("line", "text"))
    hits = lines.select("app_id", "version", "path", (F.col("line") + 1).alias("line"), F.explode(F.arrays_zip(F.regexp_extract_all("text", F.lit(pattern), 1).alias("container"), F.regexp_extract_all("text", F.lit(pattern), 2).alias("call"))).alias("x"))
    return hits.select("app_id", "version", "path", "line", "x.container", "x.call")


def script_calls(pages: DataFrame) -> DataFrame:
    """The numbers that the scripts of each page, all of them, pass to ``track``."""
    scripts = F.array_join(F.regexp_extract_all("html", F.lit(r"(?s)<script[^>]*>(.*?)</script>"), 1), "\n")
    return pages.select("page_id", F.explode(F.regexp_extract_all(scripts, F.lit(r"track\((\d+)\)"), 1)).alias("track")).withColumn("track", F.col("track").cast("long"))



def track_entities(found: DataFrame) -> DataFrame:
    """Versions of each entity by field set only, with what came and went; no relationships (input: ``versions_of``)."""
    sets = found.groupBy("app_id", "container", "version").agg(F.sort_array(F.collect_set("field")).alias("fields"))
    before = F.lag("fields").over(W.partitionBy("app_id", "container").orderBy("version"))
    s = sets.withColumn("before", before)
    return s.select("app_id", "container", "version", F.size("fields").alias("n_fields"), F.array_join(F.array_except("fields", F.coalesce("before", F.array().cast("array<string>"))), ",").alias("added"), F.coalesce(F.array_join(F.array_except("before", "fields"), ","), F.lit("")).alias("removed"))
