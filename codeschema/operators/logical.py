"""Logical schema: entities, variations and features from the physical structure; rendering and comparison."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import digest_of, singular
from .access import Access

FEATURE = "entity string, root boolean, variation int, feature string, kind string, type string, lower int, upper string, target string"


def entity_of(container, field):
    """The non-root entity of an embedded field: the container and the field's singular, dotted."""
    return F.concat_ws(".", container, F.array_join(F.transform(F.split(field, "[.]"), singular), "."))


def to_logical(a: Access, keys: DataFrame | None = None, by_version: bool = True) -> DataFrame:
    """Features of every entity type (``FEATURE``).

    Containers are root entities; fields that hold objects are aggregates and entities of their own; references are
    attributes that a join condition identifies; keys are ``_id``, referenced fields and what ``keys``
    (entity, feature) declares.  Lower bounds are 0: code cannot show more.
    """
    f = a.fields().withColumn("parent", F.when(F.col("field").contains("."), F.expr("substring_index(field, '.', size(split(field, '[.]')) - 1)")).otherwise(F.lit("")))
    f = f.withColumn("entity", F.when(F.col("parent") == "", F.col("container")).otherwise(entity_of(F.col("container"), F.col("parent")))).withColumn("feature", F.expr("substring_index(field, '.', -1)"))
    refs = a.refs.groupBy("app_id", F.col("holder").alias("container"), "field").agg(F.min("referenced").alias("target"), F.max(F.when(F.col("upper_bound") == "many", 1).otherwise(0)).alias("many_ref"))
    ids = a.refs.select("app_id", F.col("referenced").alias("container"), F.col("referenced_field").alias("field"), F.lit(True).alias("is_key")).distinct()
    missing = a.refs.select("app_id", F.col("holder").alias("container"), "field").distinct().join(f.select("app_id", "container", "field"), ["app_id", "container", "field"], "left_anti")
    versions = f.select("app_id", "version", "container").distinct()
    added = missing.join(versions, ["app_id", "container"]).select("app_id", "version", "container", "field", F.lit("attribute").alias("type_kind"), F.lit("string").alias("prim_type"), F.lit("default").alias("evidence"), F.lit(0).cast("long").alias("n_sites"), F.lit("").alias("parent"), F.col("container").alias("entity"), F.col("field").alias("feature")).where("not field like '%.%'")
    f = f.unionByName(added).join(refs, ["app_id", "container", "field"], "left").join(ids, ["app_id", "container", "field"], "left")
    if keys is not None:
        f = f.join(keys.select("entity", "feature", F.lit(True).alias("declared")), ["entity", "feature"], "left").withColumn("is_key", F.coalesce("is_key", "declared"))
    kind = F.when(F.col("target").isNotNull(), "reference").when(F.coalesce("is_key", F.col("feature") == "_id", F.lit(False)) | (F.col("feature") == "_id"), "key").when(F.col("type_kind").isin("aggregate", "collection_of_aggregates"), "aggregate").otherwise("attribute")
    many = F.col("type_kind").isin("collection", "collection_of_aggregates") | (F.coalesce("many_ref", F.lit(0)) == 1)
    kind_type = F.when(F.col("type_kind") == "collection", F.concat(F.lit("array<"), F.col("prim_type"), F.lit(">"))).when(F.col("type_kind").isin("aggregate", "collection_of_aggregates"), F.lit("struct")).otherwise(F.col("prim_type"))
    target = F.when(F.col("target").isNotNull(), F.col("target")).when(F.col("type_kind").isin("aggregate", "collection_of_aggregates"), entity_of(F.col("container"), F.col("field")))
    out = f.select("app_id", "version", "entity", (F.col("parent") == "").alias("root"), "feature", kind.alias("kind"), kind_type.alias("type"), F.lit(0).alias("lower"), F.when(many, "many").otherwise("one").alias("upper"), target.alias("target"), "evidence")
    shape = out.groupBy("app_id", "version", "entity").agg(digest_of(F.concat_ws(":", "feature", "kind", "type", "upper")).alias("shape"))
    if not by_version:
        shape = shape.withColumn("shape", F.lit(""))
    first = shape.groupBy("app_id", "entity", "shape").agg(F.min("version").alias("since"))
    number = F.dense_rank().over(W.partitionBy("app_id", "entity").orderBy("since"))
    named = shape.join(first.withColumn("variation", number), ["app_id", "entity", "shape"])
    return out.join(named.select("app_id", "version", "entity", "variation"), ["app_id", "version", "entity"]).select("app_id", "entity", "root", "variation", "feature", "kind", "type", "lower", "upper", "target", "evidence").distinct()


def relationship_types(schema: DataFrame) -> DataFrame:
    """Entities that only link others: two references or more, nothing refers to them, and few attributes besides."""
    n = schema.groupBy("app_id", "entity").agg(F.sum((F.col("kind") == "reference").cast("int")).alias("n_refs"), F.count("*").alias("n"))
    used = schema.where("kind = 'reference'").select("app_id", F.col("target").alias("entity")).distinct()
    return n.where("n_refs >= 2").join(used, ["app_id", "entity"], "left_anti").select("app_id", "entity", F.lit("relationship").alias("kind"), "n_refs")


def declare_schema(spark: SparkSession, rows: list[tuple], app_id: str = "declared") -> DataFrame:
    """A schema that is given: (entity, feature, kind, type, upper, target) rows."""
    df = spark.createDataFrame(rows, "entity string, feature string, kind string, type string, upper string, target string")
    return df.select(F.lit(app_id).alias("app_id"), "entity", (~F.col("entity").contains(".")).alias("root"), F.lit(1).alias("variation"), "feature", "kind", "type", F.lit(0).alias("lower"), "upper", "target", F.lit("declared").alias("evidence"))


def schema_diff(a: DataFrame, b: DataFrame) -> DataFrame:
    """Features that were added, removed or changed from ``a`` to ``b``."""
    pick = lambda s, p: s.select("entity", "feature", F.concat_ws(" ", "kind", "type", "upper", "target").alias(p)).distinct()
    both = pick(a, "old").join(pick(b, "new"), ["entity", "feature"], "full")
    change = F.when(F.col("old").isNull(), "added").when(F.col("new").isNull(), "removed").when(F.col("old") != F.col("new"), "changed")
    return both.withColumn("change", change).where("change is not null").select("entity", "feature", "change", "old", "new")


def render(schema: DataFrame, fmt: str = "text") -> DataFrame:
    """A line an entity: ``text``, ``ddl`` (Spark types), ``json``, or edges of ``dot``."""
    s = schema.select("app_id", "entity", "variation", "feature", "kind", "type", "upper", "target")
    if fmt == "dot":
        return s.where("target is not null").select("app_id", F.format_string('  "%s" -> "%s" [label="%s"];', "entity", "target", "feature").alias("line")).distinct()
    if fmt == "json":
        item = F.struct("feature", "kind", "type", "upper", "target")
    elif fmt == "ddl":
        return _ddl(s)
    else:
        item = F.struct("feature", F.concat_ws(" ", F.col("kind"), F.col("type"), F.when(F.col("upper") == "many", "*"), F.concat(F.lit("-> "), "target")).alias("t"))
    lines = s.groupBy("app_id", "entity", "variation").agg(F.sort_array(F.collect_set(item)).alias("f"))
    if fmt == "json":
        body = F.to_json("f")
    else:
        body = F.array_join(F.transform("f", lambda x: F.concat(x["feature"], F.lit(": "), x["t"])), "; ")
    return lines.select("app_id", "entity", "variation", body.alias("line"))


def _ddl(s: DataFrame) -> DataFrame:
    """Spark types of each entity; embedded entities are structs, from the deepest level up."""
    plain = F.when(F.col("type") == "long", "bigint").otherwise(F.regexp_replace("type", "array<long>", "array<bigint>"))
    depth = F.size(F.split("entity", "[.]"))
    levels = s.agg(F.max(depth)).first()[0] or 0
    done = None
    for level in range(levels, 0, -1):
        here = s.where(depth == level)
        if done is None:
            here = here.withColumn("inner", F.lit(None).cast("string"))
        else:
            here = here.join(done.groupBy("app_id", F.col("entity").alias("target")).agg(F.max_by("line", "variation").alias("inner")), ["app_id", "target"], "left")
        kind = F.when(F.col("type") == "struct", F.concat(F.lit("struct<"), F.regexp_replace(F.coalesce("inner", F.lit("")), "(^|, )([^ ,<>]+) ", "$1$2: "), F.lit(">"))).otherwise(plain)
        kind = F.when((F.col("upper") == "many") & ~F.col("type").startswith("array"), F.concat(F.lit("array<"), kind, F.lit(">"))).otherwise(kind)
        line = here.groupBy("app_id", "entity", "variation").agg(F.array_join(F.sort_array(F.collect_set(F.concat_ws(" ", "feature", kind))), ", ").alias("line"))
        done = line if done is None else done.unionByName(line)
    return done if done is not None else s.select("app_id", "entity", "variation", F.lit("").alias("line"))


def schema_intersect(a: DataFrame, b: DataFrame) -> DataFrame:
    """Features that both schemas have alike."""
    pick = lambda s: s.select("entity", "feature", "kind", "type", "upper", "target")
    return pick(a).intersect(pick(b))


def schema_except(a: DataFrame, b: DataFrame) -> DataFrame:
    """Features of the first schema that the second one lacks or has otherwise."""
    pick = lambda s: s.select("entity", "feature", "kind", "type", "upper", "target")
    return pick(a).exceptAll(pick(b)).distinct()


def variations(schema: DataFrame) -> DataFrame:
    return schema.groupBy("app_id", "entity").agg(F.countDistinct("variation").alias("n_variations"))


def overloaded_entities(schema: DataFrame, threshold: float = 0.9) -> DataFrame:
    """Entities with more fields than most: candidates to be split."""
    n = schema.groupBy("app_id", "entity").agg(F.countDistinct("feature").alias("n_fields"))
    rank = F.percent_rank().over(W.partitionBy("app_id").orderBy("n_fields"))
    return n.withColumn("rank", F.round(rank, 6)).where(F.col("rank") >= threshold)


def versions_of(a: Access) -> DataFrame:
    """Fields of each version with their shapes and what they refer to, for evolution."""
    refs = a.refs.groupBy("app_id", "version", F.col("holder").alias("container"), "field").agg(F.min("referenced").alias("target"))
    f = a.fields().join(refs, ["app_id", "version", "container", "field"], "left")
    return f.select("app_id", "version", "container", "field", F.concat_ws(":", "type_kind", "prim_type").alias("shape"), "target")


def schema_evolution(found: DataFrame) -> DataFrame:
    """Fields added, removed, retyped or with another reference from each version to the next one of the program (input:
    ``versions_of``)."""
    if "target" not in found.columns:
        found = found.withColumn("target", F.lit(None).cast("string"))
    steps = found.select("app_id", "version").distinct().withColumn("next", F.lead("version").over(W.partitionBy("app_id").orderBy("version"))).where("next is not null")
    old = found.join(steps, ["app_id", "version"]).select("app_id", F.col("next").alias("version"), "container", "field", F.col("shape").alias("old"), F.col("target").alias("old_target"))
    new = found.join(steps.select("app_id", F.col("next").alias("version")), ["app_id", "version"]).select("app_id", "version", "container", "field", F.col("shape").alias("new"), F.col("target").alias("new_target"))
    both = old.join(new, ["app_id", "version", "container", "field"], "full")
    change = F.when(F.col("old").isNull(), "added").when(F.col("new").isNull(), "removed").when(F.col("old") != F.col("new"), "retyped").when(~F.col("old_target").eqNullSafe(F.col("new_target")), "reference changed")
    return both.withColumn("change", change).where("change is not null")
