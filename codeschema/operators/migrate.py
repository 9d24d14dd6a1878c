"""Duplicating fields in stored documents, checks of it, and keeping duplicates up to date."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .rewrite import duplicate_name

BROADCAST_ROWS, BROADCAST_BYTES = 100_000, 64 << 20  # a referenced side of at most so many rows and bytes may be sent to all executors


@dataclass(frozen=True)
class Duplication:
    """What to copy: ``fields`` of ``referenced`` into ``host`` under ``name``; ``key``: what the reference is compared with.

    The reference is ``path`` of the host (an id, an array of ids, or an id inside an array of objects: ``array.key``), or, if
    ``reverse``, the field ``path`` of the referenced collection holds ids of hosts.
    """

    host: str
    referenced: str
    path: str
    fields: tuple[str, ...]
    name: str
    many: bool = False
    reverse: bool = False
    inside: str | None = None
    key: str = "_id"


def duplication_of(plan) -> Duplication:
    """The copy that a removal plan (a row of ``removal_plans``) stands for."""
    return Duplication(plan["host"], plan["referenced"], plan["holder_field"], tuple(plan["fields"]), duplicate_name(plan["names"]), many=plan["shape"].startswith("array"), reverse=plan["reverse"], inside=plan["inside"], key=plan["key_field"])


def _value(d: Duplication) -> Column:
    """What is copied of one referenced object: a field, or an object of several."""
    return F.col(d.fields[0]) if len(d.fields) == 1 else F.struct(*d.fields)


def _free(stem: str, *frames: DataFrame) -> str:
    """A column name that no frame has, in any case."""
    have, name = {c.lower() for f in frames for c in f.columns}, f"__{stem}"
    while name.lower() in have:
        name += "_"
    return name


def fits_broadcast(df: DataFrame, most_rows: int = BROADCAST_ROWS, most_bytes: int = BROADCAST_BYTES) -> bool:
    """Whether a frame is counted and measured to be small; no more than ``most_rows`` + 1 rows are looked at."""
    seen = df.limit(most_rows + 1).select(F.length(F.to_json(F.struct(*[F.col(f"`{c}`") for c in df.columns]))).alias("n")).agg(F.count("*").alias("rows"), F.sum("n").alias("bytes")).first()
    return seen["rows"] <= most_rows and (seen["bytes"] or 0) <= most_bytes


def apply_to_data(host: DataFrame, referenced: DataFrame, d: Duplication, strategy: str = "auto") -> DataFrame:
    """``host`` with the duplicate: NULL (or left out of arrays) where a reference leads nowhere.

    auto and broadcast: a referenced side that is measured to be small is broadcast; otherwise, and for shuffle, both sides are
    shuffled by the reference.  Arrays are exploded with their places and put together again in order; empty and NULL
    arrays stay as they are.  A key that several referenced objects have stands for the least of them, so hosts never multiply.
    """
    ref, value, at, own, all_ = (_free(x, host, referenced) for x in ("ref", "value", "at", "own", "all"))
    is_array = lambda df, path: dict(df.dtypes).get(path, "").startswith("array")
    kind = referenced.select(_value(d).alias("v")).schema[0].dataType.simpleString()
    empty = F.array().cast(f"array<{kind}>")
    if d.reverse or d.many and not d.inside and not is_array(host, d.path):
        # One object stands for many: the holders are folded by what they hold.
        held_by = F.col(d.path) if d.reverse else F.col(d.key)
        held = referenced.select(F.explode(held_by).alias(own) if d.reverse and is_array(referenced, d.path) else held_by.alias(own), F.col("_id").alias(ref), _value(d).alias(value))
        folded = held.where(F.col(own).isNotNull()).groupBy(own).agg(F.sort_array(F.collect_list(F.struct(ref, value))).alias(all_))
        values = F.transform(all_, lambda x: x[value])
        return host.join(folded, host["_id" if d.reverse else d.path] == F.col(own), "left").withColumn(d.name, F.coalesce(values, empty) if d.many else F.try_element_at(values, F.lit(1))).drop(own, all_)
    r = referenced.select(F.col(d.key).alias(ref), _value(d).alias(value)).where(F.col(ref).isNotNull()).groupBy(ref).agg(F.min(value).alias(value))
    if strategy in ("broadcast", "map", "auto") and fits_broadcast(r):
        r = F.broadcast(r)
    if d.inside:
        return _inside(host, r, d, (ref, value, at, own, all_))
    if not d.many:
        return host.join(r, host[d.path] == F.col(ref), "left").withColumn(d.name, F.col(value)).drop(ref, value)
    ids = host.select(F.col("_id").alias(own), F.posexplode(d.path).alias(at, ref))
    found = ids.join(r, ref).groupBy(own).agg(F.sort_array(F.collect_list(F.struct(at, value))).alias(all_))
    values = F.transform(all_, lambda x: x[value])
    return host.join(found, host["_id"] == F.col(own), "left").withColumn(d.name, F.coalesce(values, F.when(F.col(d.path).isNotNull(), empty))).drop(own, all_)


def _inside(host: DataFrame, r: DataFrame, d: Duplication, names: tuple[str, ...]) -> DataFrame:
    """The duplicate goes into each object of the array ``inside``, or into the single object there, beside its reference."""
    ref, value, at, own, all_ = names
    key = d.path.rpartition(".")[2]
    if not dict(host.dtypes)[d.inside.partition(".")[0]].startswith("array"):
        top, _, below = f"{d.inside}.{d.name}".partition(".")
        return host.join(r, F.col(d.path) == F.col(ref), "left").withColumn(top, F.when(F.col(top).isNotNull(), F.col(top).withField(below, F.col(value)))).drop(ref, value)
    item = _free("item", host)
    items = host.select(F.col("_id").alias(own), F.posexplode(d.inside).alias(at, item))
    joined = items.join(r, F.col(f"{item}.{key}") == F.col(ref), "left")
    put = F.col(item).withField(d.name, F.col(value))
    back = joined.groupBy(own).agg(F.sort_array(F.collect_list(F.struct(at, put.alias(item)))).alias(all_))
    new = F.transform(all_, lambda x: x[item])
    kind = joined.select(put.alias("x")).schema[0].dataType.simpleString()
    out = host.join(back, host["_id"] == F.col(own), "left")
    return out.withColumn(d.inside, F.coalesce(new, F.when(F.col(d.inside).isNotNull(), F.array().cast(f"array<{kind}>")))).drop(own, all_)


def verify_duplication(after: DataFrame, referenced: DataFrame, d: Duplication) -> DataFrame:
    """Hosts whose duplicate differs from what the reference gives now: none after a correct update."""
    again = apply_to_data(after.drop(d.name) if not d.inside else after, referenced, d, "shuffle")
    column = d.inside or d.name
    return after.select("_id", F.to_json(F.struct(column)).alias("has")).join(again.select("_id", F.to_json(F.struct(column)).alias("due")), "_id", "full").where("not has <=> due")


def run_original(host: DataFrame, referenced: DataFrame, d: Duplication) -> DataFrame:
    """The join query as it was: (_id, place or id, fields)."""
    names = [F.col(f).alias(f"ref_{f}") for f in d.fields]
    if d.reverse:
        held = referenced.select(F.explode(d.path).alias("__host"), F.col("_id").alias("ref_id"), *names)
        return host.select("_id").join(held, host["_id"] == F.col("__host")).select("_id", *[f"ref_{f}" for f in d.fields])
    r = referenced.select(F.col(d.key).alias("__ref"), *names)
    if d.many:
        return host.select("_id", F.explode(d.path).alias("__ref")).join(r, "__ref").select("_id", *[f"ref_{f}" for f in d.fields])
    return host.select("_id", F.col(d.path).alias("__ref")).join(r, "__ref").select("_id", *[f"ref_{f}" for f in d.fields])


def run_refactored(updated: DataFrame, d: Duplication) -> DataFrame:
    """The same result from the updated host alone."""
    if not d.many:
        v = F.col(d.name)
        rows = updated.where(v.isNotNull()).select("_id", v.alias("v"))
    else:
        rows = updated.select("_id", F.explode(d.name).alias("v"))
    return rows.select("_id", *([F.col("v").alias(f"ref_{d.fields[0]}")] if len(d.fields) == 1 else [F.col(f"v.{f}").alias(f"ref_{f}") for f in d.fields]))


def check_equivalence(host: DataFrame, referenced: DataFrame, updated: DataFrame, d: Duplication) -> DataFrame:
    """Rows that only one of the two forms gives: none if the refactoring keeps the query's meaning."""
    a, b = run_original(host, referenced, d), run_refactored(updated, d)
    return a.exceptAll(b).withColumn("only_in", F.lit("original")).unionByName(b.exceptAll(a).withColumn("only_in", F.lit("refactored")))


def sync_duplicates(updated: DataFrame, changes: DataFrame, d: Duplication, referenced: DataFrame | None = None) -> DataFrame:
    """Hosts after a batch of changed referenced objects (``_id``, the reference and the fields, as they are now).

    A plain duplicate takes the change itself.  Arrays, duplicates inside embedded objects and reverse ones are made anew from
    ``referenced`` (its state after the batch), for the hosts that a change concerns and no others.
    """
    if not (d.many or d.inside or d.reverse):
        ref, value, changed = (_free(x, updated, changes) for x in ("ref", "value", "changed"))
        c = changes.select(F.col(d.key).alias(ref), _value(d).alias(value)).groupBy(ref).agg(F.min(value).alias(value)).withColumn(changed, F.lit(True))
        out = updated.join(c, updated[d.path] == F.col(ref), "left")
        return out.withColumn(d.name, F.when(F.coalesce(changed, F.lit(False)), F.col(value)).otherwise(F.col(d.name))).drop(ref, value, changed)
    if referenced is None:
        raise ValueError("duplicates of this shape are made anew: the referenced collection is needed")
    is_array = lambda df, path: dict(df.dtypes).get(path, "").startswith("array")
    if d.reverse:
        concerned = changes.select((F.explode(d.path) if is_array(changes, d.path) else F.col(d.path)).alias("_id"))
    else:
        holds = F.col(d.path)  # of an array of objects: the array of their references
        refs = updated.select("_id", (F.explode(holds) if d.inside and is_array(updated, d.inside) or is_array(updated, d.path) else holds).alias("ref"))
        concerned = refs.join(changes.select(F.col(d.key).alias("ref")), "ref", "left_semi").select("_id")
    concerned = concerned.where("_id is not null").distinct()
    stale = updated.join(concerned, "_id", "left_semi")
    bare = stale if d.inside else stale.drop(d.name)
    fresh = apply_to_data(bare, referenced, d, "shuffle")
    return updated.join(concerned, "_id", "left_anti").select(*updated.columns).unionByName(fresh.select(*updated.columns))


def sync_operations(plans: DataFrame) -> DataFrame:
    """plan_id, operation: the update that the application has to run when a referenced object (``row``) has changed."""
    name = F.when(F.size("names") == 1, F.get("names", F.lit(0))).otherwise(F.concat(F.substring_index(F.get("names", F.lit(0)), "_", 1), F.lit("_info")))
    value = F.when(F.size("fields") == 1, F.concat(F.lit("row."), F.get("fields", F.lit(0)))).otherwise(F.concat(F.lit("{ "), F.array_join(F.transform("fields", lambda f: F.concat(f, F.lit(": row."), f)), ", "), F.lit(" }")))
    which = F.when(F.col("reverse"), F.concat(F.lit("{ _id: { $in: row."), F.col("holder_field"), F.lit(" } }"))).otherwise(F.concat(F.lit("{ '"), F.col("holder_field"), F.lit("': row."), F.col("key_field"), F.lit(" }")))
    put = F.concat(F.lit("{ $set: { '"), F.concat_ws(".", "inside", name), F.lit("': "), value, F.lit(" } }"))
    each = F.concat(F.lit("for (const host of await db.collection('"), F.col("host"), F.lit("').find("), which, F.lit(").toArray()) { await duplicate"), F.initcap("referenced"), F.lit("(db, host); }"))
    plain = F.concat(F.lit("await db.collection('"), F.col("host"), F.lit("').updateMany("), which, F.lit(", "), put, F.lit(");"))
    return plans.select("plan_id", F.when(F.col("shape").startswith("array"), each).otherwise(plain).alias("operation"))
