"""Join removal: which fields of a referenced entity to duplicate in the host, and plans for it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import singular, steps_path
from ..plans import Options
from ..store import written
from .access import Access, reach
from .models import KEY


def _both_sides(a: Access, options: Options) -> tuple[DataFrame, DataFrame]:
    """Uses of the host's and of the referenced result, for each join: (key, prev_path, prev_op, next_op, use_path, elem, block, seq[, field])."""
    j = a.joins.select(*KEY, "prev_path", "prev_op", "next_op")
    r = a.reads
    if not options.aliases or not a.options.aliases:
        # The printed procedure follows assignments here even where the extraction doesn't.
        from .access import accesses

        r = accesses(a.m, a.ops, reach(a.m, a.ops))
    field = steps_path(F.col("steps"))
    use = r.where("role <> 'stage'").select(*KEY, "op", "use_path", "elem", "block", "seq", "role", field.alias("field"))
    host = j.join(use.withColumnRenamed("op", "prev_op").withColumnRenamed("path", "prev_path"), ["app_id", "version", "prev_path", "prev_op"])
    # What is handed to the function that holds the query is the reference itself, not a use together with the result.
    in_function = a.ops.join(a.m.units.where("kind = 'function'").select(*KEY, "unit"), [*KEY, "unit"]).select(*KEY, F.col("op").alias("next_op"), F.col("unit").alias("asked_in")).distinct()
    at = a.m.nodes.select("app_id", "version", F.col("path").alias("use_path"), "seq", F.col("unit").alias("used_in"))
    known = a.refs.select(*KEY, "prev_path", "prev_op", "next_op", "field", F.lit(True).alias("refers")).distinct()
    host = host.join(in_function, [*KEY, "next_op"], "left").join(at, ["app_id", "version", "use_path", "seq"], "left").join(known, [*KEY, "prev_path", "prev_op", "next_op", "field"], "left")
    handed = F.col("refers") & (F.col("role") == "arg") & ((F.col("use_path") != F.col("path")) | (F.col("asked_in") != F.col("used_in")))
    host = host.where(~F.coalesce(handed, F.lit(False)))
    ref = j.join(use.withColumnRenamed("op", "next_op"), [*KEY, "next_op"]).where("(use_path <> path or floor(next_op / 100) <= seq) and field <> ''")
    return host, ref


def duplication_fields(a: Access, options: Options | None = None) -> DataFrame:
    """(key, prev_path, prev_op, next_op, field, n_sites): fields of the join's result that are used together with the host's."""
    options = options or a.options
    host, ref = _both_sides(a, options)
    # Elements of a result that is passed to a function are used inside its block: their own statement is there,
    # so a use of the host counts for the blocks around it too.
    around = _blocks_above(a)
    on_join = [] if not options.reset_per_join else ["next_op"]
    if options.co_use == "any":
        hit = ref
    elif options.co_use == "statement":
        h = host.select(*KEY, *on_join, "use_path", "elem").distinct()
        hit = ref.join(h, [*KEY, *on_join, "use_path", "elem"], "left_semi")
    else:
        inside = around.withColumnRenamed("path", "use_path")
        at = ["app_id", "version", "use_path", "block"]
        h = host.where("use_path <> path or seq > floor(next_op / 100)").join(inside, at).select(*KEY, *on_join, "use_path", F.col("above").alias("block")).distinct()
        up = ref.join(inside, at).select(*KEY, "prev_path", "prev_op", "next_op", "field", "use_path", "seq", F.col("above").alias("block"))
        hit = up.join(h, [*KEY, *on_join, "use_path", "block"], "left_semi")
    return hit.groupBy(*KEY, "prev_path", "prev_op", "next_op", "field").agg(F.countDistinct("use_path", "seq").alias("n_sites"))


def _blocks_above(a: Access) -> DataFrame:
    """(key, block, above): each block, and those that enclose it inside the function of the join."""
    b = a.m.elements.where("kind = 'block'").select(*KEY, F.col("elem").alias("block"), "parent", "unit")
    e = a.m.elements.select(*KEY, F.col("elem").alias("parent"), F.col("block").alias("outer"))
    functions = a.m.units.where("kind = 'callback'").select(*KEY, "unit").distinct()
    own = written(b.join(functions, [*KEY, "unit"], "left_semi").join(e, [*KEY, "parent"]).select(*KEY, "block", F.col("outer").alias("above")), "blocks")
    out = step = b.select(*KEY, "block", F.col("block").alias("above"))
    while True:
        step = step.withColumnRenamed("above", "mid").join(own.select(*KEY, F.col("block").alias("mid"), "above"), [*KEY, "mid"]).where("mid <> above").select(*KEY, "block", "above")
        step = written(step.join(out.hint("merge"), [*KEY, "block", "above"], "left_anti").distinct(), "blocks")
        if step.isEmpty():
            return out.distinct()
        out = out.unionByName(step)


def removal_plans(a: Access, options: Options | None = None) -> DataFrame:
    """A plan for each join and referenced entity: hosts, fields, shape, names, code, and how often the data are used and updated.

    Holder, field and direction are those of one condition of the join, one on ``_id`` first; ``conditions`` lists all.
    ``new_query`` is what the host is asked after the removal; ``other_queries`` are the lines of all other operations on
    the two containers.  ``safe``: no field of the joined result is used anywhere else after the join.
    """
    options = options or a.options
    chosen = duplication_fields(a, options)
    every = duplication_fields(a, Options(**{**options.__dict__, "co_use": "any"})).groupBy(*KEY, "next_op").agg(F.sort_array(F.collect_set("field")).alias("all_fields"))
    pair = [*KEY, "prev_path", "prev_op", "next_op"]
    f = chosen.groupBy(*pair).agg(F.sort_array(F.collect_set("field")).alias("fields"), F.sum("n_sites").alias("n_use_sites"))
    first = F.struct((F.col("referenced_field") != "_id").alias("natural"), "holder", "field", "referenced_field", (F.col("upper_bound") == "many").alias("many"), "reverse")
    said = F.concat(F.col("holder"), F.lit("."), F.col("field"), F.lit(" = "), F.col("referenced"), F.lit("."), F.col("referenced_field"))
    r = a.refs.groupBy(*pair).agg(F.min(first).alias("c"), F.sort_array(F.collect_set(said)).alias("conditions"))
    r = r.select(*pair, "c.holder", F.col("c.field").alias("holder_field"), F.col("c.referenced_field").alias("key_field"), "c.many", "c.reverse", "conditions")
    op = a.ops.select(*KEY, "op", "text", "line", "as_field").distinct()
    j = a.joins.join(f, pair).join(r, pair, "left").join(every, [*KEY, "next_op"], "left")
    j = j.join(op.select("app_id", "version", F.col("path").alias("prev_path"), F.col("op").alias("prev_op"), F.col("text").alias("host_query"), F.col("line").alias("host_line")), ["app_id", "version", "prev_path", "prev_op"]).join(op.select(*KEY, F.col("op").alias("next_op"), F.col("text").alias("join_query"), F.col("line").alias("join_line"), "as_field"), [*KEY, "next_op"])
    where = F.concat(F.col("path"), F.lit(":"), F.format_string("%05d", "line"), F.lit(" "), F.col("kind"))
    counts = a.ops.where("not synthetic").groupBy("app_id", "version", F.col("container")).agg(F.count("*").alias("n_ops"), F.sum(F.col("kind").isin("U", "I", "D").cast("int")).alias("n_updates"), F.sort_array(F.collect_set(where)).alias("sites"))
    j = j.join(counts.select("app_id", "version", F.col("container").alias("referenced"), F.col("n_updates").alias("n_updates_referenced"), F.col("n_ops").alias("n_ops_referenced"), F.col("sites").alias("referenced_sites")), ["app_id", "version", "referenced"], "left")
    j = j.join(counts.select("app_id", "version", F.col("container").alias("host"), F.col("n_ops").alias("n_ops_host"), F.col("sites").alias("host_sites")), ["app_id", "version", "host"], "left")
    many, several = F.coalesce("many", F.lit(False)), F.size("fields") > 1
    shape = F.when(many & several, "array_of_struct").when(many, "array").when(several, "struct").otherwise("plain")
    entity = singular(F.col("referenced"))
    named = F.transform("fields", lambda x: F.concat(entity, F.lit("_"), F.translate(x, ".", "_")) if options.naming == "prefixed" else F.translate(x, ".", "_"))
    inside = F.when((F.col("holder") == F.col("host")) & F.col("holder_field").contains("."), F.regexp_extract("holder_field", r"^(.*)\.[^.]+$", 1))
    none = F.array().cast("array<string>")
    own = F.array(F.concat(F.col("prev_path"), F.lit(":"), F.format_string("%05d", "host_line"), F.lit(" R")), F.concat(F.col("path"), F.lit(":"), F.format_string("%05d", "join_line"), F.lit(" R")))
    # A pipeline loses the stage of its lookup (and the one that unwinds it); other host queries stay as they are.
    unwound = F.concat(F.lit(r"\s*\{\s*\$unwind\s*:\s*'\$"), F.coalesce("as_field", F.lit("")), F.lit(r"'\s*\}\s*,?"))
    stage = F.regexp_replace(F.regexp_replace("host_query", unwound, F.lit("")), F.concat(F.lit(r"\s*\{\s*\$lookup\s*:\s*\{[^{}]*from\s*:\s*'"), F.col("referenced"), F.lit(r"'[^{}]*\}\s*\}\s*,?")), F.lit(""))
    return j.select(
        *KEY, F.concat_ws(":", "path", "next_op").alias("plan_id"), "prev_path", "prev_op", "next_op", "host", "referenced", "holder", "holder_field", "key_field", F.coalesce("reverse", F.lit(False)).alias("reverse"), inside.alias("inside"), "conditions", "fields", named.alias("names"), shape.alias("shape"), "join_type",
        "host_query", F.when(F.col("join_type") == "pipeline", stage).otherwise(F.col("host_query")).alias("new_query"), "join_query", "host_line", "join_line", F.array_except(F.array_union(F.coalesce("host_sites", none), F.coalesce("referenced_sites", none)), own).alias("other_queries"),
        "n_use_sites", "n_ops_host", "n_ops_referenced", F.coalesce("n_updates_referenced", F.lit(0)).alias("n_updates_referenced"), (F.size(F.array_except(F.coalesce("all_fields", none), "fields")) == 0).alias("safe"),
    )


def select_plans(plans: DataFrame, where: str | None = None, ids: list[str] | None = None) -> DataFrame:
    out = plans.where(where) if where else plans
    return out.where(F.col("plan_id").isin(ids)) if ids is not None else out


def rank_plans(plans: DataFrame, read_weight: float = 1.0, update_weight: float = 1.0, workload: DataFrame | None = None) -> DataFrame:
    """Plans of each program by benefit minus the cost of keeping duplicates up to date.

    Without a ``workload`` the benefit is the number of places that use the join, the cost that of updates in the code; with one
    (container, kind, n: operations that were run) it is how often the host was read, the cost how often the referenced
    container was written.
    """
    benefit, cost = F.col("n_use_sites"), F.col("n_updates_referenced")
    if workload is not None:
        per = lambda kinds, name, n: workload.where(F.col("kind").isin(*kinds)).groupBy(F.col("container").alias(name)).agg(F.sum("n").alias(n))
        plans = plans.join(per(["R"], "host", "n_reads"), "host", "left").join(per(["I", "U", "D"], "referenced", "n_writes"), "referenced", "left")
        benefit, cost = F.coalesce("n_reads", F.lit(0)), F.coalesce("n_writes", F.lit(0))
    p = plans.withColumn("benefit", benefit * read_weight).withColumn("update_cost", cost * update_weight)
    order = W.partitionBy("app_id", "version").orderBy(F.desc(F.col("benefit") - F.col("update_cost")), "plan_id")
    return p.withColumn("rank", F.row_number().over(order))


def aggregate_candidates(a: Access) -> DataFrame:
    """Pairs of entities that code joins: candidates to be grouped into one aggregate."""
    return a.joins.groupBy("app_id", "host", "referenced").agg(F.count("*").alias("n_joins"))


def copy_operation(plans: DataFrame) -> DataFrame:
    """The copy each plan stands for, as a line of text."""
    where = F.when(F.col("reverse"), F.format_string("%s.%s contains %s._id", "holder", "holder_field", "host")).otherwise(F.format_string("%s.%s = %s.%s", "referenced", "key_field", "host", "holder_field"))
    to = F.when(F.col("inside").isNotNull(), F.concat_ws(".", "host", "inside")).otherwise(F.col("host"))
    return plans.select("plan_id", F.concat(F.lit("duplicate "), F.col("referenced"), F.lit("("), F.array_join("fields", ", "), F.lit(") as "), F.array_join("names", ", "), F.lit(" in "), to, F.lit(" where "), where).alias("operation"))


def apply_to_schema(schema: DataFrame, plans: DataFrame) -> DataFrame:
    """The logical schema with the duplicated features of the plans."""
    p = plans.select("app_id", F.coalesce(F.concat_ws(".", "host", F.array_join(F.transform(F.split("inside", "[.]"), singular), ".")), F.col("host")).alias("with_inside"), "host", "inside", "referenced", "shape", F.explode(F.arrays_zip("fields", "names")).alias("x"))
    p = p.select("app_id", F.when(F.col("inside").isNull(), F.col("host")).otherwise(F.col("with_inside")).alias("entity"), "referenced", "shape", F.col("x.fields").alias("source"), F.col("x.names").alias("feature"), F.col("inside").isNull().alias("root"))
    types = schema.groupBy(F.col("entity").alias("referenced"), F.col("feature").alias("source")).agg(F.min("type").alias("t"))
    added = p.join(types, ["referenced", "source"], "left").select("app_id", "entity", "root", F.lit(1).alias("variation"), "feature", F.lit("attribute").alias("kind"), F.coalesce("t", F.lit("string")).alias("type"), F.lit(0).alias("lower"), F.when(F.col("shape").startswith("array"), "many").otherwise("one").alias("upper"), F.concat_ws(".", "referenced", "source").alias("target"), F.lit("duplicated").alias("evidence"))
    return schema.unionByName(added.distinct())
