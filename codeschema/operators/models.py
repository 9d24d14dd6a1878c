"""The bundle of model tables of analysed programs, and the flow model."""

from __future__ import annotations

from functools import cached_property

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..frontend.inject import inject
from ..schema import STEPS
from ..store import written

KEY = ["app_id", "version", "path"]


class Models:
    """Tables of the code model; each is read from the stored model rows with only its own columns."""

    def __init__(self, files: DataFrame, model: DataFrame | None = None) -> None:
        self.files = files
        self.model = model if model is not None else written(inject(files), "model")

    def table(self, name: str) -> DataFrame:
        return self.model.select(*KEY, F.explode(name).alias("x")).select(*KEY, "x.*")

    @cached_property
    def nodes(self) -> DataFrame:
        return self.table("nodes")

    @cached_property
    def uses(self) -> DataFrame:
        return self.table("uses")

    @cached_property
    def aliases(self) -> DataFrame:
        return self.table("aliases")

    @cached_property
    def calls(self) -> DataFrame:
        return self.table("calls")

    @cached_property
    def args(self) -> DataFrame:
        return self.table("args")

    @cached_property
    def units(self) -> DataFrame:
        return self.table("units")

    @cached_property
    def elements(self) -> DataFrame:
        return self.table("elements")

    @cached_property
    def bindings(self) -> DataFrame:
        """Flows between functions, in one file or several: arguments to parameters, returned values to results.

        (app_id, version, path, lhs, at, root_path, root, steps, literal, mode, site): ``lhs`` of ``path`` holds what ``root`` of
        ``root_path`` held; mode 1 enters a function at the call ``site``, mode 2 leaves it.  A function of the caller's
        own file is meant before one of that name in another file.
        """
        program = ["app_id", "version"]
        f = self.units.where("kind = 'function' and name <> ''").select(*program, F.col("path").alias("in_path"), F.col("name").alias("callee"), "unit", "params")
        own = f.select(*program, F.col("in_path").alias("path"), "callee", F.lit(True).alias("own")).distinct()
        c = self.table("resolved").join(f, [*program, "callee"]).join(own, [*KEY, "callee"], "left").where("own is null or path = in_path")
        c = written(c.select(*KEY, "seq", "in_path", "unit", "params", F.concat_ws(":", "path", "seq").alias("site")), "called")
        given = c.join(self.args.where("key = '' and (root is not null or literal is not null)"), [*KEY, "seq"])
        given = given.withColumn("name", F.get("params", F.col("arg"))).where("name <> ''")
        into = given.select(*program, F.col("in_path").alias("path"), F.concat_ws("@", "name", "unit").alias("lhs"), F.col("seq").alias("at"), F.col("path").alias("root_path"), "root", "steps", F.when(F.col("literal_type") == "string", F.col("literal")).alias("literal"), F.lit(1).alias("mode"), "site")
        back = c.join(self.calls.where("result is not null").select(*KEY, "seq", "result", "result_seq"), [*KEY, "seq"])
        back = back.select(*KEY, F.col("result").alias("lhs"), F.coalesce("result_seq", "seq").alias("at"), F.col("in_path").alias("root_path"), F.concat_ws("@", F.lit("return"), "unit").alias("root"), F.expr(f"cast(array() as {STEPS})").alias("steps"), F.lit(None).cast("string").alias("literal"), F.lit(2).alias("mode"), "site")
        return written(into.unionByName(back), "bindings")

    def errors(self) -> DataFrame:
        return self.model.where("error is not null").select(*KEY, "error")


def containers(files: DataFrame) -> DataFrame:
    """Folders and files of each program, with their parents."""
    parts = F.split("path", "/")
    level = files.select("app_id", "version", F.posexplode(parts).alias("depth", "name"), parts.alias("parts"))
    full = lambda n: F.array_join(F.slice("parts", 1, n), "/")
    return level.select("app_id", "version", full(F.col("depth") + 1).alias("container"), F.when(F.col("depth") > 0, full(F.col("depth"))).alias("parent"), F.when(F.col("depth") + 1 == F.size("parts"), "file").otherwise("folder").alias("kind")).distinct()


def infer_local_types(m: Models) -> DataFrame:
    """Variables with a type from their initialiser or from comparisons with literals; otherwise unknown."""
    rank = F.when(F.col("t") == "null", 0).when(F.col("t") == "string", 1).when(F.col("t") == "boolean", 1).when(F.col("t") == "long", 2).otherwise(3)
    first = m.elements.where("kind = 'decl'").select(*KEY, F.regexp_extract("text", r"^(?:const|let|var)\s+([\w$]+)\s*=\s*(\d+\.\d+|\d+|'[^']*'|\"[^\"]*\"|true|false)\s*[;,]?\s*$", 1).alias("variable"), F.regexp_extract("text", r"=\s*(.*?)\s*;?\s*$", 1).alias("value")).where("variable <> ''")
    literal = F.when(F.col("value").rlike(r"^\d+$"), "long").when(F.col("value").rlike(r"^\d+\.\d+$"), "double").when(F.col("value").isin("true", "false"), "boolean").otherwise("string")
    compared = m.uses.where("literal_type is not null and size(steps) = 0").select(*KEY, F.substring_index("root", "@", 1).alias("variable"), F.col("literal_type").alias("t"), F.lit("comparison").alias("evidence"))
    found = first.select(*KEY, "variable", literal.alias("t"), F.lit("initialiser").alias("evidence")).unionByName(compared)
    return found.groupBy(*KEY, "variable").agg(F.max_by("t", rank).alias("type"), F.min("evidence").alias("evidence"))


def object_sketches(m: Models) -> DataFrame:
    """For each variable that properties are read of: its properties."""
    return m.uses.where("get(steps, 0).kind = 'prop'").groupBy(*KEY, "root").agg(F.sort_array(F.collect_set(F.get("steps", F.lit(0))["name"])).alias("properties"))


# -- flow model ------------------------------------------------------------------------------------
def flow_nodes(m: Models) -> DataFrame:
    """Nodes of statements, and a start and an end for each unit."""
    ends = m.units.select(*KEY, F.explode(F.array(F.lit("start"), F.lit("end"))).alias("kind"), "unit")
    ends = ends.select(*KEY, F.when(F.col("kind") == "start", -2 * F.col("unit") - 1).otherwise(-2 * F.col("unit") - 2).alias("seq"), "unit", "kind")
    return m.nodes.select(*KEY, "seq", "unit", "kind").unionByName(ends)


def flow_edges(m: Models, callbacks: str = "nested") -> DataFrame:
    """Edges (key, src, dst_path, dst, kind): ``next`` inside a unit, ``true``/``false`` into branches, ``back`` of loops, ``call``
    and ``return`` of functions in this file or another one, and of callbacks.

    ``callbacks``: ``nested`` takes a callback for what comes next after its call, ``skip`` leaves it apart, as it runs later.
    Within a unit a node goes to the next one that its branch does not exclude; a branch's last node goes to
    the first node behind the selection.
    """
    flip = F.transform("branch", lambda b: F.translate(b, "TF", "FT"))
    n = m.nodes.select(*KEY, "seq", "unit", "kind", "branch", "loops", flip.alias("not_in"))
    a, b = n.alias("a"), n.alias("b")
    same = [F.col(f"a.{k}") == F.col(f"b.{k}") for k in [*KEY, "unit"]]
    order = W.partitionBy(*KEY, "unit").orderBy("seq")
    first = F.lead("seq").over(order)
    plain = n.select("*", first.alias("after"), F.lead("not_in").over(order).alias("after_not"))
    # The next node in source order is also the next in the flow unless it lies in the other branch of a selection.
    inner = plain.where("after is not null and not arrays_overlap(branch, after_not)").select(*KEY, F.col("seq").alias("src"), F.col("after").alias("dst"), F.col("kind").alias("of"))
    jumps = plain.where("after is not null and arrays_overlap(branch, after_not)").select(*KEY, "unit", "seq", "branch", "not_in").alias("a")
    past = jumps.join(b, [*same, F.col("b.seq") > F.col("a.seq"), ~F.arrays_overlap(F.col("a.branch"), F.col("b.not_in"))])
    past = past.groupBy(*[F.col(f"a.{k}").alias(k) for k in KEY], F.col("a.seq").alias("src")).agg(F.min("b.seq").alias("dst")).withColumn("of", F.lit("jump"))
    selected = n.where("kind = 'selection'").alias("a")
    branch = selected.join(b, [*same, F.col("b.seq") > F.col("a.seq"), F.size("b.branch") > F.size("a.branch")])
    label = F.try_element_at("b.branch", (F.size("a.branch") + 1).cast("int"))
    into = branch.where(F.slice("b.branch", 1, F.size("a.branch")) == F.col("a.branch"))
    own = m.nodes.where("kind = 'selection'").select(*KEY, "seq", "elem")
    into = into.select(*[F.col(f"a.{k}").alias(k) for k in KEY], F.col("a.seq").alias("src"), F.col("b.seq").alias("dst"), label.alias("label")).join(own.withColumnRenamed("seq", "src"), [*KEY, "src"]).where(F.substring_index("label", ":", 1) == F.col("elem").cast("string"))
    into = into.groupBy(*KEY, "src", F.substring_index("label", ":", -1).alias("side")).agg(F.min("dst").alias("dst")).select(*KEY, "src", "dst", F.when(F.col("side") == "T", "true").otherwise("false").alias("kind"))
    steps = inner.unionByName(past)
    steps = steps.join(into.select(*KEY, "src", "dst", F.col("kind").alias("side")), [*KEY, "src", "dst"], "left").select(*KEY, "src", "dst", F.coalesce("side", F.lit("next")).alias("kind"))
    other = into.join(steps, [*KEY, "src", "dst"], "left_anti")
    looped = m.nodes.select(*KEY, "seq", F.explode("loops").alias("loop")).groupBy(*KEY, "loop").agg(F.max("seq").alias("src"))
    heads = m.nodes.where("kind = 'loop'").select(*KEY, F.col("elem").alias("loop"), F.col("seq").alias("dst"))
    back = looped.join(heads, [*KEY, "loop"]).select(*KEY, "src", "dst", F.lit("back").alias("kind"))
    spans = m.nodes.groupBy(*KEY, "unit").agg(F.min("seq").alias("low"), F.max("seq").alias("high"))
    starts = spans.select(*KEY, (-2 * F.col("unit") - 1).alias("src"), F.col("low").alias("dst"), F.lit("next").alias("kind"))
    ends = spans.select(*KEY, F.col("high").alias("src"), (-2 * F.col("unit") - 2).alias("dst"), F.lit("next").alias("kind"))
    nested = m.units.where("call_seq is not null" if callbacks == "nested" else "false").select(*KEY, F.col("call_seq").alias("src"), F.col("path").alias("dst_path"), (-2 * F.col("unit") - 1).alias("dst"), F.lit("call").alias("kind"))
    units = m.units.where("kind = 'function'").select("app_id", "version", F.col("path").alias("dst_path"), F.col("name").alias("callee"), "unit")
    own = units.select("app_id", "version", F.col("dst_path").alias("path"), "callee", F.lit(True).alias("own")).distinct()
    named = m.table("resolved").join(units, ["app_id", "version", "callee"]).join(own, [*KEY, "callee"], "left").where("own is null or path = dst_path")
    calls = nested.unionByName(named.select(*KEY, F.col("seq").alias("src"), "dst_path", (-2 * F.col("unit") - 1).alias("dst"), F.lit("call").alias("kind")))
    returns = calls.select("app_id", "version", F.col("dst_path").alias("path"), (F.col("dst") - 1).alias("src"), F.col("path").alias("dst_path"), F.col("src").alias("dst"), F.lit("return").alias("kind"))
    inside = steps.unionByName(other.select(*KEY, "src", "dst", "kind")).unionByName(back).unionByName(starts).unionByName(ends)
    return inside.select(*KEY, "src", F.col("path").alias("dst_path"), "dst", "kind").unionByName(calls).unionByName(returns)


def cross_file_calls(m: Models) -> DataFrame:
    """Calls of functions that another file of the program declares."""
    units = m.units.where("kind = 'function'").select("app_id", "version", F.col("path").alias("in_path"), F.col("name").alias("callee"))
    return m.table("resolved").join(units, ["app_id", "version", "callee"]).where("path <> in_path").select(*KEY, "seq", "callee", "in_path")


def unresolved_calls(m: Models) -> DataFrame:
    """Calls by name of functions that no file of the program declares: known at run time only."""
    known = m.units.where("kind = 'function'").select("app_id", "version", F.col("name").alias("callee"))
    return m.table("resolved").join(known, ["app_id", "version", "callee"], "left_anti").select(*KEY, "seq", "callee")


def basic_blocks(m: Models) -> DataFrame:
    """Nodes with the number of their basic block in the unit: a block begins at a selection's or loop's target."""
    order = W.partitionBy(*KEY, "unit").orderBy("seq")
    turn = (F.lag("branch").over(order) != F.col("branch")) | (F.lag("loops").over(order) != F.col("loops")) | F.lag("kind").over(order).isin("selection", "loop")
    leader = F.coalesce(turn, F.lit(True)).cast("int")
    return m.nodes.withColumn("leader", leader).select(*KEY, "unit", "seq", "kind", F.sum("leader").over(order.rowsBetween(W.unboundedPreceding, 0)).alias("basic_block"))


def reachable(edges: DataFrame, start: DataFrame) -> DataFrame:
    """(key, src, dst_path, dst, dist): what each start node reaches, in other files too; level by level, each node once,
    until nothing is new."""
    if "dst_path" not in edges.columns:
        edges = edges.withColumn("dst_path", F.col("path"))
    step = written(edges.select("app_id", "version", F.col("path").alias("at_path"), F.col("src").alias("at"), F.col("dst_path").alias("to_path"), F.col("dst").alias("to")).distinct(), "edges")
    seen = written(start.select(*KEY, F.col("seq").alias("src"), F.col("path").alias("dst_path"), F.col("seq").alias("dst"), F.lit(0).alias("dist")), "reach")
    fresh, hop = seen, 0
    while True:
        hop += 1
        at = fresh.select(*KEY, "src", F.col("dst_path").alias("at_path"), F.col("dst").alias("at"))
        found = at.join(step, ["app_id", "version", "at_path", "at"]).select(*KEY, "src", F.col("to_path").alias("dst_path"), F.col("to").alias("dst")).distinct()
        fresh = written(found.join(seen.hint("merge"), [*KEY, "src", "dst_path", "dst"], "left_anti").select("*", F.lit(hop).alias("dist")), "reach")
        if fresh.isEmpty():
            return seen
        seen = seen.unionByName(fresh)
        if hop % 16 == 0:  # few parts, however long the walk
            seen = written(seen, "reach")


def export_graph(m: Models, fmt: str = "rows") -> DataFrame:
    """Edges for drawing, as rows or as lines of DOT."""
    edges = flow_edges(m).select(*KEY, "src", "dst_path", "dst", "kind")
    if fmt == "rows":
        return edges
    return edges.select(*KEY, F.format_string('  "%s:%d" -> "%s:%d" [label="%s"];', "path", "src", "dst_path", "dst", "kind").alias("line"))
