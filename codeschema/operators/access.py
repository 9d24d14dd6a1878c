"""Access model: operations on the store, their dependencies, and the structure of the data they touch."""

from __future__ import annotations

import re
import uuid
from collections import defaultdict, deque
from collections.abc import Iterator
from functools import reduce
from itertools import count

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from ..functions import digest_of, steps_path
from ..plans import Options
from ..schema import API, STEPS
from ..store import written
from .models import KEY, Models

# The calls of the store's interface (call, kind, filter argument, payload argument, many results, scalar result).
DEFAULT_API = [
    ("findOne", "R", 0, None, False, False), ("find", "R", 0, None, True, False), ("aggregate", "R", None, None, True, False),
    ("countDocuments", "R", 0, None, False, True), ("distinct", "R", 1, None, True, True),
    ("insertOne", "I", None, 0, False, False), ("insertMany", "I", None, 0, True, False),
    ("updateOne", "U", 0, 1, False, False), ("updateMany", "U", 0, 1, True, False), ("replaceOne", "U", 0, 1, False, False), ("findOneAndUpdate", "U", 0, 1, False, False),
    ("deleteOne", "D", 0, None, False, False), ("deleteMany", "D", 0, None, True, False), ("findOneAndDelete", "D", 0, None, False, False),
]
_PATH = "transform(filter(split(key, '[.]'), p -> not p like '$%' and not p rlike '^[0-9]+$'), p -> p)"


def api_table(spark: SparkSession, api: list | None = None) -> DataFrame:
    return spark.createDataFrame(api or DEFAULT_API, API)


def find_operations(m: Models, api: list | None = None, needs_container: bool = True) -> DataFrame:
    """Calls whose name is in the dictionary, a broadcast table of fixed size; containers that callers name are bound."""
    names = [a[0] for a in api or DEFAULT_API]
    mine = F.filter("calls", lambda c: c["name"].isin(*names) & (c["container"].isNotNull() if needs_container else F.lit(True)))
    # A node's number is its place, so an operation finds its node without a join.
    at = F.transform(mine, lambda c: F.struct(c.alias("c"), F.get("nodes", c["seq"]).alias("n")))
    calls = m.model.select(*KEY, F.explode(at).alias("x")).select(*KEY, "x.c.*", F.col("x.n.elem").alias("elem"), F.col("x.n.block").alias("block"), F.col("x.n.branch").alias("branch"), F.col("x.n.loops").alias("loops"), F.col("x.n.line").alias("line"))
    found = calls.join(F.broadcast(api_table(m.files.sparkSession, api)), calls["name"] == F.col("call"))
    named = bind_containers(m)
    if named is not None:
        found = found.join(named, [*KEY, "seq"], "left").withColumn("container", F.coalesce("named", "container"))
    return found.select(*KEY, (F.col("seq") * 100).cast("long").alias("op"), "seq", "kind", "call", "container", "filter_arg", "payload_arg", (F.col("multi") & ~F.col("scalar")).alias("multi"), "scalar", F.col("result").alias("result_var"), "result_seq", "element", "callback", "unit", "elem", "block", "branch", "loops", "line", "text", F.lit(None).cast("string").alias("as_field"), F.lit(False).alias("synthetic"))


def bind_containers(m: Models) -> DataFrame | None:
    """(key, seq, named): names that callers, in this file or another, give as an argument for an operation's container.

    One row for each name; None where every container is named in place.
    """
    open_ = m.model.select(*KEY, F.explode(F.filter("calls", lambda c: c["container_var"].isNotNull())).alias("c")).select(*KEY, F.col("c.seq").alias("seq"), F.col("c.container_var").alias("var"))
    fresh = written(open_.select(*KEY, "seq", F.col("path").alias("at_path"), "var"), "unnamed")
    if fresh.isEmpty():
        return None
    local = m.aliases.where("root is not null and size(steps) = 0").select("app_id", "version", F.col("path").alias("at_path"), F.col("lhs").alias("var"), F.col("path").alias("root_path"), "root", F.lit(None).cast("string").alias("literal"))
    given = written(local.unionByName(m.bindings.where("mode = 1 and size(steps) = 0").select("app_id", "version", F.col("path").alias("at_path"), F.col("lhs").alias("var"), "root_path", "root", "literal")), "given")
    seen, found = fresh, None
    while True:
        step = fresh.join(given, ["app_id", "version", "at_path", "var"])
        hit = step.where("literal is not null").select(*KEY, "seq", F.col("literal").alias("named"))
        found = hit if found is None else found.unionByName(hit)
        step = step.where("root is not null").select(*KEY, "seq", F.col("root_path").alias("at_path"), F.col("root").alias("var")).distinct()
        fresh = written(step.join(seen.hint("merge"), step.columns, "left_anti"), "unnamed")
        if fresh.isEmpty():
            return written(found.distinct(), "named")
        seen = seen.unionByName(fresh)


def expand_pipelines(m: Models, ops: DataFrame) -> DataFrame:
    """A synthetic read for each lookup stage of an aggregation, with its fields."""
    base = ops.where("call = 'aggregate'").select(*KEY, "op", "seq", "container")
    stage = m.args.where("arg = 0 and literal is not null").select(*KEY, "seq", F.regexp_extract("key", r"^(\d+)\.\$lookup\.(\w+)$", 1).alias("stage"), F.regexp_extract("key", r"^(\d+)\.\$lookup\.(\w+)$", 2).alias("what"), "literal").where("stage <> ''")
    one = stage.groupBy(*KEY, "seq", F.col("stage").cast("int").alias("stage")).agg(*[F.max(F.when(F.col("what") == w, F.col("literal"))).alias(w) for w in ("from", "localField", "foreignField", "as")])
    return one.join(base, [*KEY, "seq"]).select(*KEY, "seq", (F.col("op") + 1 + F.col("stage")).alias("op"), F.col("op").alias("base_op"), "container", F.col("from").alias("referenced"), "localField", "foreignField", F.col("as").alias("as_field"))


def all_operations(m: Models, api: list | None = None) -> DataFrame:
    """Operations with the synthetic reads of pipelines."""
    ops = find_operations(m, api)
    extra = expand_pipelines(m, ops).alias("l").join(ops.alias("o"), [F.col(f"l.{k}") == F.col(f"o.{k}") for k in KEY] + [F.col("l.base_op") == F.col("o.op")])
    put = {"op": F.col("l.op"), "container": F.col("l.referenced"), "as_field": F.col("l.as_field"), "synthetic": F.lit(True), "call": F.lit("lookup"), "filter_arg": F.lit(None).cast("int"), "multi": F.lit(True)}
    return ops.unionByName(extra.select(*[put.get(c, F.col(f"o.{c}")).alias(c) for c in ops.columns]))


# -- backward pass -------------------------------------------------------------------------------
# One walk, three ways to run it.  It goes from the arguments of an operation to what gave them their values:
# assignments and results before it (a place after it counts in a common loop) that do not lie in the other branch of
# a selection, arguments of the calls that enter a function (mode 1), and the end of functions whose result is used
# (mode 2).  A function that was entered from one call is left to that call only.  With ``kill`` only the last
# assignment counts, and those after it, where it is made on every way to the operation.
END = 2**31 - 1  # the place after all nodes of a file
_WALK = "app_id string, version int, path string, prev_seq int, next_seq int, via_var string, hops int, prev_container string, next_container string, prev_var string, next_var string, prev_kind string, next_kind string, open_var string, bound int, sites array<string>"


def _flip(x: str) -> str:
    return x[:-1] + ("F" if x[-1] == "T" else "T")


def _kernel(options: Options, api: list) -> object:
    """Map-only walk inside each file; ways that lead to other files are given as open ends."""
    kinds = {a[0]: a for a in api}

    def links(row: dict[str, list]) -> Iterator[dict]:
        calls = list(zip(*(row[f"calls_{c}"] for c in _READ["calls"]), strict=True))
        ops = [c for c in calls if c[2] is not None and c[1] in kinds]
        if not ops:
            return
        # A node's number is its place.
        branch, loops = row["nodes_branch"], row["nodes_loops"]
        functions = defaultdict(list)
        for unit, kind, name, params in zip(*(row[f"units_{c}"] for c in _READ["units"]), strict=True):
            if kind == "function" and name:
                functions[name].append((unit, params))
        callee = dict(zip(row["resolved_seq"], row["resolved_callee"], strict=True))
        # What may give a variable its value: (place, place from which it holds, mode, variable or operation).
        sources, outside = defaultdict(list), {f"{p}@{unit}" for us in functions.values() for unit, params in us for p in params if p}
        by_seq = {}
        for c in calls:
            seq, name, container, _, result, result_seq = c
            by_seq[seq] = c
            if not result:
                continue
            held = seq if result_seq is None else int(result_seq)
            if container is not None and name in kinds and not kinds[name][5]:
                sources[result].append((seq, held, 3, seq))
            if seq in callee:
                found = functions.get(callee[seq])
                for unit, _ in found or ():
                    sources[result].append((held, held, 2, (f"return@{unit}", seq)))
                if not found:
                    outside.add(result)
        for seq, lhs, root in zip(row["aliases_seq"], row["aliases_lhs"], row["aliases_root"], strict=True):
            sources[lhs].append((seq, seq, 0, root))
        roots = defaultdict(set)
        for seq, root, role in zip(row["uses_seq"], row["uses_root"], row["uses_role"], strict=True):
            if role == "arg":
                roots[seq].add(root)
        for seq, arg, key, root in zip(*(row[f"args_{c}"] for c in _READ["args"]), strict=True):
            if root:
                roots[seq].add(root)
                if key == "" and seq in callee:
                    for unit, params in functions.get(callee[seq], ()):
                        if arg < len(params) and params[arg]:
                            sources[f"{params[arg]}@{unit}"].append((seq, seq, 1, root))

        def counts(q: int, bound: int, op: int) -> bool:
            if options.walk == "linear":
                return q < bound
            if any(_flip(x) in branch[op] for x in branch[q]):
                return False
            return q < bound or q != op and not set(loops[q]).isdisjoint(loops[op])

        for c in ops:
            op, hits, open_ = c[0], {}, {}
            seen: dict[tuple, int] = {}
            todo = deque((v, op, 0, ()) for v in sorted(roots[op]))
            while todo:
                v, bound, hops, sites = todo.popleft()
                if seen.get((v, sites), -1) >= bound:
                    continue
                seen[v, sites] = bound
                if v in outside:
                    open_.setdefault((v, sites), (bound, hops))
                    open_[v, sites] = (max(bound, open_[v, sites][0]), open_[v, sites][1])
                given = [x for x in sources[v] if x[2] == 1 or counts(x[0], bound, op)]
                if options.kill and not v.startswith("return@"):
                    sure = [x[1] for x in given if x[2] != 1 and x[1] < bound and set(branch[x[1]]) <= set(branch[op])]
                    last = max(sure, default=-1)
                    given = [x for x in given if x[2] == 1 or x[1] >= last]
                for q, _, mode, what in given:
                    if mode == 3:
                        if what != op and (what not in hits or hits[what] > (hops, v)):
                            hits[what] = (hops, v)
                    elif mode == 0:
                        if what:
                            todo.append((what, q, hops + 1, sites))
                    elif mode == 1:
                        if not sites or sites[0] == q:
                            todo.append((what, q, hops + 1, sites[1:]))
                    elif what[1] not in sites:
                        todo.append((what[0], END, hops + 1, (what[1], *sites)))
            own = {"app_id": row["app_id"], "version": row["version"], "path": row["path"], "next_seq": op, "next_container": c[2], "next_var": c[3], "next_kind": kinds[c[1]][1]}
            for q, (hops, v) in sorted(hits.items()):
                yield {**own, "prev_seq": q, "via_var": v, "hops": hops, "prev_container": by_seq[q][2], "prev_var": by_seq[q][3], "prev_kind": kinds[by_seq[q][1]][1]}
            for (v, sites), (bound, hops) in sorted(open_.items()):
                yield {**own, "open_var": v, "bound": bound, "hops": hops, "sites": [f"{row['path']}:{x}" for x in sites]}

    schema = to_arrow_schema(StructType.fromDDL(_WALK))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            weights, at = np.diff(batch.column("nodes_branch").offsets.to_numpy()), 0
            ends = np.cumsum(weights)
            while at < batch.num_rows:  # few models are Python objects at once
                stop = max(at + 1, int(np.searchsorted(ends, (ends[at - 1] if at else 0) + 50_000, "right")))
                some = batch.slice(at, stop - at)
                columns = {n: _python(some.column(n)) for n in some.schema.names}
                out = [x for row in zip(*columns.values(), strict=True) for x in links(dict(zip(columns, row, strict=True)))]
                yield pa.RecordBatch.from_pylist(out, schema=schema)
                at = stop

    return run


#: What the kernel reads of a model: each field is a list of its own, so nothing else leaves the stored model.
_READ = {"units": ("unit", "kind", "name", "params"), "nodes": ("branch", "loops"), "uses": ("seq", "root", "role"), "aliases": ("seq", "lhs", "root"), "calls": ("seq", "name", "container", "container_var", "result", "result_seq"), "args": ("seq", "arg", "key", "root"), "resolved": ("seq", "callee")}


def _python(column: pa.Array) -> list:
    """A column as Python values; lists by their flat values, which is several times as fast as value by value."""
    if pa.types.is_list(column.type):
        flat, ends = _python(column.flatten()), column.offsets.to_numpy()
        ends = (ends - ends[0]).tolist()
        return [flat[a:b] for a, b in zip(ends, ends[1:])]
    if pa.types.is_string(column.type) or not column.null_count:
        return column.to_numpy(zero_copy_only=False).tolist()
    return column.to_pylist()


def rounds(options: Options) -> Iterator[int]:
    """Numbers of the rounds of a walk, which its caller ends; an error beyond ``max_rounds``, if that is given."""
    for turn in count(1):
        if options.max_rounds is not None and turn > options.max_rounds:
            raise RuntimeError(f"the walk is not done after {options.max_rounds} rounds")
        yield turn


_HOME = ["app_id", "version", "path", "seq"]


def _events(m: Models, ops: DataFrame) -> DataFrame:
    """What may give a variable its value: (app_id, version, at_path, var, at, holds, mode, to_path, to_var, site, branch, loops)."""
    none = F.lit(None).cast("string")
    node = m.nodes.select(*KEY, "seq", "branch", "loops")
    # A node's number is its place, so an assignment finds its node without a join.
    placed = m.model.select(*KEY, F.explode(F.transform("aliases", lambda a: F.struct(a["seq"].alias("seq"), a["lhs"].alias("lhs"), a["root"].alias("root"), F.get("nodes", a["seq"]).alias("n")))).alias("x")).where("x.n is not null")
    local = placed.select("app_id", "version", F.col("path").alias("at_path"), F.col("x.lhs").alias("var"), F.col("x.seq").alias("at"), F.col("x.seq").alias("holds"), F.lit(0).alias("mode"), F.col("path").alias("to_path"), F.col("x.root").alias("to_var"), none.alias("site"), F.col("x.n.branch").alias("branch"), F.col("x.n.loops").alias("loops"))
    made = ops.where("not synthetic and not scalar and result_var is not null").select("app_id", "version", F.col("path").alias("at_path"), F.col("result_var").alias("var"), F.col("seq").alias("at"), F.coalesce("result_seq", "seq").alias("holds"), F.lit(3).alias("mode"), F.col("path").alias("to_path"), none.alias("to_var"), none.alias("site"), "branch", "loops").distinct()
    back = m.bindings.where("mode = 2").join(node.withColumnRenamed("seq", "at"), [*KEY, "at"]).select("app_id", "version", F.col("path").alias("at_path"), F.col("lhs").alias("var"), "at", F.col("at").alias("holds"), "mode", F.col("root_path").alias("to_path"), F.col("root").alias("to_var"), "site", "branch", "loops")
    words = F.array().cast("array<string>")
    into = m.bindings.where("mode = 1 and root is not null").select("app_id", "version", F.col("path").alias("at_path"), F.col("lhs").alias("var"), "at", F.col("at").alias("holds"), "mode", F.col("root_path").alias("to_path"), F.col("root").alias("to_var"), "site", words.alias("branch"), F.array().cast("array<int>").alias("loops"))
    return local.unionByName(made).unionByName(back).unionByName(into)


def _counted(options: Options) -> str:
    """Whether an event counts for a state of the walk, in SQL."""
    inside = "at < bound" if options.walk == "linear" else "not arrays_overlap(branch, not_in) and (at < bound or at_path = path and at <> seq and arrays_overlap(loops, op_loops))"
    return f"case mode when 1 then size(sites) = 0 or element_at(sites, 1) = site when 2 then ({inside}) and not array_contains(sites, site) else {inside} end"


def _walk(events: DataFrame, fresh: DataFrame, options: Options, whole: bool = True) -> DataFrame:
    """The walk as joins to a fixpoint: what was found last round is followed, the greatest bound of each variable kept.

    ``fresh``: (home of the operation, not_in, op_loops, own_branch, at_path, var, bound, sites, hops).  ``whole``: not a
    continuation of walks inside files.
    """
    state = [*_HOME, "at_path", "var", "sites"]
    fresh = written(fresh, "walk")
    seen, hits = fresh.select(*state, "bound"), None
    for turn in rounds(options):
        step = fresh.join(events, ["app_id", "version", "at_path", "var"]).where(_counted(options))
        if options.kill:
            sure = F.when((F.col("mode") != 1) & (F.col("holds") < F.col("bound")) & (F.size(F.array_except("branch", "own_branch")) == 0) & ~F.col("var").startswith("return@"), F.col("holds"))
            step = step.withColumn("last", F.max(sure).over(W.partitionBy(*state, "bound"))).where("mode = 1 or last is null or holds >= last").drop("last")
        step = written(step, "walk-step")
        hit = step.where("mode = 3 and (at_path <> path or at <> seq)").select(*_HOME, F.col("at_path").alias("prev_path"), F.col("at").alias("prev_seq"), F.col("var").alias("via_var"), "hops")
        hits = hit if hits is None else hits.unionByName(hit)
        bound = F.when(F.col("mode") == 2, F.lit(END)).otherwise(F.col("at"))
        sites = F.when(F.col("mode") == 1, F.slice("sites", 2, END)).when(F.col("mode") == 2, F.concat(F.array("site"), "sites")).otherwise(F.col("sites"))
        step = step.where("mode <> 3 and to_var is not null").select(*_HOME, "not_in", "op_loops", "own_branch", F.col("to_path").alias("at_path"), F.col("to_var").alias("var"), sites.alias("sites"), bound.alias("bound"), (F.col("hops") + 1).alias("hops"))
        step = step.groupBy(*state).agg(F.max("bound").alias("bound"), F.min("hops").alias("hops"), F.first("not_in").alias("not_in"), F.first("op_loops").alias("op_loops"), F.first("own_branch").alias("own_branch"))
        known = seen.groupBy(*state).agg(F.max("bound").alias("known"))
        fresh = written(step.join(known.hint("merge"), state, "left").where("known is null or known < bound").drop("known"), "walk")
        if fresh.isEmpty():
            break
        seen = seen.unionByName(fresh.select(*state, "bound"))
        if turn % 16 == 0:
            seen, hits = written(seen, "walk"), written(hits, "walk-hits")
    return hits.groupBy(*_HOME, "prev_path", "prev_seq").agg(F.min_by("via_var", F.struct("hops", "via_var")).alias("via_var"), F.min("hops").alias("hops"))


def _starts(m: Models, ops: DataFrame) -> DataFrame:
    roots = m.args.where("root is not null").select(*KEY, "seq", F.col("root").alias("var")).unionByName(m.uses.where("role = 'arg'").select(*KEY, "seq", F.col("root").alias("var"))).distinct()
    return _homes(ops).join(roots, [*KEY, "seq"]).select("*", F.col("path").alias("at_path"), F.col("seq").alias("bound"), F.array().cast("array<string>").alias("sites"), F.lit(0).alias("hops"))


def _homes(ops: DataFrame) -> DataFrame:
    return ops.where("not synthetic").select(*_HOME, F.transform("branch", lambda b: F.translate(b, "TF", "FT")).alias("not_in"), F.col("loops").alias("op_loops"), F.col("branch").alias("own_branch")).distinct()


def _recursive(m: Models, ops: DataFrame, options: Options) -> DataFrame:
    """The same walk as one recursive query, which follows each way once; it can't compare the ways, so it has no ``kill``."""
    if options.kill:
        raise ValueError("the recursive query can't honour kill")
    spark, tag = m.files.sparkSession, uuid.uuid4().hex[:8]
    spark.conf.set("spark.sql.cteRecursionRowLimit", "-1")  # the walk is as long as the programs make it
    events = written(_events(m, ops), "events")
    events.createOrReplaceTempView(f"events_{tag}")
    written(_starts(m, ops), "starts").createOrReplaceTempView(f"starts_{tag}")
    most = events.groupBy("app_id", "version").count().agg(F.max("count")).first()[0] or 0
    levels = most + 2 if options.max_rounds is None else options.max_rounds
    home, on = ", ".join(_HOME), _counted(options)
    carried = ", ".join(f"w.{c}" for c in _HOME)
    return spark.sql(f"""
        WITH RECURSIVE w({home}, not_in, op_loops, at_path, var, bound, sites, hops, seen) MAX RECURSION LEVEL {levels} AS (
          SELECT {home}, not_in, op_loops, at_path, var, bound, sites, hops, array(concat_ws(':', at_path, var, bound)) FROM starts_{tag}
          UNION ALL
          SELECT {home}, not_in, op_loops, to_path, to_var, next_bound, next_sites, hops + 1, array_append(seen, next_state) FROM (
            SELECT *, concat_ws(':', to_path, to_var, next_bound) AS next_state FROM (
              SELECT {carried}, w.not_in, w.op_loops, w.seen, w.hops, e.to_path, e.to_var, CASE e.mode WHEN 2 THEN {END} ELSE e.at END AS next_bound,
                CASE e.mode WHEN 1 THEN slice(w.sites, 2, {END}) WHEN 2 THEN concat(array(e.site), w.sites) ELSE w.sites END AS next_sites
              FROM w JOIN events_{tag} e ON w.app_id = e.app_id AND w.version = e.version AND w.at_path = e.at_path AND w.var = e.var
              WHERE e.mode <> 3 AND e.to_var IS NOT NULL AND ({_prefixed(on)})))
          WHERE NOT array_contains(seen, next_state)
        )
        SELECT {carried}, e.at_path AS prev_path, e.at AS prev_seq, min_by(w.var, struct(w.hops, w.var)) AS via_var, min(w.hops) AS hops
        FROM w JOIN events_{tag} e ON w.app_id = e.app_id AND w.version = e.version AND w.at_path = e.at_path AND w.var = e.var
        WHERE e.mode = 3 AND (e.at_path <> w.path OR e.at <> w.seq) AND ({_prefixed(on)})
        GROUP BY {carried}, e.at_path, e.at
    """)


def _prefixed(condition: str) -> str:
    """A condition over states and events with the sides of the join named."""
    of = {"bound": "w", "not_in": "w", "path": "w", "seq": "w", "op_loops": "w", "sites": "w", "at": "e", "mode": "e", "site": "e", "branch": "e", "loops": "e", "at_path": "e"}
    return re.sub(r"\b(" + "|".join(sorted(of, key=len, reverse=True)) + r")\b", lambda x: f"{of[x.group()]}.{x.group()}", condition)


def backward_links(m: Models, ops: DataFrame, options: Options = Options(), api: list | None = None) -> DataFrame:  # noqa: B008
    """Pairs of operations of which the later one's arguments depend on the earlier one's result, in one file or several.

    The key is the later operation's file; ``prev_path`` is the earlier one's.
    """
    out = [*KEY, "prev_path", "prev_op", "next_op", "prev_seq", "next_seq", "prev_container", "next_container", "prev_kind", "next_kind", "via_var", "hops", "cross_container"]
    cross = (F.col("prev_container") != F.col("next_container")).alias("cross_container")
    if options.strategy == "kernel":
        raw = written(m.model.select(*KEY, *[F.col(f"{t}.{c}").alias(f"{t}_{c}") for t, cs in _READ.items() for c in cs]).mapInArrow(_kernel(options, api or DEFAULT_API), _WALK), "walked")
        inside = raw.where("open_var is null")
        unnamed = inside.where("prev_var is not null or next_var is not null")
        plain = inside.where("prev_var is null and next_var is null").select("*", F.col("path").alias("prev_path"), (F.col("prev_seq") * 100).cast("long").alias("prev_op"), (F.col("next_seq") * 100).cast("long").alias("next_op"), cross).select(*out)
        parts = [plain]
        if not unnamed.isEmpty():
            parts.append(_named(unnamed.select(*KEY, F.col("next_seq").alias("seq"), F.col("path").alias("prev_path"), "prev_seq", "via_var", "hops"), ops, cross, out))
        ends = _open_ends(raw.where("open_var is not null"), m, ops)
        if ends is not None:
            parts.append(_named(_walk(written(_events(m, ops), "events"), ends, options), ops, cross, out))
        both = reduce(DataFrame.unionByName, parts)
        if ends is None:
            return both
        # A pair that both parts find keeps its shorter way.
        return both.groupBy(*[c for c in out if c not in ("via_var", "hops")]).agg(F.min_by("via_var", F.struct("hops", "via_var")).alias("via_var"), F.min("hops").alias("hops")).select(*out)
    raw = _walk(written(_events(m, ops), "events"), _starts(m, ops), options) if options.strategy == "relational" else _recursive(m, ops, options)
    return _named(raw, ops, cross, out)


def _named(raw: DataFrame, ops: DataFrame, cross, out: list[str]) -> DataFrame:
    """Links with the containers and kinds of both operations."""
    side = lambda p: ops.where("not synthetic").select("app_id", "version", F.col("path").alias("prev_path" if p == "prev" else "path"), F.col("seq").alias(f"{p}_seq"), F.col("op").alias(f"{p}_op"), F.col("container").alias(f"{p}_container"), F.col("kind").alias(f"{p}_kind"))
    both = raw.withColumnRenamed("seq", "next_seq").join(side("prev"), ["app_id", "version", "prev_path", "prev_seq"]).join(side("next"), [*KEY, "next_seq"])
    return both.select("*", cross).select(*out)


def _open_ends(raw: DataFrame, m: Models, ops: DataFrame) -> DataFrame | None:
    """Where walks that leave their file go on; None if none does."""
    if raw.isEmpty():
        return None  # most programs: nothing more to join
    beyond = m.bindings.where("path <> root_path and root is not null").select("app_id", "version", F.col("path").alias("path"), F.col("lhs").alias("open_var"), "at", "mode", "site", "root_path", "root")
    go = raw.drop("prev_seq").join(beyond, [*KEY, "open_var"]).where("case mode when 1 then size(sites) = 0 else at < bound and not array_contains(sites, site) end")
    go = go.select(*KEY, F.col("next_seq").alias("seq"), F.col("root_path").alias("at_path"), F.col("root").alias("var"), F.when(F.col("mode") == 1, F.col("at")).otherwise(F.lit(END)).alias("bound"), F.when(F.col("mode") == 1, F.col("sites")).otherwise(F.concat(F.array("site"), "sites")).alias("sites"), (F.col("hops") + 1).alias("hops"))
    ends = written(go.join(_homes(ops), _HOME), "open-ends")
    return None if ends.isEmpty() else ends


def operation_chains(ops: DataFrame) -> DataFrame:
    """Operations of a unit in order, each with the one before and after."""
    order = W.partitionBy(*KEY, "unit").orderBy("op")
    return ops.select(*KEY, "unit", "op", "kind", "container", F.lag("op").over(order).alias("prev"), F.lead("op").over(order).alias("next"))


def chain_depth(links: DataFrame) -> DataFrame:
    """For each operation the longest chain of dependencies that ends at it; an error if the links have a cycle."""
    if "prev_path" not in links.columns:
        links = links.withColumn("prev_path", F.col("path"))
    links = links.select(*KEY, "prev_path", "prev_op", "next_op")
    depth = links.select("app_id", "version", F.col("prev_path").alias("path"), F.col("prev_op").alias("op"), F.lit(0).alias("depth")).unionByName(links.select(*KEY, F.col("next_op").alias("op"), F.lit(1).alias("depth")))
    depth = written(depth.groupBy(*KEY, "op").agg(F.max("depth").alias("depth")), "depth")
    most = depth.groupBy("app_id", "version").count().agg(F.max("count")).first()[0] or 0
    for _ in range(most + 1):  # without a cycle a chain has each operation once
        step = links.join(depth.select("app_id", "version", F.col("path").alias("prev_path"), F.col("op").alias("prev_op"), "depth"), ["app_id", "version", "prev_path", "prev_op"]).select(*KEY, F.col("next_op").alias("op"), (F.col("depth") + 1).alias("deeper"))
        step = step.groupBy(*KEY, "op").agg(F.max("deeper").alias("deeper"))
        new = written(depth.join(step, [*KEY, "op"], "left").select(*KEY, "op", F.col("depth").alias("was"), F.greatest("depth", F.coalesce("deeper", F.lit(0))).alias("depth")), "depth")
        depth = new.drop("was")
        if new.where("was <> depth").isEmpty():
            return depth
    raise ValueError("the links have a cycle: no longest chain")


# -- forward pass --------------------------------------------------------------------------------
def reach(m: Models, ops: DataFrame, options: Options = Options()) -> DataFrame:  # noqa: B008
    """Variables that hold an operation's result or a part of it: (key, op, var_path, var, prefix of the path, from where).

    ``var_path`` is the variable's file: results go into functions as arguments and out of them as returned values.
    """
    program, words = ["app_id", "version"], F.array().cast("array<string>")
    start = ops.where("not synthetic and not scalar and result_var is not null").select(*KEY, "op", F.col("path").alias("var_path"), F.col("result_var").alias("var"), F.expr(f"cast(array() as {STEPS})").alias("prefix"), words.alias("sites"), F.col("seq").alias("at")).distinct()
    seen = fresh = written(start, "held")
    state = [*KEY, "op", "var_path", "var", "prefix", "sites"]
    if options.aliases:
        none = F.lit(None).cast("string")
        local = m.aliases.where("root is not null").select(*program, F.col("path").alias("var_path"), F.col("root").alias("var"), F.col("path").alias("to_path"), "lhs", "steps", F.col("seq").alias("place"), F.lit(0).alias("mode"), none.alias("site"))
        given = local.unionByName(m.bindings.where("root is not null").select(*program, F.col("root_path").alias("var_path"), F.col("root").alias("var"), F.col("path").alias("to_path"), "lhs", "steps", F.col("at").alias("place"), "mode", "site"))
        for turn in rounds(options):
            step = fresh.join(given, [*program, "var_path", "var"]).where("case mode when 0 then place >= at when 1 then place >= at and not array_contains(sites, site) else size(sites) = 0 or element_at(sites, 1) = site end")
            sites = F.when(F.col("mode") == 1, F.concat(F.array("site"), "sites")).when(F.col("mode") == 2, F.slice("sites", 2, END)).otherwise(F.col("sites"))
            step = step.select(*KEY, "op", F.col("to_path").alias("var_path"), F.col("lhs").alias("var"), F.concat("prefix", "steps").alias("prefix"), sites.alias("sites"), F.when(F.col("mode") == 1, F.lit(-1)).otherwise(F.col("place")).alias("at"))
            step = step.groupBy(*state).agg(F.min("at").alias("at"))
            known = seen.groupBy(*state).agg(F.min("at").alias("known"))
            fresh = written(step.join(known.hint("merge"), state, "left").where((F.col("known").isNull() | (F.col("at") < F.col("known"))) & (F.size("prefix") < 24)).drop("known"), "held")
            if fresh.isEmpty():
                break
            seen = seen.unionByName(fresh)
            if turn % 16 == 0:
                seen = written(seen, "held")
    return seen.groupBy(*KEY, "op", "var_path", "var", "prefix").agg(F.min("at").alias("at"))


def accesses(m: Models, ops: DataFrame, held: DataFrame) -> DataFrame:
    """Property paths that are read of each operation's objects: (key, op, container, use_path, seq, elem, block, steps, evidence).

    ``use_path`` is the file in which they are read.  Paths that lead through the field a lookup stage makes belong to that stage's operation.
    """
    op = ops.where("not synthetic").select(*KEY, "op", "container", "multi", "element")
    uses = m.uses.withColumnRenamed("root", "var").withColumnRenamed("path", "var_path")
    path = held.join(uses, ["app_id", "version", "var_path", "var"]).where("seq >= at or role = 'write'")
    path = path.select(*KEY, "op", F.col("var_path").alias("use_path"), "seq", "elem", "block", "role", "literal_type", F.concat("prefix", "steps").alias("steps"))
    path = path.join(op, [*KEY, "op"])
    # Methods that a cursor or array of results has are not fields; an index into the results is one of them.
    indexed = F.col("multi") & (F.get("steps", F.lit(0))["kind"] == "index")
    path = path.withColumn("steps", F.when(indexed, F.slice("steps", 2, 64)).otherwise(F.col("steps")))
    listed = F.col("multi") & ~F.col("element") & ~indexed & ((F.get("steps", F.lit(0))["kind"] == "method") | (F.get("steps", F.lit(0))["name"] == "length"))
    path = path.where(~F.coalesce(listed, F.lit(False)) & (F.size("steps") > 0)).drop("multi", "element")
    staged = m.args.select(*KEY, "seq", "key", "literal").where(r"key rlike '^[0-9]+[.][$](project|group|match|sort)[.]' or key rlike '^[0-9]+[.][$]unwind'")
    named = staged.select(*KEY, "seq", F.when(F.col("key").rlike("unwind"), F.expr("substring(literal, 2)")).otherwise(F.regexp_replace("key", r"^[0-9]+[.][$]\w+[.]", "")).alias("dotted"), F.col("key").rlike("unwind").alias("many"))
    named = named.where("dotted is not null and dotted <> '' and not dotted like '%$%'")
    steps = F.transform(F.split("dotted", "[.]"), lambda p: F.struct(p.alias("name"), F.lit("prop").alias("kind")))
    steps = F.when(F.col("many"), F.concat(steps, F.array(F.struct(F.lit("[]").alias("name"), F.lit("index").alias("kind"))))).otherwise(steps)
    named = named.select(*KEY, "seq", steps.alias("steps")).join(ops.where("call = 'aggregate'").select(*KEY, "seq", "op", "container", "elem", "block"), [*KEY, "seq"])
    path = path.unionByName(named.select(*KEY, "op", F.col("path").alias("use_path"), "seq", "elem", "block", F.lit("stage").alias("role"), F.lit(None).cast("string").alias("literal_type"), "steps", "container"))
    stage = ops.where("synthetic").select(*KEY, F.col("op").alias("stage_op"), (F.floor(F.col("op") / 100) * 100).alias("op"), F.col("container").alias("stage_container"), F.col("as_field").alias("head"))
    joined = path.withColumn("head", F.get("steps", F.lit(0))["name"]).join(stage, [*KEY, "op", "head"], "left")
    into = F.col("stage_op").isNotNull()
    rest = F.slice("steps", 2, 64)
    rest = F.when(F.element_at(F.concat(rest, F.array(F.struct(F.lit("").alias("name"), F.lit("prop").alias("kind")))), 1)["kind"] == "index", F.slice(rest, 2, 64)).otherwise(rest)
    out = joined.select(*KEY, F.coalesce("stage_op", "op").alias("op"), F.coalesce("stage_container", "container").alias("container"), "use_path", "seq", "elem", "block", "role", "literal_type", F.when(into, rest).otherwise(F.col("steps")).alias("steps"))
    return out.where(F.exists("steps", lambda s: s["kind"] == "prop"))


_COLLECTS = "'push','pop','shift','unshift','splice','join','sort','reverse','at','entries','keys','values','forEach','map','filter','some','every','flatMap','reduce'"
_AMBIGUOUS = "'length','indexOf','includes','slice','concat'"


def filter_fields(m: Models, ops: DataFrame) -> DataFrame:
    """Keys of filters as fields of the container that is asked: (key, op, container, path, literal_type)."""
    f = m.args.join(ops.where("filter_arg is not null").select(*KEY, "seq", "op", "container", F.col("filter_arg").alias("arg")), [*KEY, "seq", "arg"])
    return f.where("key <> ''").select(*KEY, "op", "container", "seq", F.expr(f"array_join({_PATH}, '.')").alias("field"), "literal_type", F.col("key").rlike(r"[$](in|nin|all|elemMatch)").alias("many"), "root", "steps").where("field <> ''")


def payload_fields(m: Models, ops: DataFrame) -> DataFrame:
    """Keys of inserted and updated values as fields."""
    p = m.args.join(ops.where("payload_arg is not null").select(*KEY, "seq", "op", "container", F.col("payload_arg").alias("arg")), [*KEY, "seq", "arg"])
    return p.where("key <> ''").select(*KEY, "op", "container", F.expr(f"array_join({_PATH}, '.')").alias("field"), "literal_type", F.col("key").rlike(r"[$](push|addToSet|pull)").alias("pushed")).where("field <> ''")


def field_evidence(m: Models, ops: DataFrame, reads: DataFrame, options: Options = Options()) -> DataFrame:  # noqa: B008
    """Every sign of a field: one row for each prefix of each path."""
    read_ops = ops.where("kind = 'R'").select(*KEY, "op")
    e = reads.join(read_ops, [*KEY, "op"], "left_semi")
    e = e.select(*KEY, "op", "container", "literal_type", "steps", F.posexplode("steps").alias("pos", "step")).where("step.kind = 'prop'")
    next_step = F.expr("try_element_at(steps, pos + 2)")
    later = F.exists(F.expr("slice(steps, pos + 2, 64)"), lambda s: (s["kind"] == "prop") & ~s["name"].isin("length"))
    e = e.select(
        *KEY, "op", "container", F.expr("array_join(transform(filter(slice(steps, 1, pos + 1), s -> s.kind = 'prop'), s -> s.name), '.')").alias("field"), "step.name",
        F.coalesce(later, F.lit(False)).alias("deep"),
        F.coalesce((next_step["kind"] == "index") | (next_step["kind"] == "method") & next_step["name"].isin(*[x.strip("'") for x in _COLLECTS.split(",")]), F.lit(False)).alias("many"),
        F.when((F.size("steps") == F.col("pos") + 1) | (next_step["kind"] == "index") & (F.size("steps") == F.col("pos") + 2), F.col("literal_type")).when((next_step["kind"] == "method") & F.col("literal_type").isNotNull(), F.col("literal_type")).alias("literal_type"),
        F.lit("read").alias("source"),
    ).where("name not in ('length')")
    f = filter_fields(m, ops).select(*KEY, "op", "container", "field", F.lit(False).alias("deep"), F.lit(False).alias("many"), F.when(F.col("root").isNull(), F.col("literal_type")).alias("literal_type"), F.lit("filter").alias("source"))
    e = e.drop("name").unionByName(f)
    if options.learn_from_writes:
        e = e.unionByName(payload_fields(m, ops).select(*KEY, "op", "container", "field", F.lit(False).alias("deep"), F.col("pushed").alias("many"), "literal_type", F.lit("write").alias("source")))
    # A dotted key shows its prefixes to be aggregates.
    dotted = e.where("field like '%.%'").select(*KEY, "op", "container", F.explode(F.expr("transform(sequence(1, size(split(field, '[.]')) - 1), i -> array_join(slice(split(field, '[.]'), 1, i), '.'))")).alias("field"), F.lit(True).alias("deep"), F.lit(False).alias("many"), F.lit(None).cast("string").alias("literal_type"), "source")
    return e.unionByName(dotted)


def fields(m: Models, ops: DataFrame, reads: DataFrame, options: Options = Options(), by: list[str] | None = None) -> DataFrame:  # noqa: B008
    """Fields of containers, folded so that the order of evidence doesn't matter.

    type_kind: attribute, aggregate, collection (of attributes), collection_of_aggregates; type ``string`` with evidence
    ``default`` where nothing shows another.
    """
    keys = by if by is not None else ["app_id", "version"]
    e = field_evidence(m, ops, reads, options).where("container is not null and container <> '?'")
    g = e.groupBy(*keys, "container", "field").agg(F.max("deep").alias("deep"), F.max("many").alias("many"), F.sort_array(F.collect_set(F.when(F.col("literal_type") != "null", F.col("literal_type")))).alias("types"), F.count("*").alias("n_sites"))
    n, numeric = F.size("types"), F.array_except("types", F.array(F.lit("long"), F.lit("double")))
    kind = F.when(F.col("deep") & F.col("many"), "collection_of_aggregates").when(F.col("many"), "collection").when(F.col("deep"), "aggregate").otherwise("attribute")
    prim = F.when(n == 0, "string").when(n == 1, F.get("types", F.lit(0))).when(F.size(numeric) == 0, "double").otherwise("string")
    evidence = F.when(n == 0, "default").when((n > 1) & (F.size(numeric) > 0), "conflict").otherwise("literal")
    return g.select(*keys, "container", "field", kind.alias("type_kind"), F.when(kind.isin("aggregate", "collection_of_aggregates"), F.lit(None).cast("string")).otherwise(prim).alias("prim_type"), F.when(kind.isin("aggregate", "collection_of_aggregates"), "structure").otherwise(evidence).alias("evidence"), "n_sites")


# -- references ----------------------------------------------------------------------------------
def references(m: Models, ops: DataFrame, held: DataFrame, links: DataFrame) -> DataFrame:
    """Join conditions: (key, prev_path, prev_op, next_op, holder, field, referenced, referenced_field, cmp, upper_bound, reverse).

    A condition on the asked container's ``_id`` shows a reference of the known one, a known ``_id`` that is asked for one
    of the asked container; where neither is ``_id`` the known field refers to the asked one, a key of its own.
    """
    f = filter_fields(m, ops).where("root is not null").select(*KEY, F.col("op").alias("next_op"), F.col("container").alias("asked"), F.col("seq").alias("next_seq"), F.col("field").alias("asked_field"), "many", F.col("root").alias("var"), "steps")
    f = f.join(ops.where("not synthetic").select(*KEY, F.col("op").alias("next_op"), F.col("multi").alias("asks_many")).distinct(), [*KEY, "next_op"])
    h = held.join(ops.where("not synthetic").select(*KEY, "op", F.col("container").alias("known"), "multi"), [*KEY, "op"]).select("app_id", "version", F.col("path").alias("prev_path"), F.col("op").alias("prev_op"), F.col("var_path").alias("path"), "var", "prefix", "at", "known", "multi")
    c = f.join(h, [*KEY, "var"]).where("(prev_path <> path or next_op <> prev_op) and at <= next_seq")
    on = [*KEY, "prev_path", "prev_op", "next_op"]
    c = c.join(links.select(*on), on, "left_semi")
    full = F.concat("prefix", "steps")
    collected = F.col("many") | F.exists(full, lambda s: s["kind"] == "index") & ~F.col("multi")
    c = c.select(*on, "known", "asked", "asked_field", steps_path(full).alias("known_field"), collected.alias("collected"), "many", "asks_many").where("known_field <> '' and known <> asked")
    by_key = F.when(F.col("many"), "in").otherwise("eq").alias("cmp")
    pick = lambda df, held_by, to, upper, reverse: df.select(*on, F.col(held_by).alias("holder"), F.col(f"{held_by}_field").alias("field"), F.col(to).alias("referenced"), F.col(f"{to}_field").alias("referenced_field"), by_key, upper.alias("upper_bound"), F.lit(reverse).alias("reverse"))
    one = F.when(F.col("collected"), "many").otherwise("one")
    forward = pick(c.where("asked_field = '_id' and known_field <> '_id'"), "known", "asked", one, False)
    backward = pick(c.where("asked_field <> '_id' and known_field = '_id'"), "asked", "known", F.lit("one"), True)
    natural = pick(c.where("asked_field <> '_id' and known_field <> '_id'"), "known", "asked", F.when(F.col("collected") | F.col("asks_many"), "many").otherwise("one"), False)
    s = expand_pipelines(m, ops.where("not synthetic"))
    unwound = m.args.where(r"key rlike '^[0-9]+[.][$]unwind'").select(*KEY, "seq", F.expr("substring(literal, 2)").alias("as_field"), F.lit(True).alias("unwound"))
    s = s.join(unwound, [*KEY, "seq", "as_field"], "left")
    to_id = (F.col("foreignField") == "_id") | (F.col("localField") != "_id")
    # A stage that finds the holders of an id and is then unwound stands for the one holder of each object.
    stages = s.select(*KEY, F.col("path").alias("prev_path"), F.col("base_op").alias("prev_op"), F.col("op").alias("next_op"), F.when(to_id, F.col("container")).otherwise(F.col("referenced")).alias("holder"), F.when(to_id, F.col("localField")).otherwise(F.col("foreignField")).alias("field"), F.when(to_id, F.col("referenced")).otherwise(F.col("container")).alias("referenced"), F.when(to_id, F.col("foreignField")).otherwise(F.lit("_id")).alias("referenced_field"), F.lit("lookup").alias("cmp"), F.when(F.coalesce("unwound", F.lit(False)) & ~to_id, "one").otherwise("many").alias("upper_bound"), (~to_id).alias("reverse"))
    return forward.unionByName(backward).unionByName(natural).unionByName(stages)


def join_pairs(m: Models, ops: DataFrame, links: DataFrame, refs: DataFrame, options: Options = Options()) -> DataFrame:  # noqa: B008
    """Joins: (key, prev_path, prev_op, next_op, host, referenced, join_type), sequential ones by the rule and one a lookup stage.

    The operation that receives the data is the join; the host is what is read first.
    """
    reads = links.where("prev_kind = 'R' and next_kind = 'R'")
    if options.join_rule == "cross_container":
        reads = reads.where("cross_container")
    elif options.join_rule == "key_equality":
        reads = reads.join(refs.select(*KEY, "prev_path", "prev_op", "next_op"), [*KEY, "prev_path", "prev_op", "next_op"], "left_semi")
    plain = reads.select(*KEY, "prev_path", "prev_op", "next_op", F.col("prev_container").alias("host"), F.col("next_container").alias("referenced"), F.lit("sequential").alias("join_type"))
    s = expand_pipelines(m, ops.where("not synthetic"))
    return plain.unionByName(s.select(*KEY, F.col("path").alias("prev_path"), F.col("base_op").alias("prev_op"), F.col("op").alias("next_op"), F.col("container").alias("host"), "referenced", F.lit("pipeline").alias("join_type")))


def merge_structures(found: DataFrame, scope: str = "container") -> DataFrame:
    """One structure for each distinct field set (by version), and the places that share it.

    ``global`` merges over containers but keeps every container's row.
    """
    keys = ["app_id", "version", "container"]
    s = found.groupBy(*keys).agg(digest_of(F.concat_ws(":", "field", "type_kind")).alias("digest"), F.count("*").alias("n_fields"))
    over = W.partitionBy("app_id", *([] if scope == "global" else ["container"]), "digest").orderBy("container", "version")
    return s.withColumn("kept_as", F.first(F.concat_ws("@", "container", "version")).over(over)).withColumn("kept", F.row_number().over(over) == 1)


class Access:
    """The access model of a bundle; parts are made when they are read, shared ones once."""

    def __init__(self, m: Models, options: Options = Options(), api: list | None = None) -> None:  # noqa: B008
        self.m, self.options, self.api = m, options, api
        self.ops = written(all_operations(m, api), "ops")
        self.links = written(backward_links(m, self.ops, options, api), "links")
        self.held = written(reach(m, self.ops, options), "held-all")
        self.reads = written(accesses(m, self.ops, self.held), "reads")
        self.refs = written(references(m, self.ops, self.held if options.aliases else reach(m, self.ops), self.links), "refs")
        self.joins = written(join_pairs(m, self.ops, self.links, self.refs, options), "joins")

    def fields(self, by: list[str] | None = None) -> DataFrame:
        return fields(self.m, self.ops, self.reads, self.options, by)

    def structures(self) -> DataFrame:
        return merge_structures(self.fields(), self.options.merge_scope)


def trace(a: Access) -> DataFrame:
    """The steps of the extraction: (step, rule, subject, update).  Fields of containers that a join reads are a step of their own."""
    row = lambda step, rule, df, subject, update: df.select(F.lit(step).alias("step"), F.lit(rule).alias("rule"), subject.alias("subject"), update.alias("update")).distinct()
    f = a.fields().join(a.joins.select("app_id", "version", F.col("referenced").alias("container"), F.lit(True).alias("joined")).distinct(), ["app_id", "version", "container"], "left")
    plain, full = "type_kind = 'attribute' and not field like '%.%'", F.concat_ws(".", "container", "field")
    kind = F.coalesce("prim_type", "type_kind")
    return (
        row(1, "model", a.m.model, F.col("app_id"), F.lit("create empty"))
        .unionByName(row(2, "operation", a.ops, F.col("container"), F.concat(F.lit("create "), F.col("kind"))))
        .unionByName(row(3, "dependency", a.joins, F.col("referenced"), F.concat(F.lit("join with "), F.col("host"))))
        .unionByName(row(4, "container", a.ops.where("kind = 'R'"), F.col("container"), F.lit("container and structure")))
        .unionByName(row(5, "field", f.where(f"joined is null and {plain}"), full, F.col("prim_type")))
        .unionByName(row(6, "nested field", f.where(f"joined is null and not ({plain})"), full, kind))
        .unionByName(row(7, "field of a joined container", f.where("joined"), full, kind))
        .unionByName(row(8, "reference", a.refs, F.concat_ws(".", "holder", "field"), F.concat_ws(".", "referenced", "referenced_field")))
    )


def ops_in_block_range(a: Access) -> DataFrame:
    """Operations with every block that encloses them: (key, op, block), a range join of nodes' places with blocks' spans."""
    nodes = a.m.nodes.select(*KEY, "seq", "block")
    spans = nodes.groupBy(*KEY, "block").agg(F.min("seq").alias("low"), F.max("seq").alias("high"))
    parent = a.m.elements.where("kind = 'block'").select(*KEY, F.col("elem").alias("block"))
    op = a.ops.where("not synthetic").select(*KEY, "op", "seq")
    return op.join(spans.join(parent, [*KEY, "block"]), KEY).where("seq between low and high").select(*KEY, "op", "block").distinct()


def asof_definition(m: Models) -> DataFrame:
    """For each use of a variable the last place before it that gave it a value: (key, seq, root, defined)."""
    given = m.aliases.select(*KEY, F.col("lhs").alias("root"), "seq", F.col("seq").alias("given"))
    both = m.uses.select(*KEY, "root", "seq", F.lit(None).cast("int").alias("given")).distinct().unionByName(given)
    order = W.partitionBy(*KEY, "root").orderBy("seq", F.col("given").isNotNull()).rowsBetween(W.unboundedPreceding, -1)
    return both.withColumn("defined", F.last("given", ignorenulls=True).over(order)).where("given is null and defined is not null").select(*KEY, "seq", "root", "defined")


def path_prefixes(reads: DataFrame) -> DataFrame:
    """Every prefix of every property path that is read: (app_id, version, container, prefix, n)."""
    names = F.transform(F.filter("steps", lambda x: x["kind"] == "prop"), lambda x: x["name"])
    each = reads.select("app_id", "version", "container", names.alias("names")).where("size(names) > 0")
    each = each.select("app_id", "version", "container", F.explode(F.transform(F.sequence(F.lit(1), F.size("names")), lambda i: F.array_join(F.slice("names", 1, i), "."))).alias("prefix"))
    return each.groupBy("app_id", "version", "container", "prefix").agg(F.count("*").alias("n"))


def distinct_fields(found: DataFrame, exact: bool = False) -> DataFrame:
    """How many fields the containers of each program have: by a sketch, or exactly."""
    name = F.concat_ws(".", "container", "field")
    n = F.countDistinct(name) if exact else F.approx_count_distinct(name, 0.02)
    return found.groupBy("app_id", "version").agg(n.alias("n_fields"))


def list_statements(a: Access) -> DataFrame:
    """The text of every statement that accesses the store, with its line."""
    return a.ops.where("not synthetic").select(*KEY, "line", "kind", "container", "text")


def op_matrix(ops: DataFrame) -> DataFrame:
    """Operations by container and kind."""
    return ops.groupBy("container").pivot("kind", ["R", "I", "U", "D"]).count().na.fill(0).select("container", *[F.col(k).alias(f"n_{k.lower()}") for k in ("R", "I", "U", "D")])


