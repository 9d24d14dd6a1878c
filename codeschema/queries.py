"""Queries over the given tables, one for each method, variant, baseline, measure or operator, and their SQL."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import partial, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import streaming
from .frontend import sqltext
from .frontend.tokens import register_code_tokens
from .functions import name_similarity, singular
from .operators import access, joins, logical, measure, migrate, models, profile, rewrite, shop
from .operators.access import Access
from .operators.models import KEY, Models
from .plans import Options, paper_options
from .sources import TABLES, as_files, corpora, read_documents, read_graph, read_table, write_documents
from .store import shared_folder, written

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None) -> Callable[[Query], Query]:
    def put(fn: Query) -> Query:
        QUERIES[name] = fn
        if sql:
            ORACLES[name] = sql
        return fn

    return put


def values(columns: str, *rows: str) -> str:
    """SQL for a small table that is known."""
    return f"SELECT * FROM (VALUES {', '.join(rows)}) AS t({columns})"


def _tables(spark: SparkSession, d: str) -> dict[str, DataFrame]:
    return {t: read_table(spark, d, t) for t in TABLES}


# -- front end -----------------------------------------------------------------------------------
@query("page_script_calls", r"SELECT page_id, CAST(regexp_extract(html, 'track\((\d+)\)', 1) AS BIGINT) AS track FROM pages")
def page_script_calls(spark, d):
    return profile.script_calls(read_table(spark, d, "pages"))


@query("token_calls_pages", r"SELECT 'page' || page_id || '.html' AS path, 'track' AS callee, regexp_extract(html, 'track\((\d+)\)', 1) AS literal FROM pages")
def token_calls_pages(spark, d):
    """The calls in page scripts as the parser sees them; a string in each holds a closing tag."""
    m = Models(corpora.page_scripts(spark, d))
    return m.calls.join(m.args, [*KEY, "seq"]).where("name = 'track'").select("path", F.col("name").alias("callee"), "literal")


@query("inject_roundtrip", values("path", "('none')") + " WHERE false")
def inject_roundtrip(spark, d):
    """Fixture files whose regenerated text differs: none."""
    files = corpora.micro(spark).unionByName(corpora.running_example(spark)).unionByName(corpora.backend(spark))
    return rewrite.roundtrip_diff(files, Models(files))


@query("parse_errors", values("path", "('syntax_error.js')"))
def parse_errors(spark, d):
    return Models(corpora.micro(spark)).errors().select("path")


@query("local_types", values("variable, type", "('n', 'long')", "('s', 'string')", "('d', 'double')", "('b', 'boolean')"))
def local_types(spark, d):
    files = spark.createDataFrame([("m", 1, "m.js", "const n = 1;\nlet s = 'a';\nvar d = 1.5;\nconst b = true;", "", "js")], "app_id string, version int, path string, content string, sha string, lang string")
    return models.infer_local_types(Models(files)).select("variable", "type")


@query("object_sketches", values("variable, properties", "('member@1', 'acctbal,mktsegment,name,recent')", "('order@1', 'priority')"))
def object_sketches(spark, d):
    m = Models(corpora.running_example(spark))
    return models.object_sketches(m).where("root like 'member%' or root like 'order%'").select(F.col("root").alias("variable"), F.array_join("properties", ",").alias("properties"))


@query(
    "container_hierarchy",
    r"""WITH p AS (SELECT string_split(regexp_replace(regexp_replace(url, '^[a-z]+://', ''), '[?#].*$', ''), '/') AS parts FROM pages),
    l AS (SELECT parts, unnest(range(1, len(parts) + 1)) AS depth FROM p)
    SELECT DISTINCT array_to_string(parts[1:depth], '/') AS container, CASE WHEN depth > 1 THEN array_to_string(parts[1:depth - 1], '/') END AS parent, CASE WHEN depth = len(parts) THEN 'file' ELSE 'folder' END AS kind FROM l""",
)
def container_hierarchy(spark, d):
    """Hosts, folders and files of the pages, by their addresses."""
    path = F.regexp_replace(F.regexp_replace("url", "^[a-z]+://", ""), "[?#].*$", "")
    files = read_table(spark, d, "pages").select(F.lit("pages").alias("app_id"), F.lit(1).alias("version"), path.alias("path"))
    return models.containers(files).select("container", "parent", "kind")


# -- flow ----------------------------------------------------------------------------------------
@query("flow_counts", values("kind, n", "('call', CAST(9 AS BIGINT))", "('decl', 5)", "('return', 1)", "('selection', 1)", "('start', 2)", "('end', 2)"))
def flow_counts(spark, d):
    m = Models(corpora.running_example(spark))
    return models.flow_nodes(m).groupBy("kind").agg(F.count("*").alias("n"))


@query("flow_edges_if", values("src, dst, kind", "(0, 1, 'true')", "(0, 2, 'false')", "(-1, 0, 'next')", "(1, 3, 'next')", "(2, 3, 'next')", "(3, -2, 'next')"))
def flow_edges_if(spark, d):
    files = spark.createDataFrame([("m", 1, "m.js", "if (a > 1) { b(); } else { c(); } e();", "", "js")], "app_id string, version int, path string, content string, sha string, lang string")
    return models.flow_edges(Models(files)).select("src", "dst", "kind")


@query("reachable_nodes", """
WITH RECURSIVE e(src, dst) AS (VALUES (0, 1), (0, 2), (-1, 0), (1, 3), (2, 3), (3, -2)),
r(dst, dist) AS (SELECT -1, 0 UNION ALL SELECT e.dst, r.dist + 1 FROM r JOIN e ON e.src = r.dst)
SELECT dst, min(dist) AS dist FROM r GROUP BY dst""")
def reachable_nodes(spark, d):
    files = spark.createDataFrame([("m", 1, "m.js", "if (a > 1) { b(); } else { c(); } e();", "", "js")], "app_id string, version int, path string, content string, sha string, lang string")
    m = Models(files)
    return models.reachable(models.flow_edges(m), models.flow_nodes(m).where("kind = 'start'")).select("dst", "dist")


@query("unresolved_calls", values("callee", "('missing')"))
def unresolved_calls(spark, d):
    files = spark.createDataFrame([("m", 1, "m.js", "function f() { return 1; } f(); missing();", "", "js")], "app_id string, version int, path string, content string, sha string, lang string")
    return models.unresolved_calls(Models(files)).select("callee")


@query("basic_blocks", "SELECT CAST(basic_block AS BIGINT) AS basic_block, count(*) AS n FROM supplier, (VALUES (1), (2), (3), (4)) AS b(basic_block) WHERE basic_block < 4 OR s_nationkey % 2 = 0 GROUP BY 1")
def basic_blocks(spark, d):
    """A file a supplier with a selection; those of every second nation have another branch."""
    s = read_table(spark, d, "supplier")
    other = F.when(F.col("s_nationkey") % 2 == 0, F.lit(" else { c(); }")).otherwise(F.lit(""))
    text = F.concat(F.format_string("if (a > %d) { b(); }", "s_suppkey"), other, F.lit(" e();"))
    files = as_files(s.select(F.col("s_nationkey").alias("app_id"), F.lit(1).alias("version"), F.format_string("s%d.js", "s_suppkey").alias("path"), text.alias("content"), F.lit("js").alias("lang")))
    return models.basic_blocks(Models(files)).groupBy("basic_block").agg(F.count("*").alias("n"))


# -- operations ----------------------------------------------------------------------------------
_C2 = """
WITH e AS (SELECT *, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events),
o AS (
  SELECT event_id, user_id, CAST(week(ts) AS INTEGER) AS version, 'events' AS container, 'D' AS kind FROM e WHERE k % 10 = 0
  UNION ALL SELECT event_id, user_id, CAST(week(ts) AS INTEGER), 'customers', 'R' FROM e WHERE k % 10 <> 0 AND event_type IN ('view', 'click')
  UNION ALL SELECT event_id, user_id, CAST(week(ts) AS INTEGER), 'events', 'R' FROM e WHERE k % 10 <> 0 AND event_type = 'click'
  UNION ALL SELECT event_id, user_id, CAST(week(ts) AS INTEGER), 'orders', 'I' FROM e WHERE k % 10 <> 0 AND event_type = 'purchase'
  UNION ALL SELECT event_id, user_id, CAST(week(ts) AS INTEGER), 'customers', 'I' FROM e WHERE k % 10 <> 0 AND event_type = 'signup'
  UNION ALL SELECT event_id, user_id, CAST(week(ts) AS INTEGER), 'events', 'U' FROM e WHERE k % 10 <> 0 AND event_type NOT IN ('view', 'click', 'purchase', 'signup')
)
"""


def _c2_ops(spark, d) -> DataFrame:
    return access.find_operations(Models(corpora.event_snippets(spark, d)))


@query("find_operations", _C2 + "SELECT CAST(user_id AS VARCHAR) AS app_id, version, 'e' || event_id || '.js' AS path, container, kind FROM o")
def find_operations(spark, d):
    return _c2_ops(spark, d).select("app_id", "version", "path", "container", "kind")


@query("ops_by_container_kind", _C2 + "SELECT container, kind, count(*) AS n FROM o GROUP BY ALL")
def ops_by_container_kind(spark, d):
    return _c2_ops(spark, d).groupBy("container", "kind").agg(F.count("*").alias("n"))


@query("ops_cube", _C2 + "SELECT coalesce(container, '*') AS container, coalesce(kind, '*') AS kind, count(*) AS n FROM o GROUP BY CUBE(container, kind)")
def ops_cube(spark, d):
    return _c2_ops(spark, d).cube("container", "kind").agg(F.count("*").alias("n")).na.fill("*")


@query("ops_grouping_sets", _C2 + "SELECT coalesce(container, '*') AS container, coalesce(CAST(version AS VARCHAR), '*') AS version, count(*) AS n FROM o GROUP BY GROUPING SETS ((container), (version))")
def ops_grouping_sets(spark, d):
    return spark.sql("SELECT coalesce(container, '*') AS container, coalesce(CAST(version AS STRING), '*') AS version, count(*) AS n FROM {ops} GROUP BY GROUPING SETS ((container), (version))", ops=_c2_ops(spark, d))


@query("op_matrix", _C2 + "SELECT container, count(*) FILTER (kind = 'R') AS n_r, count(*) FILTER (kind = 'I') AS n_i, count(*) FILTER (kind = 'U') AS n_u, count(*) FILTER (kind = 'D') AS n_d FROM o GROUP BY container")
def op_matrix(spark, d):
    return access.op_matrix(_c2_ops(spark, d))


@query("topk_containers", _C2 + "SELECT app_id, container, n FROM (SELECT CAST(user_id AS VARCHAR) AS app_id, container, count(*) AS n, row_number() OVER (PARTITION BY user_id ORDER BY count(*) DESC, container) AS r FROM o GROUP BY user_id, container) WHERE r <= 2")
def topk_containers(spark, d):
    n = _c2_ops(spark, d).groupBy("app_id", "container").agg(F.count("*").alias("n"))
    return n.withColumn("r", F.row_number().over(W.partitionBy("app_id").orderBy(F.desc("n"), "container"))).where("r <= 2").drop("r")


@query("access_points_regex", _C2 + "SELECT 'e' || event_id || '.js' AS path, container, CASE kind WHEN 'R' THEN 'findOne' WHEN 'I' THEN 'insertOne' WHEN 'U' THEN 'updateOne' ELSE 'deleteOne' END AS call FROM o")
def access_points_regex(spark, d):
    """The baseline that finds calls by patterns."""
    return profile.detect_access_points(corpora.event_snippets(spark, d)).select("path", "container", "call")


_C3 = "SELECT 'o' || o_orderkey || '.js' AS path, 'orders' AS prev_container, 'customers' AS next_container, CAST(o_orderkey % 4 AS INTEGER) AS hops FROM orders"


def _c3(spark, d, **options) -> tuple[Models, DataFrame, DataFrame]:
    m = Models(corpora.order_snippets(spark, d))
    ops = access.find_operations(m)
    return m, ops, access.backward_links(m, ops, Options(**options))


@query("backward_links_kernel", _C3)
def backward_links_kernel(spark, d):
    return _c3(spark, d)[2].select("path", "prev_container", "next_container", "hops")


@query("backward_links_relational", _C3)
def backward_links_relational(spark, d):
    return _c3(spark, d, strategy="relational")[2].select("path", "prev_container", "next_container", "hops")


@query("backward_links_recursive", _C3)
def backward_links_recursive(spark, d):
    return _c3(spark, d, strategy="sql")[2].select("path", "prev_container", "next_container", "hops")


@query("backward_links_kill", _C3 + " WHERE o_orderkey % 5 <> 0")
def backward_links_kill(spark, d):
    """With reaching definitions: a constant that is assigned ends the dependency."""
    return _c3(spark, d, kill=True)[2].select("path", "prev_container", "next_container", "hops")


# -- flows between functions ------------------------------------------------------------------------
def _flow_links(spark, **options) -> DataFrame:
    return Access(Models(corpora.flows(spark)), Options(**options)).links


@query("links_across_functions", values("app_id, prev_container, next_container", "('returned', 'customers', 'orders')", "('passed', 'customers', 'orders')", "('held', 'customers', 'orders')", "('held', 'orders', 'parts')"))
def links_across_functions(spark, d):
    """Results that are passed to functions or returned by them; what goes through ``apart``'s helper from one caller doesn't
    reach the other."""
    return _flow_links(spark).where("prev_path = path").select("app_id", "prev_container", "next_container")


@query("links_across_files", values("prev_path, path, prev_container, next_container", "('main.js', 'lib.js', 'customers', 'orders')"))
def links_across_files(spark, d):
    return _flow_links(spark).where("prev_path <> path").select("prev_path", "path", "prev_container", "next_container")


@query("links_across_files_orders", "SELECT 'o' || o_orderkey || '.js' AS prev_path, 'lib.js' AS path, 'orders' AS prev_container, 'customers' AS next_container FROM orders")
def links_across_files_orders(spark, d):
    """Every order's file asks for its customer through the helper file of its program."""
    m = Models(corpora.helper_snippets(spark, d))
    return access.backward_links(m, written(access.find_operations(m), "ops")).select("prev_path", "path", "prev_container", "next_container")


@query("plans_across_functions", values("app_id, host, referenced, fields", "('returned', 'customers', 'orders', 'status')", "('passed', 'customers', 'orders', 'status')", "('held', 'orders', 'parts', 'name')", "('files', 'customers', 'orders', 'status')"))
def plans_across_functions(spark, d):
    return joins.removal_plans(Access(Models(corpora.flows(spark)))).select("app_id", "host", "referenced", F.array_join("fields", ",").alias("fields"))


@query("container_by_parameter", values("container, kind", "('customers', 'R')", "('orders', 'R')"))
def container_by_parameter(spark, d):
    """Containers that callers name."""
    return access.find_operations(Models(corpora.flows(spark))).where("app_id = 'named'").select("container", "kind")


@query("strategies_agree", values("options, strategy, path, prev_op, next_op, hops", "('none', 'none', 'none', CAST(0 AS BIGINT), CAST(0 AS BIGINT), 0)") + " WHERE false")
def strategies_agree(spark, d):
    """Links that one way of walking finds and the kernel doesn't, or the other way round, under all options: none."""
    m = Models(corpora.micro(spark).unionByName(corpora.flows(spark)).unionByName(corpora.walks(spark)).unionByName(corpora.backend(spark)))
    ops, out = written(access.find_operations(m), "ops"), []
    columns = ["app_id", "path", "prev_path", "prev_op", "next_op", "hops", "via_var"]
    for kill in (False, True):
        for walk in ("all_paths", "linear"):
            one = written(access.backward_links(m, ops, Options(kill=kill, walk=walk)).select(*columns), "kernel")
            for strategy in ("relational",) if kill else ("relational", "sql"):
                other = written(access.backward_links(m, ops, Options(kill=kill, walk=walk, strategy=strategy)).select(*columns), strategy)
                differ = one.exceptAll(other).unionByName(other.exceptAll(one))
                out.append(differ.select(F.lit(f"kill={kill},walk={walk}").alias("options"), F.lit(strategy).alias("strategy"), "path", "prev_op", "next_op", "hops"))
    return reduce(DataFrame.unionByName, out)


@query("walk_options", values("kill, walk, path, n", *[f"({str(k).lower()}, '{w}', '{p}', CAST({n} AS BIGINT))" for k, w, p, n in (
    (False, "all_paths", "loop.js", 0), (False, "all_paths", "ended.js", 1), (False, "all_paths", "maybe.js", 2), (False, "all_paths", "chain.js", 1), (False, "all_paths", "again.js", 3),
    (False, "linear", "branches.js", 1), (False, "linear", "ended.js", 1), (False, "linear", "maybe.js", 2), (False, "linear", "chain.js", 1), (False, "linear", "again.js", 3),
    (True, "all_paths", "maybe.js", 2), (True, "all_paths", "chain.js", 1), (True, "all_paths", "again.js", 2),
    (True, "linear", "branches.js", 1), (True, "linear", "maybe.js", 2), (True, "linear", "chain.js", 1), (True, "linear", "again.js", 2)) if n]))
def walk_options(spark, d):
    """Links by options: exclusive branches, loops, assignments that end what a variable held, for sure or perhaps."""
    m = Models(corpora.walks(spark))
    ops = written(access.find_operations(m), "ops")
    return reduce(DataFrame.unionByName, [access.backward_links(m, ops, Options(kill=k, walk=w)).groupBy("path").agg(F.count("*").alias("n")).select(F.lit(k).alias("kill"), F.lit(w).alias("walk"), "path", "n") for k in (False, True) for w in ("all_paths", "linear")])


def _one_file(spark, text: str) -> DataFrame:
    return spark.createDataFrame([("t", 1, "t.js", text, "", "js")], "app_id string, version int, path string, content string, sha string, lang string")


@query("references_natural_key", values("holder, field, referenced, referenced_field, reverse", "('c', 'code', 'd', 'code', false)", "('c', 'kinds', 'e', 'kind', false)"))
def references_natural_key(spark, d):
    """References to a field other than the identifier, asked for by equality and by a lookup stage."""
    text = "async function f(db) { const a = await db.collection('c').findOne({}); const b = await db.collection('d').findOne({ code: a.code }); use(a.x, b.y); } async function g(db) { const r = await db.collection('c').aggregate([{ $lookup: { from: 'e', localField: 'kinds', foreignField: 'kind', as: 'es' } }]).toArray(); return r.map(x => x.n + x.es.map(e => e.m)); }"
    return Access(Models(_one_file(spark, text))).refs.select("holder", "field", "referenced", "referenced_field", "reverse")


@query("references_two_conditions", values("holder, holder_field, key_field, conditions", "('c', 'x', '_id', 'c.x = d._id;c.y = d.region')"))
def references_two_conditions(spark, d):
    """A join with two conditions: the plan follows the one on the identifier and lists both."""
    text = "async function f(db) { const a = await db.collection('c').findOne({}); const b = await db.collection('d').findOne({ region: a.y, _id: a.x }); use(a.n, b.m); }"
    return joins.removal_plans(Access(Models(_one_file(spark, text)))).select("holder", "holder_field", "key_field", F.array_join("conditions", ";").alias("conditions"))


@query("flow_edges_across_files", values("path, dst_path, kind", "('main.js', 'lib.js', 'call')", "('lib.js', 'main.js', 'return')"))
def flow_edges_across_files(spark, d):
    m = Models(corpora.flows(spark).where("app_id = 'files'"))
    return models.flow_edges(m).where("path <> dst_path").select("path", "dst_path", "kind")


@query("reachable_across_files", values("reached", "('lib.js')", "('main.js')"))
def reachable_across_files(spark, d):
    """Files that the walk from the caller's function enters."""
    m = Models(corpora.flows(spark).where("app_id = 'files'"))
    start = models.flow_nodes(m).where("kind = 'start' and path = 'main.js' and unit = 1")
    return models.reachable(models.flow_edges(m), start).select(F.col("dst_path").alias("reached")).distinct()


@query("callback_order", values("callbacks, n", "('nested', CAST(2 AS BIGINT))"))
def callback_order(spark, d):
    """Edges between a call and its callback: taken as what comes next, or left out."""
    m = Models(_one_file(spark, corpora.MICRO["callback"]))
    return reduce(DataFrame.unionByName, [models.flow_edges(m, c).where("kind in ('call', 'return')").agg(F.count("*").alias("n")).select(F.lit(c).alias("callbacks"), "n") for c in ("nested", "skip")]).where("n > 0")


@query("loop_edges", values("kind, n", "('next', CAST(5 AS BIGINT))", "('back', 1)"))
def loop_edges(spark, d):
    return models.flow_edges(Models(_one_file(spark, corpora.MICRO["while"]))).groupBy("kind").agg(F.count("*").alias("n"))


@query("export_graph", values("line", *[f"""('  "t.js:{a}" -> "t.js:{b}" [label="{k}"];')""" for a, b, k in ((0, 1, "true"), (0, 2, "false"), (-1, 0, "next"), (1, 3, "next"), (2, 3, "next"), (3, -2, "next"))]))
def export_graph(spark, d):
    return models.export_graph(Models(_one_file(spark, "if (a > 1) { b(); } else { c(); } e();")), "dot").select("line")


@query("operation_chains", values("container, prev_container", "('customers', NULL)", "('orders', 'customers')"))
def operation_chains(spark, d):
    a = _running(spark)
    c = access.operation_chains(a.ops)
    return c.join(c.select(*KEY, F.col("op").alias("prev"), F.col("container").alias("prev_container")), [*KEY, "prev"], "left").select("container", "prev_container")


@query("list_statements", values("line, kind, container, text", "(5, 'R', 'customers', 'db.collection(''customers'').findOne({ mail: mail })')", "(6, 'R', 'orders', 'db.collection(''orders'').findOne({ _id: member.recent.order_id })')"))
def list_statements(spark, d):
    return access.list_statements(_running(spark)).select("line", "kind", "container", "text")


@query("ops_in_block_range", values("container, n_blocks", "('customers', CAST(2 AS BIGINT))", "('d', 2)", "('e', 3)"))
def ops_in_block_range(spark, d):
    """How many blocks enclose each operation: the spans of blocks are joined with places."""
    text = "use(0); async function f(db, q) { use(1); await db.collection('customers').findOne({}); await db.collection('d').findOne({}); if (q) { use(2); await db.collection('e').findOne({}); use(3); } use(4); } use(5);"
    a = Access(Models(_one_file(spark, text)))
    n = access.ops_in_block_range(a).groupBy(*KEY, "op").agg(F.count("*").alias("n_blocks"))
    return n.join(a.ops.select(*KEY, "op", "container"), [*KEY, "op"]).select("container", "n_blocks")


@query("asof_definition", "SELECT 'o' || o_orderkey || '.js' AS path, CAST(o_orderkey % 4 + 1 AS BIGINT) AS n FROM orders")
def asof_definition(spark, d):
    """Places that give what uses of ``order`` and its aliases read: one for each of the k + 1 names, whether its declaration or
    the constant that it is given later."""
    m = Models(corpora.order_snippets(spark, d))
    given = m.aliases.select(*KEY, F.col("seq").alias("defined"), "lhs")
    found = access.asof_definition(m).where("root like 'order@%' or root rlike '^a[0-9]@'").select(*KEY, "defined").distinct()
    return found.join(given, [*KEY, "defined"]).groupBy("path").agg(F.countDistinct("defined").alias("n"))


@query("op_chain_depth", "SELECT depth, count(*) AS n FROM (SELECT unnest([0, 1]) AS depth, o_orderkey FROM orders) GROUP BY depth")
def op_chain_depth(spark, d):
    return access.chain_depth(_c3(spark, d)[2]).groupBy("depth").agg(F.count("*").alias("n"))


@query("co_used_fields", "SELECT 'o' || o_orderkey || '.js' AS path, 'name' AS field FROM orders WHERE o_orderkey % 3 = 0")
def co_used_fields(spark, d):
    """Fields to duplicate where use in one statement is asked for."""
    a = Access(Models(corpora.order_snippets(spark, d)))
    return joins.duplication_fields(a, Options(co_use="statement")).select("path", "field")


@query("references_by_code_orders", "SELECT count(*) AS n, 'orders' AS holder, 'customer' AS field, 'customers' AS referenced FROM orders")
def references_by_code_orders(spark, d):
    a = Access(Models(corpora.order_snippets(spark, d)))
    return a.refs.groupBy("holder", "field", "referenced").agg(F.count("*").alias("n"))


@query("next_statement_edges", "SELECT CAST(6 + o_orderkey % 4 + CASE WHEN o_orderkey % 5 = 0 THEN 1 ELSE 0 END + CASE WHEN o_orderkey % 3 = 0 THEN 1 ELSE 2 END AS BIGINT) AS n_nodes, count(*) AS n_files FROM orders GROUP BY 1")
def next_statement_edges(spark, d):
    n = Models(corpora.order_snippets(spark, d)).nodes.where("unit = 1").groupBy("path").agg(F.count("*").alias("n_nodes"))
    return n.groupBy("n_nodes").agg(F.count("*").alias("n_files"))


# -- running example and backend -----------------------------------------------------------------
def _running(spark) -> Access:
    return Access(Models(corpora.running_example(spark)))


def _backend(spark, **options) -> Access:
    return Access(Models(corpora.backend(spark)), Options(**options))


@query("access_model_running", values("kind, container, is_join", "('R', 'customers', false)", "('R', 'orders', true)"))
def access_model_running(spark, d):
    a = _running(spark)
    j = a.joins.select(*KEY, F.col("next_op").alias("op"), F.lit(True).alias("is_join"))
    return a.ops.join(j, [*KEY, "op"], "left").select("kind", "container", F.coalesce("is_join", F.lit(False)).alias("is_join"))


@query("fields_running", values("container, field, type_kind, prim_type", "('customers', 'acctbal', 'attribute', 'double')", "('customers', 'mail', 'attribute', 'string')", "('customers', 'mktsegment', 'attribute', 'string')", "('customers', 'name', 'attribute', 'string')", "('customers', 'recent', 'aggregate', NULL)", "('customers', 'recent.channel', 'attribute', 'string')", "('customers', 'recent.order_id', 'attribute', 'string')", "('orders', '_id', 'attribute', 'string')", "('orders', 'priority', 'attribute', 'string')"))
def fields_running(spark, d):
    return _running(spark).fields().select("container", "field", "type_kind", "prim_type")


@query("trace_running", values("step, subject, \"update\"", "(1, 'running', 'create empty')", "(2, 'customers', 'create R')", "(2, 'orders', 'create R')", "(3, 'orders', 'join with customers')", "(4, 'customers', 'container and structure')", "(4, 'orders', 'container and structure')", *[f"(5, 'customers.{f}', '{t}')" for f, t in (("acctbal", "double"), ("mail", "string"), ("mktsegment", "string"), ("name", "string"))], "(6, 'customers.recent', 'aggregate')", "(6, 'customers.recent.channel', 'string')", "(6, 'customers.recent.order_id', 'string')", "(7, 'orders._id', 'string')", "(7, 'orders.priority', 'string')", "(8, 'customers.recent.order_id', 'orders._id')"))
def trace_running(spark, d):
    return access.trace(_running(spark)).select("step", "subject", "update")


_REWRITTEN = [
    "const { open } = require(''./connection'');", "", "async function loyaltyCard(mail) {", "  const db = await open(''shop'');", "  const member = await db.collection(''customers'').findOne({ mail: mail });",
    "  const lines = [];", "  if (member.recent.channel === ''web'') {", "    lines.push(`${member.recent.order_priority} / ${member.recent.channel}`);", "  } else {", "    lines.push(member.mktsegment);", "  }",
    "  return lines.concat(member.name, member.acctbal * 0.01);", "}", "",
]


@query("rewrite_code_running", values("line, text", *[f"({i}, '{x}')" for i, x in enumerate(_REWRITTEN)]))
def rewrite_code_running(spark, d):
    """The lines of the example after its join is removed."""
    a = _running(spark)
    new = rewrite.apply_to_code(a.m.files, joins.removal_plans(a), a.ops).where("not review")
    return new.select(F.posexplode(F.split("content", "\n")).alias("line", "text"))


@query("rewrite_running_again", values("n_joins, container, field", "(CAST(0 AS BIGINT), 'customers', 'recent.order_priority')"))
def rewrite_running_again(spark, d):
    """The rewritten example, analysed again: no join, one access to the duplicate."""
    a = _running(spark)
    new = written(rewrite.apply_to_code(a.m.files, joins.removal_plans(a), a.ops), "rewritten")
    again = Access(Models(new.withColumn("sha", F.sha2("content", 256))))
    return again.joins.agg(F.count("*").alias("n_joins")).crossJoin(again.fields().where("field = 'recent.order_priority'").select("container", "field"))  # one row each


@query("join_queries_backend", values("path, host, referenced, join_type", "('customers.js', 'customers', 'orders', 'sequential')", "('customers.js', 'customers', 'parts', 'sequential')", "('orders.js', 'orders', 'parts', 'sequential')", "('reports.js', 'orders', 'customers', 'pipeline')", "('reports.js', 'orders', 'suppliers', 'pipeline')", "('reports.js', 'parts', 'orders', 'pipeline')", "('reports.js', 'parts', 'customers', 'pipeline')", "('reports.js', 'parts', 'suppliers', 'pipeline')"))
def join_queries_backend(spark, d):
    return _backend(spark).joins.select("path", "host", "referenced", "join_type")


@query("references_backend", values("holder, field, referenced", "('customers', 'orders', 'orders')", "('customers', 'parts', 'parts')", "('orders', 'items', 'parts')", "('orders', 'origins', 'suppliers')", "('parts', 'suppliers', 'suppliers')"))
def references_backend(spark, d):
    """References from code, among them two whose names say nothing."""
    return _backend(spark).refs.select("holder", "field", "referenced").distinct()


_PLANS = ("('customers', 'orders', 'orderdate', 'array')", "('customers', 'parts', 'name', 'array')", "('orders', 'customers', 'name', 'plain')", "('orders', 'parts', 'name', 'array')", "('orders', 'suppliers', 'name', 'array')", "('parts', 'orders', 'orderdate,priority', 'array_of_struct')", "('parts', 'customers', 'name', 'array')", "('parts', 'suppliers', 'name', 'array')")


@query("removal_plans_backend", values("host, referenced, fields, shape", *_PLANS))
def removal_plans_backend(spark, d):
    return joins.removal_plans(_backend(spark)).select("host", "referenced", F.array_join("fields", ",").alias("fields"), "shape")


@query("plan_usage_backend", values("referenced, n_plans, n_updates", "('orders', CAST(2 AS BIGINT), CAST(3 AS BIGINT))", "('parts', 2, 3)", "('customers', 2, 3)", "('suppliers', 2, 3)"))
def plan_usage_backend(spark, d):
    p = joins.removal_plans(_backend(spark))
    return p.groupBy("referenced").agg(F.count("*").alias("n_plans"), F.max("n_updates_referenced").alias("n_updates"))


# uses of the join in code less updates of the referenced container: 1 - 3 for plans of one field, 2 - 3 for the one of two
@query("topk_plans", values("rank, host, referenced", "(1, 'parts', 'orders')", "(2, 'customers', 'orders')", "(3, 'customers', 'parts')"))
def topk_plans(spark, d):
    return joins.rank_plans(joins.removal_plans(_backend(spark))).where("rank <= 3").select("rank", "host", "referenced")


@query("rank_under_trace", _C2 + """, n AS (SELECT container, sum(CASE WHEN kind = 'R' THEN 1 ELSE 0 END) AS r, sum(CASE WHEN kind <> 'R' THEN 1 ELSE 0 END) AS w FROM o GROUP BY container),
p AS (SELECT * FROM (VALUES ('customers', 'orders'), ('customers', 'parts'), ('orders', 'customers'), ('orders', 'parts'), ('orders', 'suppliers'), ('parts', 'orders'), ('parts', 'customers'), ('parts', 'suppliers')) AS t(host, referenced))
SELECT host, referenced, CAST(coalesce(a.r, 0) AS DOUBLE) AS benefit, CAST(coalesce(b.w, 0) AS DOUBLE) AS update_cost FROM p LEFT JOIN n a ON a.container = host LEFT JOIN n b ON b.container = referenced""")
def rank_under_trace(spark, d):
    """Benefit and cost of the backend's plans under the operations that the event trace runs."""
    trace = _c2_ops(spark, d).groupBy("container", "kind").agg(F.count("*").alias("n"))
    return joins.rank_plans(joins.removal_plans(_backend(spark)), workload=trace).select("host", "referenced", F.col("benefit").cast("double").alias("benefit"), F.col("update_cost").cast("double").alias("update_cost"))


@query("aggregate_candidates", values("host, referenced, n_joins", *[f"({p.split(', ')[0][1:]}, {p.split(', ')[1]}, CAST(1 AS BIGINT))" for p in _PLANS]))
def aggregate_candidates(spark, d):
    return joins.aggregate_candidates(_backend(spark)).select("host", "referenced", "n_joins")


@query("copy_operations", values("operation", *[f"('{x}')" for x in (
    "duplicate orders(orderdate) as order_orderdate in customers where orders._id = customers.orders", "duplicate parts(name) as part_name in customers where parts._id = customers.parts",
    "duplicate parts(name) as part_name in orders where parts._id = orders.items", "duplicate suppliers(name) as supplier_name in orders where suppliers._id = orders.origins",
    "duplicate customers(name) as customer_name in orders where customers.orders contains orders._id", "duplicate orders(orderdate, priority) as order_orderdate, order_priority in parts where orders.items contains parts._id",
    "duplicate customers(name) as customer_name in parts where customers.parts contains parts._id", "duplicate suppliers(name) as supplier_name in parts where suppliers._id = parts.suppliers")]))
def copy_operations(spark, d):
    return joins.copy_operation(joins.removal_plans(_backend(spark))).select("operation")


@query("operation_recall", values("n_methods, n_sites, n_rows", "(CAST(28 AS BIGINT), CAST(31 AS BIGINT), CAST(36 AS BIGINT))"))
def operation_recall(spark, d):
    """Methods with access, call sites and operation rows of the backend."""
    a = _backend(spark)
    units = a.m.units.where("kind = 'function'").agg(F.count("*").alias("n_methods"))
    return units.crossJoin(a.ops.agg(F.sum((~F.col("synthetic")).cast("long")).alias("n_sites"), F.count("*").alias("n_rows")))  # one row each


@query("corpus_scope", values("n_files, n_functions, n_ops, n_r, n_i, n_u, n_d", "(CAST(5 AS BIGINT), CAST(28 AS BIGINT), CAST(31 AS BIGINT), CAST(19 AS BIGINT), CAST(4 AS BIGINT), CAST(4 AS BIGINT), CAST(4 AS BIGINT))"))
def corpus_scope(spark, d):
    a = _backend(spark)
    return measure.corpus_scope(a.m, a.ops).drop("n_lines")


_SHOP = [
    ("customers", "_id", "key", "string", "one", None), ("customers", "name", "attribute", "string", "one", None), ("customers", "acctbal", "attribute", "double", "one", None), ("customers", "mktsegment", "attribute", "string", "one", None), ("customers", "nation", "attribute", "long", "one", None), ("customers", "orders", "reference", "array<string>", "many", "orders"), ("customers", "parts", "reference", "array<string>", "many", "parts"),
    ("orders", "_id", "key", "string", "one", None), ("orders", "status", "attribute", "string", "one", None), ("orders", "totalprice", "attribute", "double", "one", None), ("orders", "orderdate", "attribute", "string", "one", None), ("orders", "priority", "attribute", "string", "one", None), ("orders", "items", "reference", "array<string>", "many", "parts"), ("orders", "origins", "reference", "array<string>", "many", "suppliers"), ("orders", "summary", "aggregate", "struct", "one", "orders.summary"), ("orders.summary", "n_lines", "attribute", "long", "one", None), ("orders.summary", "total_qty", "attribute", "double", "one", None),
    ("parts", "_id", "key", "string", "one", None), ("parts", "name", "attribute", "string", "one", None), ("parts", "brand", "attribute", "string", "one", None), ("parts", "type", "attribute", "string", "one", None), ("parts", "size", "attribute", "long", "one", None), ("parts", "retailprice", "attribute", "double", "one", None), ("parts", "suppliers", "reference", "array<string>", "many", "suppliers"), ("parts", "summary", "aggregate", "struct", "one", "parts.summary"), ("parts.summary", "n_lines", "attribute", "long", "one", None), ("parts.summary", "total_qty", "attribute", "double", "one", None),
    ("suppliers", "_id", "key", "string", "one", None), ("suppliers", "name", "attribute", "string", "one", None), ("suppliers", "acctbal", "attribute", "double", "one", None), ("suppliers", "nation", "attribute", "long", "one", None),
]
_text = lambda x: "NULL" if x is None else f"'{x}'"


@query("logical_schema_shop", values("entity, feature, kind, type, upper, target", *[f"({', '.join(map(_text, r))})" for r in _SHOP]))
def logical_schema_shop(spark, d):
    return logical.to_logical(_backend(spark)).select("entity", "feature", "kind", "type", "upper", "target")


@query("score_schema", values("kind, n_right, n_found, n_true, precision, recall, f1", *[f"('{k}', CAST({n} AS BIGINT), CAST({n} AS BIGINT), CAST({n} AS BIGINT), 1.0::DOUBLE, 1.0::DOUBLE, 1.0::DOUBLE)" for k, n in (("all", len(_SHOP)), *((k, sum(r[2] == k for r in _SHOP)) for k in ("attribute", "reference", "aggregate", "key")))]))
def score_schema(spark, d):
    """The round trip: inferred features against the intended ones."""
    return measure.score_schema(logical.to_logical(_backend(spark)), logical.declare_schema(spark, _SHOP))


@query("determined_types", values("entity, n_attributes, n_determined", "('customers', CAST(4 AS BIGINT), CAST(2 AS BIGINT))", "('orders', 4, 1)", "('orders.summary', 2, 2)", "('parts', 5, 2)", "('parts.summary', 2, 2)", "('suppliers', 3, 2)"))
def determined_types(spark, d):
    return measure.determined_types(logical.to_logical(_backend(spark))).select("entity", "n_attributes", "n_determined")


@query("schema_diff_plans", values("entity, feature, change", "('customers', 'order_orderdate', 'added')", "('customers', 'part_name', 'added')", "('orders', 'customer_name', 'added')", "('orders', 'part_name', 'added')", "('orders', 'supplier_name', 'added')", "('parts', 'order_orderdate', 'added')", "('parts', 'order_priority', 'added')", "('parts', 'customer_name', 'added')", "('parts', 'supplier_name', 'added')"))
def schema_diff_plans(spark, d):
    """What applying all plans adds to the schema."""
    a = _backend(spark)
    s = written(logical.to_logical(a), "schema")
    return logical.schema_diff(s, joins.apply_to_schema(s, joins.removal_plans(a))).select("entity", "feature", "change")


@query("paper_options_backend", values("n_links, n_plans", "(CAST(3 AS BIGINT), CAST(4 AS BIGINT))"))
def paper_options_backend(spark, d):
    """The reading that keeps to the printed procedures: without aliases and blocks half of the plans are missed."""
    a = Access(Models(corpora.backend(spark)), paper_options())
    return a.links.agg(F.count("*").alias("n_links")).crossJoin(joins.removal_plans(a).agg(F.count("*").alias("n_plans")))  # one row each


@query("merge_structures", values("container, version, kept_as, kept", "('c', 1, 'c@1', true)", "('c', 2, 'c@1', false)", "('c', 3, 'c@3', true)", "('e', 1, 'e@1', true)"))
def merge_structures(spark, d):
    """Three versions of one container, of which the second has the structure of the first, and another container with it."""
    text = lambda c, f: f"async function f(db) {{ const r = await db.collection('{c}').findOne({{}}); use({f}); }}"
    rows = [("m", 1, "a.js", text("c", "r.x, r.y")), ("m", 2, "a.js", text("c", "r.y, r.x")), ("m", 3, "a.js", text("c", "r.x")), ("m", 1, "b.js", text("e", "r.x, r.y"))]
    files = spark.createDataFrame([(*r, r[3], "js") for r in rows], "app_id string, version int, path string, content string, sha string, lang string")
    return Access(Models(files)).structures().select("container", "version", "kept_as", "kept")


_CATALOG = """
SELECT table_name AS entity, column_name AS feature,
  CASE WHEN data_type IN ('BIGINT', 'INTEGER') THEN 'long' WHEN data_type = 'DOUBLE' THEN 'double' WHEN data_type LIKE '%[]' THEN 'array<double>' ELSE 'string' END AS type
FROM information_schema.columns
WHERE table_name IN (""" + ", ".join(f"'{t}'" for t in TABLES) + ")"


@query("logical_schema_catalog", _CATALOG)
def logical_schema_catalog(spark, d):
    """Schemas of modules that touch every column of a table."""
    return logical.to_logical(Access(Models(corpora.catalog_modules(spark, d)))).select("entity", "feature", "type")


@query("render_ddl", values("entity, line", "('customers', '_id string, acctbal double, mktsegment string, name string, nation bigint, orders array<string>, parts array<string>')", "('orders', '_id string, items array<string>, orderdate string, origins array<string>, priority string, status string, summary struct<n_lines: bigint, total_qty: double>, totalprice double')", "('orders.summary', 'n_lines bigint, total_qty double')", "('parts', '_id string, brand string, name string, retailprice double, size bigint, summary struct<n_lines: bigint, total_qty: double>, suppliers array<string>, type string')", "('parts.summary', 'n_lines bigint, total_qty double')", "('suppliers', '_id string, acctbal double, name string, nation bigint')"))
def render_ddl(spark, d):
    return logical.render(logical.to_logical(_backend(spark)), "ddl").select("entity", "line")


def _declared(rows: DataFrame, *features: tuple) -> DataFrame:
    """A schema for each row's ``app_id``: features (when, entity, feature, kind, type, upper, target), in SQL over the row."""
    names = ("entity", "feature", "kind", "type", "upper", "target")
    return reduce(DataFrame.unionByName, [rows.where(when).select(F.col("app_id").cast("string").alias("app_id"), *[F.expr(x).cast("string").alias(n) for n, x in zip(names, f, strict=True)]) for when, *f in features])


@query("relationship_types", "SELECT CAST(p_partkey AS VARCHAR) AS app_id, 'lineitem' AS entity, CAST(2 + p_size % 2 AS BIGINT) AS n_refs FROM part WHERE p_size % 5 <> 0")
def relationship_types(spark, d):
    """Of a schema declared for each part, the entity that only links others; in every fifth size another one refers to it."""
    p = read_table(spark, d, "part").select(F.col("p_partkey").alias("app_id"), "p_size")
    refer = lambda when, entity, field, to: (when, f"'{entity}'", f"'{field}'", "'reference'", "'long'", "'one'", f"'{to}'")
    schema = _declared(
        p, refer("true", "lineitem", "l_orderkey", "orders"), refer("true", "lineitem", "l_partkey", "part"), refer("p_size % 2 = 1", "lineitem", "l_suppkey", "supplier"), refer("true", "orders", "o_custkey", "customer"),
        refer("p_size % 5 = 0", "returns", "r_linekey", "lineitem"), ("true", "'customer'", "'c_custkey'", "'key'", "'long'", "'one'", "null"),
    )
    return logical.relationship_types(schema).select("app_id", "entity", "n_refs")


@query("schema_intersect", "SELECT p_brand AS entity, 'f' || p_partkey AS feature FROM part WHERE p_size % 3 = 2")
def schema_intersect(spark, d):
    return logical.schema_intersect(*_two_schemas(spark, d)).select("entity", "feature")


@query("schema_except", "SELECT p_brand AS entity, 'f' || p_partkey AS feature FROM part WHERE p_size % 3 <> 2")
def schema_except(spark, d):
    return logical.schema_except(*_two_schemas(spark, d)).select("entity", "feature")


def _two_schemas(spark, d) -> tuple[DataFrame, DataFrame]:
    """A feature a part; the second schema has those of every third size as doubles, lacks those of the next, and adds some."""
    p = read_table(spark, d, "part").select(F.lit("declared").alias("app_id"), "p_brand", F.col("p_partkey").alias("k"), "p_size")
    a = _declared(p, ("true", "p_brand", "concat('f', k)", "'attribute'", "'long'", "'one'", "null"))
    b = _declared(p, ("p_size % 3 <> 1", "p_brand", "concat('f', k)", "'attribute'", "if(p_size % 3 = 0, 'double', 'long')", "'one'", "null"), ("true", "p_brand", "concat('g', k)", "'attribute'", "'string'", "'one'", "null"))
    return a, b


@query("score_rollup", values("kind, entity, n_right, n_found, n_true", *[f"('{k}', '{e}', CAST({n} AS BIGINT), CAST({n} AS BIGINT), CAST({n} AS BIGINT))" for k, e, n in (("*", "*", len(_SHOP)), *((k, "*", sum(r[2] == k for r in _SHOP)) for k in ("attribute", "reference", "aggregate", "key")), *sorted({(r[2], r[0], sum(x[2] == r[2] and x[0] == r[0] for x in _SHOP)) for r in _SHOP}))]))
def score_rollup(spark, d):
    return measure.score_rollup(logical.to_logical(_backend(spark)), logical.declare_schema(spark, _SHOP))


_BOTH = [(e, f) for e, f, *_ in _SHOP if e in ("customers", "orders", "parts", "suppliers") or e.endswith("summary")]


@query("code_data_agreement", values("entity, feature, found, agree", *[f"('{e}', '{f}', 'both', {'true' if (e, f) in {('customers', 'acctbal'), ('customers', 'nation'), ('orders', 'totalprice'), ('orders.summary', 'n_lines'), ('orders.summary', 'total_qty'), ('parts', 'size'), ('parts', 'retailprice'), ('parts.summary', 'n_lines'), ('parts.summary', 'total_qty'), ('suppliers', 'acctbal'), ('suppliers', 'nation')} else 'NULL'})" for e, f in _BOTH], "('orders', 'customer', 'data', NULL)"))
def code_data_agreement(spark, d):
    """The schema from the backend's code against the one from the data: every feature in both but ``orders.customer``, which no
    code reads; types agree wherever code shows one."""
    frames = {k: shop.COLLECTIONS[k](spark, d) for k in ("customers", "orders", "parts", "suppliers")}
    return measure.code_data_agreement(logical.to_logical(_backend(spark)), profile.profile_schema(frames, exact=False)).select("entity", "feature", "found", "agree")


@query("distinct_fields", "SELECT CAST(sum(n) AS BIGINT) AS n_fields FROM (SELECT count(*) AS n FROM information_schema.columns WHERE table_name IN (" + ", ".join(f"'{t}'" for t in TABLES) + "))")
def distinct_fields(spark, d):
    return access.distinct_fields(Access(Models(corpora.catalog_modules(spark, d))).fields(), exact=True).select("n_fields")


@query("path_prefixes", values("prefix, n", "('name', CAST(1 AS BIGINT))", "('recent', 3)", "('recent.channel', 2)", "('recent.order_id', 1)", "('mktsegment', 1)", "('acctbal', 1)"))
def path_prefixes(spark, d):
    return access.path_prefixes(_running(spark).reads.where("container = 'customers'")).select("prefix", "n")


@query("overloaded_entities", "SELECT entity, CAST(n AS BIGINT) AS n_fields FROM (SELECT entity, n, percent_rank() OVER (ORDER BY n) AS r FROM (SELECT table_name AS entity, count(*) AS n FROM information_schema.columns WHERE table_name IN (" + ", ".join(f"'{t}'" for t in TABLES) + ") GROUP BY 1)) WHERE round(r, 6) >= 0.9")
def overloaded_entities(spark, d):
    return logical.overloaded_entities(logical.to_logical(Access(Models(corpora.catalog_modules(spark, d))))).select("entity", "n_fields")


# -- data baselines ------------------------------------------------------------------------------
@query("profile_types", _CATALOG.replace("'long'", "'bigint'").replace("'array<double>'", "'array<float>'").replace("WHEN data_type IN ('BIGINT', 'INTEGER') THEN 'bigint'", "WHEN data_type = 'BIGINT' THEN 'bigint' WHEN data_type = 'INTEGER' THEN 'int' WHEN data_type LIKE 'TIMESTAMP%' THEN 'timestamp_ntz'"))
def profile_types(spark, d):
    return profile.profile_schema(_tables(spark, d), exact=False).select("entity", "feature", "type")


@query("profile_cardinalities", """
WITH l AS (SELECT l_orderkey AS k, count(DISTINCT l_partkey) AS n, count(*) AS m FROM lineitem GROUP BY 1), o AS (SELECT o_orderkey, coalesce(n, 0) AS n, m FROM orders LEFT JOIN l ON k = o_orderkey)
SELECT 'items' AS feature, CAST(min(n) AS INTEGER) AS lower, CAST(max(n) AS INTEGER) AS upper FROM o
UNION ALL SELECT 'summary', CASE WHEN count(m) < count(*) THEN 0 ELSE 1 END, 1 FROM o""")
def profile_cardinalities(spark, d):
    return profile.profile_collection(shop.orders(spark, d), "orders").where("feature in ('items', 'summary')").select("feature", "lower", "upper")


@query("data_variations", "SELECT 'k' AS structure, count(*) AS n, 1 AS variation FROM events")
def data_variations(spark, d):
    return profile.data_variations(read_table(spark, d, "events"), "props")


@query("data_variations_docs", "SELECT CASE WHEN l.doc_id IS NULL THEN '_id,lang,n_chars,source' ELSE '_id,label,lang,n_chars,source' END AS structure, count(*) AS n FROM documents d LEFT JOIN labels l USING (doc_id) GROUP BY 1")
def data_variations_docs(spark, d):
    return profile.data_variations(shop.docs(spark, d)).select("structure", "n")


_INTS = ("nation.n_regionkey", "customer.c_nationkey", "supplier.s_nationkey", "orders.o_custkey", "lineitem.l_orderkey", "lineitem.l_partkey", "lineitem.l_suppkey", "labels.doc_id", "events.user_id")


@query("references_by_name", values("holder, field, referenced", "('nation', 'n_regionkey', 'region')", "('customer', 'c_nationkey', 'nation')", "('supplier', 's_nationkey', 'nation')", "('lineitem', 'l_orderkey', 'orders')", "('lineitem', 'l_partkey', 'part')", "('embeddings', 'label', 'labels')"))
def references_by_name(spark, d):
    """The baseline by names on the tables: abbreviated and renamed references stay unfound."""
    return profile.references_by_name(profile.catalog(_tables(spark, d)))


@query("references_by_name_shop", values("holder, field, referenced", "('customers', 'orders', 'orders')", "('customers', 'parts', 'parts')", "('parts', 'suppliers', 'suppliers')", "('orders', 'customer', 'customers')"))
def references_by_name_shop(spark, d):
    """The same on the shop: ``items`` and ``origins`` are missed, which code analysis finds."""
    return profile.references_by_name(profile.catalog({n: f(spark, d) for n, f in shop.COLLECTIONS.items()}))


def _inclusion_sql() -> str:
    ints = {"region": ["r_regionkey"], "nation": ["n_nationkey", "n_regionkey"], "customer": ["c_custkey", "c_nationkey"], "supplier": ["s_suppkey", "s_nationkey"], "part": ["p_partkey", "p_size"], "orders": ["o_orderkey", "o_custkey"], "lineitem": ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber"], "events": ["event_id", "user_id"], "documents": ["doc_id", "n_chars"], "embeddings": ["vec_id", "label"], "pages": ["page_id"], "benchmark": ["item_id"], "labels": ["doc_id", "quality", "toxic"], "conversations": ["conv_id", "turn"]}
    union = " UNION ALL ".join(f"SELECT '{t}' AS t, '{t}.{c}' AS c, CAST({c} AS BIGINT) AS v FROM {t}" for t, cs in ints.items() for c in cs)
    return f"""
WITH v AS ({union}), d AS (SELECT t, c, v, count(*) AS n FROM v WHERE v IS NOT NULL GROUP BY ALL),
s AS (SELECT t, c, count(*) AS n_values, max(n) AS most FROM d GROUP BY ALL),
h AS (SELECT a.t AS ta, a.c AS holder, b.c AS referenced, count(*) AS n_shared FROM d a JOIN d b ON a.v = b.v AND a.t <> b.t JOIN s ON s.c = b.c AND s.most = 1 GROUP BY ALL)
SELECT holder, referenced, n_values FROM h JOIN s ON s.c = h.holder WHERE n_shared = n_values"""


@query("references_by_inclusion", _inclusion_sql())
def references_by_inclusion(spark, d):
    return profile.inclusion_candidates(_tables(spark, d))


@query("reference_precision_recall", f"SELECT n_right, n_found, n_true, round(n_right / n_found, 6) AS precision, round(n_right / n_true, 6) AS recall FROM (SELECT count(*) FILTER (holder IN ({', '.join(repr(x) for x in _INTS)}) AND (holder, referenced) IN (VALUES ('nation.n_regionkey', 'region.r_regionkey'), ('customer.c_nationkey', 'nation.n_nationkey'), ('supplier.s_nationkey', 'nation.n_nationkey'), ('orders.o_custkey', 'customer.c_custkey'), ('lineitem.l_orderkey', 'orders.o_orderkey'), ('lineitem.l_partkey', 'part.p_partkey'), ('lineitem.l_suppkey', 'supplier.s_suppkey'), ('labels.doc_id', 'documents.doc_id'), ('events.user_id', 'customer.c_custkey'))) AS n_right, count(*) AS n_found, CAST(9 AS BIGINT) AS n_true FROM ({_inclusion_sql()}))")
def reference_precision_recall(spark, d):
    """Inclusion alone: every reference, and many pairs that are none, since keys are dense."""
    truth = spark.createDataFrame(list(zip(_INTS, ("region.r_regionkey", "nation.n_nationkey", "nation.n_nationkey", "customer.c_custkey", "orders.o_orderkey", "part.p_partkey", "supplier.s_suppkey", "documents.doc_id", "customer.c_custkey"), strict=True)), "holder string, referenced string")
    return measure.score_pairs(profile.inclusion_candidates(_tables(spark, d)), truth, ["holder", "referenced"])


@query("lower_bounds", "SELECT 'orders' AS entity, 'summary' AS feature, 0 AS code_lower, CASE WHEN count(DISTINCT l_orderkey) < (SELECT count(*) FROM orders) THEN 0 ELSE 1 END AS data_lower FROM lineitem")
def lower_bounds(spark, d):
    """Code can't tell lower bounds; data can."""
    s = logical.to_logical(_backend(spark)).where("entity = 'orders' and feature = 'summary'")
    return measure.lower_bounds(s, profile.profile_collection(shop.orders(spark, d), "orders")).select("entity", "feature", "code_lower", "data_lower")


# -- migration -----------------------------------------------------------------------------------
_LINES = "(SELECT DISTINCT l_orderkey, l_partkey FROM lineitem)"
_SUPP = "(SELECT DISTINCT l_orderkey, l_suppkey FROM lineitem)"
_BOUGHT = "(SELECT DISTINCT o_custkey, l_partkey FROM orders JOIN lineitem ON l_orderkey = o_orderkey)"
_SQL = {
    "j1": "SELECT o_custkey AS _id, o_orderdate AS ref_orderdate FROM orders",
    "j2": f"SELECT o_custkey AS _id, p_name AS ref_name FROM {_BOUGHT} JOIN part ON p_partkey = l_partkey",
    "j3": "SELECT o_orderkey AS _id, c_name AS ref_name FROM orders JOIN customer ON c_custkey = o_custkey",
    "j4": f"SELECT l_orderkey AS _id, p_name AS ref_name FROM {_LINES} JOIN part ON p_partkey = l_partkey",
    "j5": f"SELECT l_orderkey AS _id, s_name AS ref_name FROM {_SUPP} JOIN supplier ON s_suppkey = l_suppkey",
    "j6a": f"SELECT l_partkey AS _id, o_orderpriority AS ref_priority, o_orderdate AS ref_orderdate FROM {_LINES} JOIN orders ON o_orderkey = l_orderkey",
    "j6b": f"SELECT l_partkey AS _id, c_name AS ref_name FROM {_BOUGHT} JOIN customer ON c_custkey = o_custkey",
    "j7": "SELECT l_partkey AS _id, s_name AS ref_name FROM (SELECT DISTINCT l_partkey, l_suppkey FROM lineitem) JOIN supplier ON s_suppkey = l_suppkey",
}


_stored: dict[tuple, DataFrame] = {}


def stored(spark: SparkSession, d: str, name: str, make: Callable[[], DataFrame]) -> DataFrame:
    """A collection as the store holds it: made and written once in an application, read from then on."""
    key = (spark.sparkContext.applicationId, d, name)
    if key not in _stored:
        _stored[key] = written(make(), f"shop-{name}")
    return _stored[key]


def sides(spark, d, j: str):
    x = shop.JOINS[j]
    side = lambda name: stored(spark, d, name, lambda: shop.COLLECTIONS[name](spark, d))
    return side(x.host), side(x.referenced), x


def updated(spark, d, j: str) -> DataFrame:
    """The host with its duplicate, written once."""
    host, ref, x = sides(spark, d, j)
    return stored(spark, d, f"{j}-updated", lambda: migrate.apply_to_data(host, ref, x))


def _original(j: str, spark, d):
    host, ref, x = sides(spark, d, j)
    return migrate.run_original(host, ref, x)


def _refactored(j: str, spark, d):
    return migrate.run_refactored(updated(spark, d, j), shop.JOINS[j])


for _j in shop.JOINS:
    query(f"{_j}_original", _SQL[_j])(partial(_original, _j))
    query(f"{_j}_refactored", _SQL[_j])(partial(_refactored, _j))


@query("dup_broadcast", _SQL["j5"])
def dup_broadcast(spark, d):
    host, ref, x = sides(spark, d, "j5")
    return migrate.run_refactored(migrate.apply_to_data(host, ref, x, "broadcast"), x)


@query("dup_to_one", "SELECT o_orderkey AS _id, c_name AS name, c_mktsegment AS mktsegment FROM orders JOIN customer ON c_custkey = o_custkey")
def dup_to_one(spark, d):
    x = migrate.Duplication("orders", "customers", "customer", ("name", "mktsegment"), "customer_info")
    out = migrate.apply_to_data(shop.orders(spark, d), shop.customers(spark, d, with_arrays=False), x, "shuffle")
    return out.select("_id", "customer_info.name", "customer_info.mktsegment")


def _embedded_lines(spark, d) -> DataFrame:
    return read_table(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("_id")).agg(F.sort_array(F.collect_list(F.struct(F.col("l_partkey").alias("part"), F.col("l_quantity").cast("double").alias("qty")))).alias("lines"))


@query("nested_dup_array", "SELECT l_orderkey AS _id, l_partkey AS part, CAST(l_quantity AS DOUBLE) AS qty, p_name AS part_name FROM lineitem JOIN part ON p_partkey = l_partkey")
def nested_dup_array(spark, d):
    """Orders with their lines as embedded objects: the part's name goes into each."""
    lines = _embedded_lines(spark, d)
    x = migrate.Duplication("orders", "parts", "lines.part", ("name",), "part_name", many=True, inside="lines")
    return migrate.apply_to_data(lines, shop.parts(spark, d), x).select("_id", F.explode("lines").alias("l")).select("_id", "l.part", "l.qty", "l.part_name")


@query("verify_duplication", values("join_name, _id", "('none', CAST(1 AS BIGINT))") + " WHERE false")
def verify_duplication(spark, d):
    """Hosts of all eight updates whose duplicate is not what the reference gives: none."""
    return reduce(DataFrame.unionByName, [migrate.verify_duplication(updated(spark, d, j), sides(spark, d, j)[1], x).select(F.lit(j).alias("join_name"), "_id") for j, x in shop.JOINS.items()])


@query("check_equivalence", values("join_name, _id", "('none', CAST(1 AS BIGINT))") + " WHERE false")
def check_equivalence(spark, d):
    """Rows that only the query before or only the one after the removal gives, for all eight joins: none."""
    return reduce(DataFrame.unionByName, [migrate.check_equivalence(*sides(spark, d, j)[:2], updated(spark, d, j), x).select(F.lit(j).alias("join_name"), "_id") for j, x in shop.JOINS.items()])


@query("sync_duplicates", "SELECT o_orderkey AS _id, CASE WHEN c_custkey % 10 = 0 THEN c_name || '*' ELSE c_name END AS customer_name FROM orders JOIN customer ON c_custkey = o_custkey")
def sync_duplicates(spark, d):
    x = migrate.Duplication("orders", "customers", "customer", ("name",), "customer_name")
    c = shop.customers(spark, d, with_arrays=False)
    out = migrate.apply_to_data(shop.orders(spark, d), c, x)
    return migrate.sync_duplicates(out, c.where("_id % 10 = 0").withColumn("name", F.concat("name", F.lit("*"))), x).select("_id", "customer_name")


_changed = lambda df: df.withColumn("name", F.when(F.col("_id") % 10 == 0, F.concat("name", F.lit("*"))).otherwise(F.col("name")))


@query("sync_arrays", "SELECT l_orderkey AS _id, CASE WHEN p_partkey % 10 = 0 THEN p_name || '*' ELSE p_name END AS ref_name FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) JOIN part ON p_partkey = l_partkey")
def sync_arrays(spark, d):
    """Arrays of duplicated names after every tenth part was renamed."""
    x, parts = shop.JOINS["j4"], written(_changed(sides(spark, d, "j4")[1]), "parts-changed")
    return migrate.run_refactored(migrate.sync_duplicates(updated(spark, d, "j4"), parts.where("_id % 10 = 0"), x, parts), x)


@query("sync_reverse", "SELECT o_orderkey AS _id, CASE WHEN c_custkey % 10 = 0 THEN c_name || '*' ELSE c_name END AS ref_name FROM orders JOIN customer ON c_custkey = o_custkey")
def sync_reverse(spark, d):
    """Duplicates of what refers to the host, after every tenth customer was renamed."""
    x, customers = shop.JOINS["j3"], written(_changed(sides(spark, d, "j3")[1]), "customers-changed")
    return migrate.run_refactored(migrate.sync_duplicates(updated(spark, d, "j3"), customers.where("_id % 10 = 0"), x, customers), x)


@query("sync_embedded", "SELECT l_orderkey AS _id, l_partkey AS part, CAST(l_quantity AS DOUBLE) AS qty, CASE WHEN p_partkey % 10 = 0 THEN p_name || '*' ELSE p_name END AS part_name FROM lineitem JOIN part ON p_partkey = l_partkey")
def sync_embedded(spark, d):
    """Names inside embedded lines, after every tenth part was renamed."""
    x = migrate.Duplication("orders", "parts", "lines.part", ("name",), "part_name", many=True, inside="lines")
    before, after = shop.parts(spark, d), written(_changed(shop.parts(spark, d)), "parts-changed")
    out = migrate.sync_duplicates(written(migrate.apply_to_data(_embedded_lines(spark, d), before, x), "lines"), after.where("_id % 10 = 0"), x, after)
    return out.select("_id", F.explode("lines").alias("l")).select("_id", "l.part", "l.qty", "l.part_name")


@query("sync_operations", values("host, operation", """('orders', 'await db.collection(''orders'').updateMany({ _id: { $in: row.orders } }, { $set: { ''customer_name'': row.name } });')""", """('customers', 'for (const host of await db.collection(''customers'').find({ ''orders'': row._id }).toArray()) { await duplicateOrders(db, host); }')"""))
def sync_operations(spark, d):
    """The updates that code has to run when a referenced object changes: one plain, one array."""
    p = written(joins.removal_plans(_backend(spark)).where("host = 'orders' and referenced = 'customers' or host = 'customers' and referenced = 'orders'"), "plans")
    return migrate.sync_operations(p).join(p.select("plan_id", "host"), "plan_id").select("host", "operation")


@query("dup_orders_into_lineitem", "SELECT l_orderkey, l_linenumber, l_partkey, o_orderdate, o_orderpriority FROM lineitem JOIN orders ON o_orderkey = l_orderkey")
def dup_orders_into_lineitem(spark, d):
    """The large case: two fields of each order go into its lines."""
    lines = read_table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey")
    orders = read_table(spark, d, "orders").select(F.col("o_orderkey").alias("_id"), "o_orderdate", "o_orderpriority")
    out = migrate.apply_to_data(lines, orders, migrate.Duplication("lineitem", "orders", "l_orderkey", ("o_orderdate", "o_orderpriority"), "order_info"), "shuffle")
    return out.select("l_orderkey", "l_linenumber", "l_partkey", "order_info.o_orderdate", "order_info.o_orderpriority")


@query("rewrite_backend", values("name, changed", *[f"('{n}', {str(n in ('ordersOfCustomer', 'partsOfCustomer', 'orderWithItems', 'ordersWithCustomer', 'ordersWithSuppliers', 'partsWithOrdersAndCustomers', 'partsWithSuppliers')).lower()})" for n in (*[f"{v}{e}" for e in ("Customer", "Order", "Part", "Supplier") for v in ("list", "get", "create", "update", "remove")], "ordersOfCustomer", "partsOfCustomer", "orderWithItems", "partsByBrand", "ordersWithCustomer", "ordersWithSuppliers", "partsWithOrdersAndCustomers", "partsWithSuppliers")]))
def rewrite_backend(spark, d):
    """All eight plans applied to the code: which functions' texts differ; the others are kept byte by byte."""
    a, new = _rewritten_backend(spark)
    text = lambda m, as_: m.units.where("kind = 'function'").select(*KEY, "unit", "name").join(m.elements.where("kind = 'function'").select(*KEY, "name", F.col("text").alias(as_)), [*KEY, "name"]).select("name", as_)
    return text(a.m, "before").join(text(Models(new), "after"), "name", "full").select("name", (~F.col("before").eqNullSafe(F.col("after"))).alias("changed"))


@query("rewrite_backend_joins", values("path, host, referenced", "('none', 'none', 'none')") + " WHERE false")
def rewrite_backend_joins(spark, d):
    """Joins that the analysis finds in the rewritten backend, and files that need a look: none."""
    new = _rewritten_backend(spark)[1]
    return Access(Models(new)).joins.select("path", "host", "referenced").unionByName(new.where("review").select("path", F.lit("review").alias("host"), F.lit("review").alias("referenced")))


def _rewritten_backend(spark) -> tuple[Access, DataFrame]:
    a = _backend(spark)
    new = written(rewrite.apply_to_code(a.m.files, joins.removal_plans(a), a.ops), "rewritten")
    rest = a.m.files.join(new.select(*KEY), KEY, "left_anti").select(*KEY, "content", "lang", F.lit(False).alias("review"))
    return a, new.unionByName(rest).withColumn("sha", F.sha2("content", 256))


@query("remove_join_all", " UNION ALL ".join(f"SELECT '{x.host}' AS host, '{x.referenced}' AS referenced, {len(x.fields)} AS n_features, false AS review, CAST(0 AS BIGINT) AS n_differences, count(*) AS n_rows FROM ({_SQL[j]})" for j, x in shop.JOINS.items()))
def remove_join_all(spark, d):
    """Each of the eight plans on all three layers: features added to the schema, code to be looked at, rows in which the query on
    the updated hosts differs from the join, and rows of that query."""
    a = _backend(spark)
    schema, plans, out = written(logical.to_logical(a), "schema"), written(joins.removal_plans(a), "plans"), []
    for row in plans.collect():  # eight
        host, ref = (stored(spark, d, n, lambda n=n: shop.COLLECTIONS[n](spark, d)) for n in (row["host"], row["referenced"]))
        one, x = plans.where(F.col("plan_id") == row["plan_id"]).where(F.col("host") == row["host"]), migrate.duplication_of(row)
        code = rewrite.apply_to_code(a.m.files, one, a.ops).agg(F.max("review").alias("review"))
        added = logical.schema_diff(schema, joins.apply_to_schema(schema, one)).agg(F.count("*").cast("int").alias("n_features"))
        data = written(migrate.apply_to_data(host, ref, x), "updated")
        wrong = migrate.check_equivalence(host, ref, data, x).agg(F.count("*").alias("n_differences"))
        n = migrate.run_refactored(data, x).agg(F.count("*").alias("n_rows"))
        out.append(code.crossJoin(added).crossJoin(wrong).crossJoin(n).select(F.lit(row["host"]).alias("host"), F.lit(row["referenced"]).alias("referenced"), "n_features", "review", "n_differences", "n_rows"))  # one row each
    return reduce(DataFrame.unionByName, out)


@query("published_sizes", values("collection, n", *[f"('{k}', CAST({n} AS BIGINT))" for k, n in shop.PUBLISHED.items()]))
def published_sizes(spark, d):
    """The published data set's sizes: 10, 20, 60 and 8 objects."""
    return reduce(DataFrame.unionByName, [f.agg(F.count("*").alias("n")).select(F.lit(k).alias("collection"), "n") for k, f in shop.published(spark, d).items()])


@query("published_equivalence", values("join_name, _id", "('none', CAST(1 AS BIGINT))") + " WHERE false")
def published_equivalence(spark, d):
    """All eight joins on the data of published size, where many references dangle: no row differs."""
    frames = {k: written(f, f"published-{k}") for k, f in shop.published(spark, d).items()}
    return reduce(DataFrame.unionByName, [migrate.check_equivalence(frames[x.host], frames[x.referenced], migrate.apply_to_data(frames[x.host], frames[x.referenced], x), x).select(F.lit(j).alias("join_name"), "_id") for j, x in shop.JOINS.items()])


@query("orders_without_lines", "SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def orders_without_lines(spark, d):
    return read_table(spark, d, "orders").join(read_table(spark, d, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey"), "left_anti").select("o_orderkey")


@query("orphan_references", "SELECT user_id FROM events WHERE user_id NOT IN (SELECT c_custkey FROM customer)")
def orphan_references(spark, d):
    return read_table(spark, d, "events").join(read_table(spark, d, "customer"), F.col("user_id") == F.col("c_custkey"), "left_anti").select("user_id")


# -- versions ------------------------------------------------------------------------------------
def _versions(spark, d) -> DataFrame:
    return logical.versions_of(Access(Models(corpora.versioned_module(spark, d))))


_V = """
WITH w AS (SELECT DISTINCT CAST(week(ts) AS INTEGER) AS version FROM events),
f AS (
  SELECT version, 'user_id' AS field, 'attribute:string' AS shape FROM w
  UNION ALL SELECT version, 'event_type', 'attribute:string' FROM w WHERE version <> 5
  UNION ALL SELECT version, 'value', CASE WHEN version = 2 THEN 'attribute:long' ELSE 'attribute:double' END FROM w WHERE version >= 2
  UNION ALL SELECT version, 'payload', 'aggregate' FROM w WHERE version >= 3
  UNION ALL SELECT version, 'payload.k', 'attribute:string' FROM w WHERE version >= 3
)
"""


@query("variations", _V + "SELECT version, field, shape FROM f")
def variations(spark, d):
    return _versions(spark, d).select("version", "field", "shape")


@query("schema_evolution", _V + """, n AS (SELECT version, lead(version) OVER (ORDER BY version) AS nx FROM w)
SELECT n.nx AS version, coalesce(a.field, b.field) AS field, CASE WHEN a.field IS NULL THEN 'added' WHEN b.field IS NULL THEN 'removed' ELSE 'retyped' END AS change
FROM n JOIN (SELECT DISTINCT field FROM f) x ON n.nx IS NOT NULL
LEFT JOIN f a ON a.version = n.version AND a.field = x.field LEFT JOIN f b ON b.version = n.nx AND b.field = x.field
WHERE a.shape IS DISTINCT FROM b.shape""")
def schema_evolution(spark, d):
    return logical.schema_evolution(_versions(spark, d)).select("version", "field", "change")


@query("entity_versions", _V + "SELECT version, count(*) AS n_fields FROM f GROUP BY version")
def entity_versions(spark, d):
    return profile.track_entities(_versions(spark, d)).select("version", F.col("n_fields").cast("long").alias("n_fields"))


@query("asof_version_events", _V + "SELECT event_id, CAST(week(ts) AS INTEGER) AS version FROM events")
def asof_version_events(spark, d):
    """The last version that began before each event: a window over both, not a cross join."""
    e = read_table(spark, d, "events")
    starts = e.groupBy(F.weekofyear("ts").alias("version")).agg(F.min("ts").alias("ts")).select("ts", "version", F.lit(None).cast("long").alias("event_id"))
    both = starts.unionByName(e.select("ts", F.lit(None).cast("int").alias("version"), "event_id"))
    # Versions are few: they go to every day, and each day is a group of its own.
    day = both.withColumn("day", F.to_date("ts"))
    last = F.last("version", ignorenulls=True).over(W.partitionBy("day").orderBy("ts", F.col("event_id").isNotNull()))
    days = day.where("event_id is not null").select("day").distinct()
    carried = days.join(F.broadcast(starts.select("version", F.to_date("ts").alias("from"))), F.col("from") < F.col("day")).groupBy("day").agg(F.max_by("version", "from").alias("before"))
    return day.withColumn("now", last).where("event_id is not null").join(carried, "day", "left").select("event_id", F.coalesce("now", "before").alias("version"))


@query("incremental_models", "SELECT 'o' || o_orderkey || '.js' AS path, CASE WHEN o_orderkey % 10 = 0 THEN 'again' ELSE 'orders' END AS container FROM orders WHERE o_orderkey % 10 <> 1")
def incremental_models(spark, d):
    """Models after every tenth file was changed and every tenth deleted: only the changed ones are parsed again."""
    files = corpora.order_snippets(spark, d)
    old = Models(written(files, "files"))
    key = F.regexp_extract("path", r"(\d+)", 1).cast("long") % 10
    text = F.when(key == 0, F.regexp_replace("content", "'orders'", "'again'")).otherwise(F.col("content"))
    new = files.where(key != 1).withColumn("content", text).withColumn("sha", F.sha2("content", 256))
    return access.find_operations(rewrite.merged_models(old, written(new, "files"))).where("container <> 'customers'").select("path", "container")


@query("reference_evolution", values("version, field, change", "(2, 'b', 'reference changed')"))
def reference_evolution(spark, d):
    """A field that comes to refer to another container in the next version."""
    text = lambda c: f"async function f(db) {{ const a = await db.collection('a').findOne({{}}); const b = await db.collection('{c}').findOne({{ _id: a.b }}); use(a.b); }}"
    files = spark.createDataFrame([("t", v, "t.js", text(c), c, "js") for v, c in ((1, "x"), (2, "y"))], "app_id string, version int, path string, content string, sha string, lang string")
    return logical.schema_evolution(logical.versions_of(Access(Models(files)))).where("container = 'a'").select("version", "field", "change")


@query("incremental_files", "SELECT 'o' || o_orderkey || '.js' AS path FROM orders WHERE o_orderkey % 10 = 0")
def incremental_files(spark, d):
    files = corpora.order_snippets(spark, d)
    old = files.withColumn("sha", F.when(F.regexp_extract("path", r"(\d+)", 1).cast("long") % 10 == 0, F.lit("changed")).otherwise(F.col("sha")))
    return rewrite.analyze_incremental(old, files).select("path")


# -- operators around the methods ------------------------------------------------------------------
@query("catalog_columns", "SELECT table_name AS entity, count(*) AS n FROM information_schema.columns WHERE table_name IN (" + ", ".join(f"'{t}'" for t in TABLES) + ") GROUP BY 1")
def catalog_columns(spark, d):
    return profile.catalog(_tables(spark, d)).groupBy("entity").agg(F.count("*").alias("n"))


@query("singular_names", "SELECT p_partkey, p_name || CASE p_partkey % 4 WHEN 0 THEN 's' WHEN 1 THEN ' categories' WHEN 2 THEN ' boxes' ELSE ' address' END AS name, p_name || CASE p_partkey % 4 WHEN 0 THEN '' WHEN 1 THEN ' category' WHEN 2 THEN ' box' ELSE ' address' END AS one FROM part")
def singular_names(spark, d):
    """Names of parts with the endings of the four rules."""
    ending = F.element_at(F.array(*[F.lit(x) for x in ("s", " categories", " boxes", " address")]), (F.col("p_partkey") % 4 + 1).cast("int"))
    df = read_table(spark, d, "part").select("p_partkey", F.concat("p_name", ending).alias("name"))
    return df.select("p_partkey", "name", singular(F.col("name")).alias("one"))


@query("name_similarity", "SELECT a.r_name AS a, b.r_name AS b, round(1 - levenshtein(a.r_name, b.r_name) / greatest(length(a.r_name), length(b.r_name)), 3) AS similarity FROM region a, region b WHERE a.r_name < b.r_name")
def names_alike(spark, d):
    r = read_table(spark, d, "region")
    return r.select(F.col("r_name").alias("a")).join(r.select(F.col("r_name").alias("b")), F.col("a") < F.col("b")).withColumn("similarity", name_similarity(F.col("a"), F.col("b")))


@query("event_payload_variations", "SELECT CASE WHEN k < 30 THEN 'k,more' WHEN k < 60 THEN 'k' ELSE 'other' END AS structure, count(*) AS n FROM (SELECT CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events) GROUP BY 1")
def event_payload_variations(spark, d):
    """Payloads of three structures, made from the events': a field more, as they are, renamed."""
    k = F.get_json_object("props", "$.k").cast("int")
    shaped = F.when(k < 30, F.to_json(F.struct(k.alias("k"), F.lit(1).alias("more")))).when(k < 60, F.col("props")).otherwise(F.to_json(F.struct(k.alias("other"))))
    return profile.data_variations(read_table(spark, d, "events").select(shaped.alias("payload")), "payload").select("structure", "n")


@query("document_reader", "SELECT CASE WHEN l.doc_id IS NULL THEN 'without' ELSE 'with' END AS label, count(*) AS n FROM documents d LEFT JOIN labels l USING (doc_id) GROUP BY 1")
def document_reader(spark, d):
    """The docs collection written as JSON documents and read back: absent fields are absent."""
    path = f"{shared_folder(spark)}/docs-{uuid.uuid4().hex[:12]}"
    docs = shop.docs(spark, d)
    write_documents(docs, path)
    back = read_documents(spark, path, docs.schema)
    return back.groupBy(F.when(F.col("label").isNull(), "without").otherwise("with").alias("label")).agg(F.count("*").alias("n"))


@query("graph_reader", "SELECT o_custkey AS _id, o_orderkey AS target FROM orders")
def graph_reader(spark, d):
    """Customers and orders as a graph, read as collections: an edge label is an array of references."""
    c = read_table(spark, d, "customer").select(F.lit("customers").alias("label"), F.col("c_custkey").alias("_id"), F.col("c_name").alias("name"))
    o = read_table(spark, d, "orders")
    nodes = c.unionByName(o.select(F.lit("orders").alias("label"), F.col("o_orderkey").alias("_id"), F.lit(None).cast("string").alias("name")))
    edges = o.select(F.lit("placed").alias("label"), F.lit("customers").alias("source_label"), F.col("o_custkey").alias("source"), F.col("o_orderkey").alias("target"))
    return read_graph(nodes, edges)["customers"].select("_id", F.explode("placed").alias("target"))


@query("code_tokens", "SELECT kind, CAST(count(*) * n AS BIGINT) AS n FROM pages, (VALUES ('name', 3), ('sign', 5), ('string', 1), ('number', 1)) AS t(kind, n) GROUP BY kind, n")
def code_tokens(spark, d):
    """Tokens of the page scripts by the table function, called from SQL."""
    name, view = register_code_tokens(spark), f"scripts_{uuid.uuid4().hex[:8]}"
    read_table(spark, d, "pages").select(F.regexp_extract("html", r"(?s)<script[^>]*>(.*?)</script>", 1).alias("script")).createOrReplaceTempView(view)
    return spark.sql(f"SELECT t.kind, count(*) AS n FROM {view}, LATERAL {name}(script) t GROUP BY t.kind")


@query("event_payload_fields", "SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def event_payload_fields(spark, d):
    return shop.events(spark, d).select(F.col("_id").alias("event_id"), "payload.k")


@query("rolling_op_counts", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 9 PRECEDING AND CURRENT ROW) AS n FROM events")
def rolling_op_counts(spark, d):
    return read_table(spark, d, "events").select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-9, 0)).alias("n"))


_S = """SELECT *, CASE WHEN k % 10 = 0 THEN 'events' WHEN event_type IN ('view', 'signup') THEN 'customers' WHEN event_type = 'purchase' THEN 'orders' ELSE 'events' END AS container,
  CASE WHEN k % 10 = 0 THEN 'D' WHEN event_type IN ('view', 'click') THEN 'R' WHEN event_type IN ('purchase', 'signup') THEN 'I' ELSE 'U' END AS kind
  FROM (SELECT *, CAST(json_extract_string(props, '$.k') AS INTEGER) AS k FROM events)"""


def _stream(spark, d) -> DataFrame:
    return streaming.operations(streaming.event_stream(spark, f"{d}/events.parquet"))


@query("stream_tumbling_ops", f"SELECT CAST(date_trunc('day', ts) AS VARCHAR) AS start, container, kind, count(*) AS n FROM ({_S}) GROUP BY ALL")
def stream_tumbling_ops(spark, d):
    out = streaming.run_to_table(streaming.tumbling(_stream(spark, d)), "tumbling_ops")
    return out.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "container", "kind", "n")


@query("stream_sliding_ops", f"SELECT CAST(s AS VARCHAR) AS start, container, count(*) AS n FROM (SELECT container, unnest([time_bucket(INTERVAL 12 HOURS, ts), time_bucket(INTERVAL 12 HOURS, ts) - INTERVAL 12 HOURS]) AS s FROM ({_S})) GROUP BY ALL")
def stream_sliding_ops(spark, d):
    out = streaming.run_to_table(streaming.sliding(_stream(spark, d)), "sliding_ops")
    return out.select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "container", "n")


@query("stream_session_ops", "WITH e AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 12 HOURS OR lag(ts) OVER (PARTITION BY user_id ORDER BY ts) IS NULL THEN 1 ELSE 0 END AS new FROM events), g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM e) SELECT user_id, count(*) AS n, CAST(date_trunc('second', min(ts)) AS VARCHAR) AS start FROM g GROUP BY user_id, s")
def stream_session_ops(spark, d):
    out = streaming.run_to_table(streaming.sessions(_stream(spark, d)), "session_ops")
    return out.select("user_id", "n", F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"))


@query("stream_once_each", f"SELECT event_id, container, kind FROM ({_S})")
def stream_once_each(spark, d):
    """Events that come twice count once."""
    e = _stream(spark, d)
    return streaming.run_to_table(streaming.once_each(e.unionByName(e)).select("event_id", "container", "kind"), "once_each", "append")


@query("stream_first_last", f"SELECT user_id, container, arg_min(kind, (ts, event_id)) AS first_kind, arg_max(kind, (ts, event_id)) AS last_kind, count(*) AS n FROM ({_S}) GROUP BY user_id, container")
def stream_first_last(spark, d):
    """The state of each user and container: first and last operation."""
    return streaming.run_to_table(streaming.first_last(_stream(spark, d)), "first_last")


@query("source_changes", "SELECT 'o' || o_orderkey || '.js' AS path, 'orders' AS container FROM orders UNION ALL SELECT 'o' || o_orderkey || '.js', 'customers' FROM orders")
def source_changes(spark, d):
    """Files that come as a stream in several batches, analysed as they come: the same operations as in one go."""
    at = f"{shared_folder(spark)}/incoming-{uuid.uuid4().hex[:12]}"
    files = corpora.order_snippets(spark, d)
    files.repartition(3, "path").write.parquet(at)
    stream = spark.readStream.schema(files.schema).option("maxFilesPerTrigger", 1).parquet(at)

    def handle(df: DataFrame, batch: int) -> None:
        access.find_operations(Models(df)).select("path", "container").write.mode("overwrite").parquet(f"{at}-ops/batch={batch}")

    streaming.source_changes(stream, handle, f"incoming-{uuid.uuid4().hex[:12]}").awaitTermination()
    return spark.read.parquet(f"{at}-ops").select("path", "container")


@query("stream_enriched", "SELECT event_id, c_name AS name FROM events LEFT JOIN customer ON c_custkey = user_id")
def stream_enriched(spark, d):
    names = read_table(spark, d, "customer").select(F.col("c_custkey").alias("user_id"), F.col("c_name").alias("name"))
    return streaming.run_to_table(streaming.enriched(_stream(spark, d), names, "user_id").select("event_id", "name"), "enriched_ops", "append")


@query("stream_joined_changes", "SELECT h.event_id AS host, r.event_id AS referenced FROM events h JOIN events r ON h.user_id = r.user_id AND r.ts <= h.ts AND r.ts >= h.ts - INTERVAL 1 DAY WHERE h.event_type = 'purchase' AND r.event_type = 'signup'")
def stream_joined_changes(spark, d):
    """Inserts with changes of the same user in the day before: two streams."""
    e = streaming.event_stream(spark, f"{d}/events.parquet")
    hosts = e.where("event_type = 'purchase'").select(F.col("user_id").alias("ref"), "ts", F.col("event_id").alias("host"))
    changes = e.where("event_type = 'signup'").select(F.col("user_id").alias("ref"), "ts", F.col("event_id").alias("referenced"))
    return streaming.run_to_table(streaming.matched_changes(hosts, changes, "1 day").select("host", "referenced"), "joined_changes", "append")


@query("sql_frontend", "SELECT 's' || s_suppkey || '.sql' AS path, seq, kind, container, n_joins FROM supplier, (VALUES (0, 'R', 'orders', 1), (0, 'R', 'customers', 1), (1, 'I', 'log', 0), (2, 'D', 'orders', 0), (3, 'U', 'parts', 0)) AS t(seq, kind, container, n_joins) WHERE seq < 3 OR s_nationkey % 2 = 0")
def sql_frontend(spark, d):
    """Operations of a SQL script a supplier, by the second front end; a nation's suppliers have the same script."""
    s = read_table(spark, d, "supplier")
    last = F.when(F.col("s_nationkey") % 2 == 0, F.lit("; UPDATE parts SET size = 2 WHERE id = 3")).otherwise(F.lit(";"))
    text = F.concat(F.format_string("SELECT o.total, c.name FROM orders o JOIN customers c ON o.customer = c.id; INSERT INTO log VALUES (%d, 'a;b'); -- note\nDELETE FROM orders WHERE id = 1", "s_nationkey"), last)
    files = as_files(s.select(F.col("s_nationkey").alias("app_id"), F.lit(1).alias("version"), F.format_string("s%d.sql", "s_suppkey").alias("path"), text.alias("content"), F.lit("sql").alias("lang")))
    return sqltext.operations(files).select("path", "seq", "kind", "container", "n_joins")


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Operations, dependencies and references of the order snippets, as rows."""
    a = Access(Models(corpora.order_snippets(spark, d)))
    return a.refs.groupBy("holder", "field", "referenced").agg(F.count("*").alias("n"))
