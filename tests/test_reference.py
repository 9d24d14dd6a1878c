"""Worked examples, options, strategies and edge cases of the reference methods."""

from __future__ import annotations

import dataclasses
from types import SimpleNamespace

import pytest
from codeschema import Options, analyze, paper_options, remove_join
from codeschema import queries as Q
from codeschema.frontend.inject import inject_text
from codeschema.frontend.parser import parse
from codeschema.frontend.tokens import tokenize
from codeschema.operators import access, joins, logical, migrate, models, profile, rewrite, shop
from codeschema.operators.access import Access, backward_links, chain_depth, find_operations, reach
from codeschema.operators.models import Models
from codeschema.sources import as_files, corpora
from codeschema.store import written
from conftest import SF, TABLES
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.errors import AnalysisException
from pyspark.sql import functions as F


def files(spark, *texts: str):
    return as_files(spark.createDataFrame([("t", 1, f"f{i}.js", x, "js") for i, x in enumerate(texts)], "app_id string, version int, path string, content string, lang string"))


def found(a: Access) -> dict[str, tuple]:
    return {f"{r.container}.{r.field}": (r.type_kind, r.prim_type, r.evidence) for r in a.fields().collect()}


@pytest.mark.parametrize("name", sorted(corpora.MICRO))
def test_micro_snippets_parse(name):
    rows, error = inject_text(corpora.MICRO[name])
    assert (error is not None) == (name == "syntax_error")
    assert error or rows["units"]


@settings(max_examples=60, deadline=None)
@given(st.lists(st.sampled_from(["a", "b.c", "f(x)", "1", "'s'", "x => x.y", "{ k: 1 }", "[1, a]", "a ? b : c", "a + b * 2", "await g(a.b)", "!a"]), min_size=1, max_size=4))
def test_statements_keep_their_tokens(parts):
    text = " ".join(f"const v{i} = {p};" for i, p in enumerate(parts))
    tree, tokens = parse(text)
    assert [t.text for s in tree.kids for t in tokens[s.a : s.b]] == [t.text for t in tokenize(text)]


def test_files_of_one_shape_are_parsed_once(spark):
    """Models of texts that differ in numbers only equal those of the parser, whether filled or parsed, and only two of a shape are parsed."""
    from codeschema.frontend.inject import inject_text
    from codeschema.frontend.shapes import Shapes, shape_of
    from codeschema.schema import MODEL
    from pyspark.sql.pandas.types import to_arrow_schema

    schema = to_arrow_schema(spark.createDataFrame([], MODEL).schema)
    forms = ["const o = await db.collection('orders').findOne({{ _id: {a} }});\nuse(o.list[{b}], a{a}, '{a} x', {b}.5, 0x{a});", "f({a}, {{ k: [{b}, {a}] }}); if (o.n == {a}) g(x => x.y * {b});", "let s = '\\{a}'; const c = '{b}'; db.collection(c).insertOne({{ '{a}': {b} }});", "f({a}", "`${{ {a} }}`;", "x = 819000000000{b};", "if (a) {{ return {a} }}" + " " * 380 + "q({b});"]
    texts = [f.format(a=a, b=b) for f in forms for a, b in ((1, 22), (333, 4), (56, 56), (7, 7), (0, 7), (123456789012345, 9), (1, 1))] + ["", "f();", "f();"]
    parsed = []

    def parse(text):
        parsed.append(text)
        return inject_text(text)

    shapes, rows, same = Shapes(parse, schema), {}, []
    for i, text in enumerate(texts):
        got = shapes.find(text)
        if isinstance(got[0], int):
            same.append((i, *got))
        else:
            rows[i] = got
    assert len(same) == 4 and shape_of("f(1.5, 1e3, 0x10, a1, 007)") is None
    names = ["app_id", "version", "path", "error"]
    filled = shapes.filled({k: [None] * len(same) for k in names}, [s[1] for s in same], [s[2] for s in same]).to_pylist()
    rows |= {s[0]: ({k: v for k, v in row.items() if k not in names}, None) for s, row in zip(same, filled, strict=True)}
    assert [rows[i] for i in range(len(texts))] == [inject_text(t) for t in texts]
    parsed.clear()
    for i in range(100):
        shapes.find(f"h({i + 1});")
    assert len(parsed) == 3  # two texts and their shape
    several = files(spark, *texts)
    assert sorted(str(r) for r in Models(several).model.where("error is null").selectExpr("path", "calls", "args").collect()) == sorted(str(r) for r in spark.createDataFrame([("t", 1, f"f{i}.js", None, *[r[0][k] for k in ("units", "elements", "nodes", "uses", "aliases", "calls", "args", "resolved")]) for i, r in rows.items() if r[1] is None], MODEL).selectExpr("path", "calls", "args").collect())


def test_strings_and_comments_are_no_code():
    for name in ("comment", "string"):
        rows, _ = inject_text(corpora.MICRO[name])
        assert not [c for c in rows["calls"] if c["container"]]


def test_tracks_through_aliases_destructuring_and_callbacks(spark):
    a = analyze(files(spark, corpora.MICRO["alias"], corpora.MICRO["destructure"], corpora.MICRO["then"], corpora.MICRO["callback"]))
    f = found(a)
    assert f["c.name"][0] == "attribute" and f["c.inner"][0] == "aggregate" and f["c.k"][1:] == ("long", "literal")
    assert "c.name" not in found(analyze(files(spark, corpora.MICRO["alias"]), dataclasses.replace(Options(), aliases=False)))


def test_collections_and_nesting(spark):
    f = found(analyze(files(spark, corpora.MICRO["index"], corpora.MICRO["array_method"], corpora.MICRO["nested_object"])))
    assert f["c.list"][0] == "collection_of_aggregates" and f["c.tags"][0] == "collection"
    assert f["c.a"][0] == f["c.a.b"][0] == "aggregate" and f["c.a.b.c"][0] == "attribute"


def test_same_name_in_two_units(spark):
    f = found(analyze(files(spark, corpora.MICRO["same_name"])))
    assert "c.x" in f and "d.y" in f and "c.y" not in f and "d.x" not in f


def test_writes_only_on_request(spark):
    t = files(spark, corpora.MICRO["insert"], corpora.MICRO["update"])
    assert "c.name" not in found(analyze(t))
    f = found(analyze(t, dataclasses.replace(Options(), learn_from_writes=True)))
    assert f["c.name"][1] == "string" and f["c.deep"][0] == "aggregate" and f["c.tags"][0] == "collection"


def test_untouched_field_is_not_found(spark):
    assert "orders.orderdate" not in found(analyze(corpora.running_example(spark)))


def test_references_by_conditions(spark):
    a = analyze(files(spark, corpora.MICRO["in_filter"], corpora.MICRO["reverse"], corpora.MICRO["lookup"]))
    got = {(r.holder, r.field, r.referenced, r.upper_bound, r.reverse) for r in a.refs.collect()}
    assert got == {("c", "refs", "d", "many", False), ("d", "owner", "c", "one", True), ("c", "r", "d", "many", False)}


def test_kill_and_join_rules(spark):
    m = Models(files(spark, corpora.MICRO["reassign"]))
    ops = find_operations(m)
    for strategy in ("kernel", "relational", "sql"):
        assert backward_links(m, ops, Options(strategy=strategy)).count() == 1
    assert backward_links(m, ops, Options(kill=True)).count() == 0
    same = files(spark, "async function f(db) { const a = await db.collection('c').findOne({}); const b = await db.collection('c').findOne({ k: a.x }); use(a.y, b.z); }")
    assert analyze(same, Options(join_rule="linked")).joins.count() == 1
    assert analyze(same).joins.count() == 0


def test_strategies_agree(spark):
    m = Models(corpora.backend(spark).unionByName(corpora.micro(spark)))
    ops = written(find_operations(m), "ops")
    key = lambda df: sorted((r.path, r.prev_op, r.next_op, r.hops) for r in df.collect())
    one = key(backward_links(m, ops, Options()))
    assert one and one == key(backward_links(m, ops, Options(strategy="relational")))


def test_exclusive_branches(spark):
    text = "async function f(db, q) { let a = null; if (q) { a = await db.collection('c').findOne({}); } else { const b = await db.collection('d').findOne({ _id: a.x }); } }"
    m = Models(files(spark, text))
    ops = find_operations(m)
    assert backward_links(m, ops, Options(walk="linear")).count() == 1
    assert backward_links(m, ops, Options()).count() == 0


def test_empty_corpus_and_broken_files(spark):
    none = files(spark, "use(1);").where("false")
    a = analyze(none)
    assert a.ops.count() == a.joins.count() == logical.to_logical(a).count() == 0
    m = Models(files(spark, corpora.MICRO["syntax_error"], corpora.MICRO["callback"]))
    assert m.errors().count() == 1 and find_operations(m).count() == 1


def test_null_content(spark):
    df = as_files(spark.createDataFrame([("t", 1, "n.js", None, "js")], "app_id string, version int, path string, content string, lang string"))
    assert Models(df).nodes.count() == 0


def test_cross_file_calls(spark):
    m = Models(files(spark, "load(1);", "function load(n) { return n; }"))
    assert [(r.path, r.in_path) for r in models.cross_file_calls(m).collect()] == [("f0.js", "f1.js")]
    assert models.unresolved_calls(m).count() == 0


def test_loop_has_back_edge(spark):
    kinds = {r.kind for r in models.flow_edges(Models(files(spark, corpora.MICRO["while"]))).collect()}
    assert "back" in kinds


def test_relationship_types(spark):
    s = logical.declare_schema(spark, [("link", "a", "reference", "long", "one", "x"), ("link", "b", "reference", "long", "one", "y"), ("x", "_id", "key", "long", "one", None)])
    assert [r.entity for r in logical.relationship_types(s).collect()] == ["link"]


def test_rendering(spark):
    s = logical.to_logical(analyze(corpora.running_example(spark)))
    text = {r.entity: r.line for r in logical.render(s).collect()}
    assert "order_id: reference string -> orders" in text["customers.recent"] and "recent struct<channel: string, order_id: string>" in {r.entity: r.line for r in logical.render(s, "ddl").collect()}["customers"]
    assert spark.createDataFrame([], {r.entity: r.line for r in logical.render(s, "ddl").collect()}["orders"]).columns == ["_id", "priority"]
    assert logical.render(s, "json").count() == 3 and logical.render(s, "dot").count() == 2


def test_paper_options_find_the_running_example(spark):
    p = joins.removal_plans(analyze(corpora.running_example(spark), paper_options())).collect()
    assert [(r.fields, r.names) for r in p] == [(["priority"], ["priority"])]


def test_remove_join_on_three_layers(spark):
    a = analyze(corpora.backend(spark))
    schema = written(logical.to_logical(a), "schema")
    plan = next(r for r in joins.removal_plans(a).collect() if (r.host, r.referenced) == ("customers", "orders"))
    frames = {n: shop.COLLECTIONS[n](spark, SF) for n in ("customers", "orders")}
    code, new, data = remove_join(a, schema, frames, plan.plan_id)
    assert [r.feature for r in logical.schema_diff(schema, new).collect()] == ["order_orderdate"]
    d = migrate.Duplication("customers", "orders", "orders", ("orderdate",), "order_orderdate", many=True)
    assert migrate.check_equivalence(frames["customers"], frames["orders"], data["customers"], d).count() == 0
    again = analyze(code.withColumn("sha", F.sha2("content", 256)))
    assert again.joins.where("referenced = 'orders'").count() == 0


def test_dangling_references_and_empty_arrays(spark):
    host = spark.createDataFrame([(1, 10, [10, 99, 10]), (2, None, []), (3, 99, None)], "_id long, one long, many array<long>")
    ref = spark.createDataFrame([(10, "x")], "_id long, name string")
    one = migrate.apply_to_data(host, ref, migrate.Duplication("h", "r", "one", ("name",), "dup"), "shuffle")
    assert {r._1: r.dup for r in one.withColumnRenamed("_id", "_1").collect()} == {1: "x", 2: None, 3: None}
    many = migrate.apply_to_data(host, ref, migrate.Duplication("h", "r", "many", ("name",), "dup", many=True), "broadcast")
    assert {r["_id"]: r.dup for r in many.collect()} == {1: ["x", "x"], 2: [], 3: None}


def test_repeated_keys_and_clashing_names(spark):
    host = spark.createDataFrame([(1, 10, "h", "v")], "_id long, one long, __ref string, __value string")
    ref = spark.createDataFrame([(10, "b"), (10, "a"), (None, "z")], "_id long, name string")
    for strategy in ("shuffle", "broadcast"):
        got = migrate.apply_to_data(host, ref, migrate.Duplication("h", "r", "one", ("name",), "dup"), strategy).collect()
        assert [(r["_id"], r.dup, r["__ref"], r["__value"]) for r in got] == [(1, "a", "h", "v")]


def test_broadcast_is_measured(spark):
    df = spark.range(10).select(F.col("id").alias("_id"), F.lit("x" * 1000).alias("name"))
    assert migrate.fits_broadcast(df) and not migrate.fits_broadcast(df, most_rows=9) and not migrate.fits_broadcast(df, most_bytes=5000)


def test_natural_keys_on_data(spark):
    host = spark.createDataFrame([(1, "a"), (2, "b"), (3, None)], "_id long, code string")
    ref = spark.createDataFrame([(7, "a", "x"), (8, "a", "y"), (9, "b", "z")], "_id long, code string, name string")
    one = migrate.apply_to_data(host, ref, migrate.Duplication("h", "r", "code", ("name",), "dup", key="code"))
    assert {r["_id"]: r.dup for r in one.collect()} == {1: "x", 2: "z", 3: None}
    many = migrate.apply_to_data(host, ref, migrate.Duplication("h", "r", "code", ("name",), "dup", many=True, key="code"))
    assert {r["_id"]: r.dup for r in many.collect()} == {1: ["x", "y"], 2: ["z"], 3: []}


def test_duplicate_inside_one_object(spark):
    host = spark.createDataFrame([(1, (10, "web")), (2, (99, "shop")), (3, None)], "_id long, recent struct<order_id: long, channel: string>")
    ref = spark.createDataFrame([(10, "high")], "_id long, priority string")
    got = migrate.apply_to_data(host, ref, migrate.Duplication("c", "o", "recent.order_id", ("priority",), "order_priority", inside="recent"))
    assert {r["_id"]: r.recent and r.recent.order_priority for r in got.collect()} == {1: "high", 2: None, 3: None}


def rewritten(spark, text: str) -> tuple[str, bool]:
    a = analyze(files(spark, text))
    row = rewrite.apply_to_code(a.m.files, joins.removal_plans(a), a.ops).first()
    return row.content, row.review


def test_rewriting_changes_its_own_places_only(spark):
    ask = "const a = await db.collection('c').findOne({ _id: k }); const b = await db.collection('d').findOne({ _id: a.ref });"
    text = f"async function one(db, k) {{ {ask} use(a.n, b.y, 'b.y'); /* b.y */ }}\nasync function two(db, k) {{ {ask} return 1; }}\nfunction three(b) {{ return b.y; }}\n"
    new, review = rewritten(spark, text)
    assert not review
    assert "use(a.n, a.d_y, 'b.y'); /* b.y */" in new and new.count("db.collection('d')") == 1
    assert new.splitlines()[1:] == text.splitlines()[1:]


def test_rewriting_refuses_what_it_cannot_do(spark):
    ask = "async function f(db, k) { const a = await db.collection('c').findOne({ _id: k }); const b = await db.collection('d').findOne({ _id: a.ref });"
    for rest in ("use(a.n, b.y); send(b); }", "use(a.n, b.y); if (b) { use(1); } }", "use(a.n, b.y); return b; }"):
        assert rewritten(spark, f"{ask} {rest}") == (f"{ask} {rest}", True)
    across = "async function load(db, id) { return db.collection('d').findOne({ _id: id }); } async function f(db, k) { const a = await db.collection('c').findOne({ _id: k }); const b = await load(db, a.ref); use(a.n, b.y); }"
    assert rewritten(spark, across) == (across, True)


def test_rewriting_callbacks_loops_and_pipelines(spark):
    new, review = rewritten(spark, "db.collection('c').findOne({ _id: 1 }, (err, a) => { db.collection('d').findOne({ _id: a.ref }, (e, b) => { use(a.n, b.y); }); });")
    assert not review and new == "db.collection('c').findOne({ _id: 1 }, (err, a) => { use(a.n, a.d_y); });"
    new, review = rewritten(spark, "async function f(db) { const a = await db.collection('c').findOne({}); const b = await db.collection('d').find({ _id: { $in: a.refs } }).toArray(); for (const x of b) { use(a.n, x.y); } }")
    assert not review and new == "async function f(db) { const a = await db.collection('c').findOne({}); for (const x of a.d_y) { use(a.n, x); } }"
    pipe = "db.collection('c').aggregate([{ $match: { k: 1 } }, { $lookup: { from: 'd', localField: 'r', foreignField: '_id', as: 'ds' } }, { $sort: { k: 1 } }]).toArray().then(rows => { for (const x of rows) { use(x.a, x.ds[0].b); } });"
    new, review = rewritten(spark, pipe)
    assert not review and "$lookup" not in new and "[{ $match: { k: 1 } }, { $sort: { k: 1 } }]" in new and "use(x.a, x.d_b[0])" in new


def test_unsafe_code_is_refused_on_all_layers(spark):
    text = "async function f(db, k) { const a = await db.collection('customers').findOne({ _id: k }); const b = await db.collection('orders').findOne({ _id: a.last }); use(a.name, b.status); if (b) { use(1); } }"
    a = analyze(files(spark, text))
    plan = joins.removal_plans(a).first()
    frames = {"customers": spark.createDataFrame([(1, 2)], "_id long, last long"), "orders": spark.createDataFrame([(2, "s")], "_id long, status string")}
    with pytest.raises(ValueError):
        remove_join(a, logical.to_logical(a), frames, plan.plan_id)
    code, _, data = remove_join(a, logical.to_logical(a), frames, plan.plan_id, force=True)
    assert code.first().content == text and data["customers"].first().order_status == "s"


def test_kinds_of_flows(spark):
    method = "class Repo { async load(db, id) { const row = await db.collection('d').findOne({ _id: id }); return row; } async show(db, k) { const a = await db.collection('c').findOne({ _id: k }); const b = await this.load(db, a.ref); use(a.n, b.y); } }"
    assert [(r.prev_container, r.next_container) for r in analyze(files(spark, method)).links.collect()] == [("c", "d")]
    deep = "async function one(db, x) { return db.collection('d').findOne({ _id: x }); } async function two(db, y) { const r = await one(db, y); return r; } async function f(db, k) { const a = await db.collection('c').findOne({ _id: k }); const b = await two(db, a.ref); use(a.n, b.y); }"
    a = analyze(files(spark, deep))
    assert [(r.hops) for r in a.links.collect()] == [2] and "d.y" in found(a)
    again = "async function walk(db, x) { const r = await db.collection('d').findOne({ _id: x }); if (r) { return walk(db, r.next); } return r; }"
    assert analyze(files(spark, again)).links.where("prev_op = next_op").count() == 0  # a walk through recursion ends


def test_template_expressions_have_their_places():
    rows, error = inject_text("const s = `a ${b.c} d ${f(e.g)}`;")
    assert error is None and {(u["root"], u["steps"][0]["name"]) for u in rows["uses"] if u["steps"]} >= {("b@0", "c"), ("e@0", "g")}
    assert [c["text"] for c in rows["calls"]] == ["f(e.g)"]


def test_merged_models_follow_deletions(spark):
    old = Models(files(spark, "a(1);", "b(2);", "c(3);"))
    new = files(spark, "a(1);", "b(4);")
    m = rewrite.merged_models(old, new)
    assert sorted(r.literal for r in m.args.collect()) == ["1", "4"]


def test_files_are_dealt_over_tasks(spark):
    from codeschema.frontend.inject import spread

    assert spread(files(spark, *["use(1);"] * 20).coalesce(1)).rdd.getNumPartitions() >= 4


def test_written_tables_can_be_released(spark, tmp_path):
    from codeschema import store

    keep, store._paths[spark.sparkContext.applicationId] = store._paths.get(spark.sparkContext.applicationId, []), []
    path = written(spark.range(3).toDF("x"), "short").inputFiles()[0]
    assert store.release(spark) == 1 and not __import__("os").path.exists(path.replace("file://", ""))
    store._paths[spark.sparkContext.applicationId] = keep


def test_volume_does_not_change_the_schema(spark):
    key = lambda d: sorted(map(tuple, logical.to_logical(analyze(corpora.catalog_modules(spark, d))).select("entity", "feature", "type").collect()))
    assert key(SF) == key("/root/testdata/sf0.01")


def test_late_events_are_dropped(spark, tmp_path):
    from codeschema import streaming

    rows = [[("2024-01-01 00:00:00", 1), ("2024-01-03 00:00:00", 2)], [("2024-01-05 00:00:00", 4)], [("2024-01-01 01:00:00", 3), ("2024-01-07 00:00:00", 5)], [("2024-01-09 00:00:00", 6)]]
    for i, r in enumerate(rows):
        spark.createDataFrame(r, "t string, user_id long").select(F.to_timestamp("t").alias("ts"), "user_id", F.lit("c").alias("container"), F.lit("R").alias("kind")).coalesce(1).write.parquet(str(tmp_path / f"in/{i}"))
    import time

    src = tmp_path / "flat"
    src.mkdir()
    for i in range(4):
        next((tmp_path / f"in/{i}").glob("*.parquet")).rename(src / f"{i}.parquet")
        time.sleep(0.05)
    stream = spark.readStream.schema("ts timestamp, user_id long, container string, kind string").option("maxFilesPerTrigger", 1).parquet(str(src))
    out = streaming.run_to_table(streaming.tumbling(stream), "late_ops", "append")
    assert spark.catalog.listTables() == [] or not any(t.name.startswith("late_ops") for t in spark.catalog.listTables())
    assert sum(r.n for r in out.collect()) == 4  # the late one is gone, the last window is open


def test_incremental_equals_batch(spark, tmp_path):
    from codeschema import streaming

    all_files = corpora.backend(spark)
    path = str(tmp_path / "src")
    all_files.repartition(3).write.parquet(path)
    got = []
    stream = spark.readStream.schema(all_files.schema).option("maxFilesPerTrigger", 1).parquet(path)
    streaming.source_changes(stream, lambda df, _: got.extend(map(tuple, find_operations(Models(df)).select("path", "op").collect()))).awaitTermination()
    assert sorted(got) == sorted(map(tuple, find_operations(Models(all_files)).select("path", "op").collect()))


def test_regenerated_text(spark):
    f = corpora.running_example(spark)
    assert rewrite.roundtrip_diff(f, Models(f)).count() == 0


# -- walks end only when nothing is new -------------------------------------------------------------------------
def linked(spark, pairs, names):
    return spark.createDataFrame([("t", 1, "f.js", *p) for p in pairs], f"app_id string, version int, path string, {names}")


def test_reachable_goes_on(spark):
    edges = linked(spark, [(i, i + 1) for i in range(70)], "src int, dst int")
    got = models.reachable(edges, linked(spark, [(0,)], "seq int"))
    assert {(r.dst, r.dist) for r in got.collect()} == {(i, i) for i in range(71)}


def test_chain_depth_goes_on(spark):
    got = chain_depth(linked(spark, [(i, i + 1) for i in range(36)], "prev_op int, next_op int"))
    assert {(r.op, r.depth) for r in got.collect()} == {(i, i) for i in range(37)}
    with pytest.raises(ValueError):
        chain_depth(linked(spark, [(1, 2), (2, 1)], "prev_op int, next_op int"))


def long_chain(spark):
    steps = " ".join(f"const a{i + 1} = a{i};" for i in range(66))
    m = Models(files(spark, f"async function f(db) {{ const a0 = await db.collection('c').findOne({{}}); {steps} const b = await db.collection('d').findOne({{ _id: a66.x }}); }}"))
    return m, written(find_operations(m), "ops")


def test_long_chains_backward(spark):
    m, ops = long_chain(spark)
    for strategy in ("kernel", "relational", "sql"):
        assert backward_links(m, ops, Options(strategy=strategy)).count() == 1, strategy


def test_long_chains_forward(spark):
    m, ops = long_chain(spark)
    assert reach(m, ops).where("var = 'a66@1'").count() == 1
    with pytest.raises(RuntimeError):
        reach(m, ops, Options(max_rounds=3))


def test_blocks_are_climbed_to_the_top(spark):
    blocks = linked(spark, [(100 + i, "block", 1000 + i, 0, None) for i in range(8)] + [(1000 + i, "call", None, 0, 101 + i) for i in range(7)], "elem int, kind string, parent int, unit int, block int")
    a = SimpleNamespace(m=SimpleNamespace(elements=blocks, units=linked(spark, [("callback", 0)], "kind string, unit int")))
    assert {r.above for r in joins._blocks_above(a).where("block = 100").collect()} == set(range(100, 108))


@pytest.mark.parametrize("n, joined", [(200_000, "SortMergeJoin"), (10, "BroadcastHashJoin")])
def test_stored_rows_are_not_broadcast_by_the_size_of_their_files(spark, n, joined):
    row = lambda: spark.range(n).select(F.floor(F.col("id") / 8).alias("k"), F.format_string("o%d.js", F.floor(F.col("id") / 50_000)).alias("path"), F.lit("orders").alias("container"))
    a, b = written(row(), "left"), written(row().withColumnRenamed("path", "other"), "right")
    both = a.where("k >= 0").join(b.select("k", "other"), "k")
    assert both.count() == sum(min(8, n - k) ** 2 for k in range(0, n, 8))
    assert joined in both._jdf.queryExecution().sparkPlan().toString()


@pytest.mark.parametrize("name", ["basic_blocks", "container_hierarchy", "relationship_types", "schema_except", "schema_intersect", "singular_names", "sql_frontend"])
def test_query_needs_its_table(spark, tmp_path, name):
    with pytest.raises(AnalysisException):
        Q.QUERIES[name](spark, str(tmp_path)).collect()


def test_catalog_counts_the_values_of_tables(spark):
    rows = spark.createDataFrame([(1, None), (2, "a"), (3, "b")], "k long, v string")
    got = profile.catalog({"t": rows, "empty": rows.where("k > 3")}).collect()
    assert {tuple(r) for r in got} == {("t", "k", "bigint", 3), ("t", "v", "string", 2), ("empty", "k", "bigint", 0), ("empty", "v", "string", 0)}


@pytest.mark.parametrize("name, some", [("catalog_columns", TABLES), ("references_by_name", TABLES), ("references_by_name_shop", ["customer", "orders", "lineitem", "part", "supplier", "events", "documents"])])
def test_catalog_queries_read_rows(spark, name, some, monkeypatch):
    seen = []
    monkeypatch.setattr(profile, "written", lambda df, label: seen.append(df) or written(df, label))
    Q.QUERIES[name](spark, SF)
    assert {f"{t}.parquet" for t in some} <= {f.rsplit("/", 1)[-1] for f in seen[0].inputFiles()}


def test_what_a_walk_knows_is_not_broadcast(spark, monkeypatch):
    """Not even after the first round, when unions hide the stored tables from the planner."""
    plans = []
    monkeypatch.setattr(access, "written", lambda df, label: label == "held" and plans.append(df._jdf.queryExecution().sparkPlan().toString()) or written(df, label))
    m = Models(files(spark, "async function f(db) { const a = await db.collection('c').findOne({}); const b = a; const d = b; use(d.x); }"))
    assert reach(m, written(find_operations(m), "ops")).where("var = 'd@1'").count() == 1
    assert len(plans) > 2 and not any("LeftOuter, BuildRight" in p for p in plans)
