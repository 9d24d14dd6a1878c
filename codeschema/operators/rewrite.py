"""Rewriting programs: regeneration from the code model, and removal of a join query from its code."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..frontend.inject import Injector, inject
from ..frontend.parser import Node, ParseError
from ..frontend.tokens import LexError, tokenize
from ..store import written
from .models import Models


def regenerate(m: Models) -> DataFrame:
    """The text of each file from its top statements in the code model."""
    top = m.elements.where("kind <> 'block'").join(m.elements.where("kind = 'block' and parent = -1").select("app_id", "version", "path", F.col("elem").alias("parent")), ["app_id", "version", "path", "parent"])
    g = top.groupBy("app_id", "version", "path").agg(F.array_sort(F.collect_list(F.struct("ord", "text"))).alias("s"))
    return g.select("app_id", "version", "path", F.array_join(F.transform("s", lambda x: x["text"]), "\n").alias("content"))


def roundtrip_diff(files: DataFrame, m: Models) -> DataFrame:
    """Files whose regenerated tokens differ from the original's (files that can't be parsed aside)."""

    def same(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for old, new in zip(batch.column(1).to_pylist(), batch.column(2).to_pylist(), strict=True):
                keep.append([t.text for t in tokenize(old)] != [t.text for t in tokenize(new or "")])
            yield batch.filter(pa.array(keep, pa.bool_()))

    good = files.join(m.errors().select("app_id", "version", "path"), ["app_id", "version", "path"], "left_anti").select("app_id", "version", "path", "content")
    both = good.join(regenerate(m).withColumnRenamed("content", "again"), ["app_id", "version", "path"], "left").select("path", "content", "again")
    return both.mapInArrow(same, "path string, content string, again string").select("path")


class _Map(Injector):
    """The code model of a text, with the places of its paths, nodes, statements and functions."""

    def __init__(self, text: str) -> None:
        self.paths: dict[tuple[int, int], tuple[str, list]] = {}
        self.node_of: dict[int, Node] = {}
        self.statement_of: dict[int, Node] = {}
        self.function_of: dict[int, Node] = {}
        super().__init__(text)

    def path(self, n: Node):
        found = super().path(n)
        if found is not None and n.kind in ("name", "member", "index"):
            self.paths[self.span(n)] = found
        return found

    def node(self, kind: str, where: dict, n: Node) -> int:
        seq = super().node(kind, where, n)
        self.node_of[seq] = n
        return seq

    def element(self, n: Node, *args, **kwargs) -> int:
        e = super().element(n, *args, **kwargs)
        self.statement_of[e] = n
        return e

    def callable(self, f: Node, *args) -> int:
        unit = super().callable(f, *args)
        self.function_of[unit] = f
        return unit


class _Refused(Exception):
    """A change that can't be made without a look by a person."""


@dataclass(frozen=True)
class Removal:
    """What a plan asks of one file: ``host`` and ``result`` are resolved variables (``name@unit``); ``as_field`` names the
    field that a pipeline's lookup makes."""

    seq: int
    host: str | None
    result: str | None
    inside: str | None
    fields: tuple[str, ...]
    names: tuple[str, ...]
    many: bool
    as_field: str | None = None


def duplicate_name(names: list[str] | tuple[str, ...]) -> str:
    """The field that holds the duplicate: the single name, or one for an object of several."""
    return names[0] if len(names) == 1 else f"{names[0].partition('_')[0]}_info"


class _Editor:
    def __init__(self, text: str, r: Removal) -> None:
        self.text, self.r, self.m = text, r, _Map(text)
        self.edits: list[tuple[int, int, str]] = []
        rows = self.m.rows
        self.calls = {c["seq"]: c for c in rows["calls"]}
        if r.seq not in self.calls:
            raise _Refused("the query isn't there")
        self.chain = [c for c in rows["calls"] if c["chain"] == self.calls[r.seq]["chain"]]
        self.loops = {self.m.span(self.m.node_of[n["seq"]]) for n in rows["nodes"] if n["kind"] == "loop"}

    def statement(self, seq: int) -> Node:
        return self.m.statement_of[self.m.rows["nodes"][seq]["elem"]]

    def drop_statement(self, n: Node) -> None:
        a, b = self.m.span(n)
        while a and self.text[a - 1] in " \t":
            a -= 1
        if b < len(self.text) and self.text[b] == "\n" and (not a or self.text[a - 1] == "\n"):
            b += 1
        self.edits.append((a, b, ""))

    # -- the query ---------------------------------------------------------------------------------
    def drop_query(self) -> None:
        unit = next((c["callback"] for c in self.chain if c["callback"] is not None), None)
        if unit is not None:
            return self.unwrap(unit)
        n = self.statement(self.chain[0]["seq"])
        kind = self.m.rows["nodes"][self.calls[self.r.seq]["result_seq"]]["kind"] if self.calls[self.r.seq]["result_seq"] is not None else ""
        if kind not in ("decl", "assign") or n.kind == "decl" and len(n.kids) != 1:
            raise _Refused("the result isn't simply assigned")
        self.drop_statement(n)

    def unwrap(self, unit: int) -> None:
        """The statement of the query gives way to the body of its callback."""
        f, n = self.m.function_of[unit], self.statement(self.chain[0]["seq"])
        others = {f"{p.name}@{unit}" for p in f.value if p.kind == "name"} - {self.r.result}
        if any(v in others for v, _ in self.m.paths.values()):
            raise _Refused("another argument of the callback is used")
        (a, b), (c, d) = self.m.span(n), self.m.span(f.kids[0])
        braces = self.text[c : c + 1] == "{"
        if not braces:
            self.edits += [(a, c, ""), (d, b, ";")]
            return
        while self.text[c + 1 : c + 2].isspace():
            c += 1
        while self.text[d - 2 : d - 1].isspace():
            d -= 1
        self.edits += [(a, c + 1, ""), (d - 1, b, "")]

    def drop_stage(self) -> None:
        """The lookup's stage, and the one that unwinds it, leave the pipeline."""
        call = self.m.node_of[self.r.seq]
        stages = call.kids[1].kids if len(call.kids) > 1 and call.kids[1].kind == "array" else []
        inner = lambda n, key: next((p.kids[0] for p in n.kids if p.name == key), None)
        gone, kept, name = [], [], self.r.as_field
        for i, s in enumerate(stages):
            look, unwind = (inner(s, "$lookup"), inner(s, "$unwind")) if s.kind == "object" else (None, None)
            said = look and look.kind == "object" and inner(look, "as")
            if unwind is not None and unwind.kind == "object":
                unwind = inner(unwind, "path")
            if said and said.value == name or unwind is not None and unwind.kind == "literal" and unwind.value == f"${name}":
                gone.append(i)
            else:
                kept.append(self.m.slice(s))
        if not gone or any(re.search(rf"[$'\"\s{{,.]{re.escape(name)}\b", x) for x in kept):
            raise _Refused("another stage uses what the lookup makes")
        if not kept:
            self.edits.append((*self.m.span(call.kids[1]), "[]"))
            return
        for i in gone:
            a, b = self.m.span(stages[i])
            if i + 1 < len(stages):
                b = self.m.span(stages[i + 1])[0]
            elif any(k not in gone for k in range(i)):
                a = self.m.span(stages[max(k for k in range(i) if k not in gone)])[1]
            self.edits.append((a, b, ""))

    # -- accesses -----------------------------------------------------------------------------------
    def holders(self, start: dict[str, list]) -> dict[str, list]:
        """Variables that hold a part of what ``start`` holds, with the steps that lead there."""
        held, grown = dict(start), True
        while grown:
            grown = False
            for a in self.m.rows["aliases"]:
                if a["root"] in held and a["lhs"] not in held and a["seq"] >= self.r.seq:
                    held[a["lhs"]], grown = held[a["root"]] + a["steps"], True
        return held

    def field_at(self, steps: list) -> tuple[str, int] | None:
        """The duplicated field that a path of steps leads to, and after how many steps."""
        for f in sorted(self.r.fields, key=len, reverse=True):
            want, at = f.split("."), 0
            for i, s in enumerate(steps):
                if s["kind"] == "index" and at == 0:
                    continue
                if s["kind"] != "prop" or s["name"] != want[at]:
                    break
                at += 1
                if at == len(want):
                    return f, i + 1
        return None

    def replace_accesses(self) -> None:
        r = self.r
        joined = self.holders({r.result: []}) if r.result else {}
        host = {}
        if r.as_field:
            host = self.holders({r.host: []})
            through = {v: s for v, s in host.items() if any(x["kind"] == "prop" and x["name"] == r.as_field for x in s)}
            for v, s in through.items():
                joined[v] = s[next(i for i, x in enumerate(s) if x["name"] == r.as_field) + 1 :]
                del host[v]
        longest: dict[int, int] = {}
        for a, b in self.m.paths:
            longest[a] = max(b, longest.get(a, 0))
        for a, b in longest.items():
            var, steps = self.m.paths[a, b]
            ends = {len(s): e for (x, e), (v, s) in self.m.paths.items() if x == a and v == var}
            if var in joined:
                self.access(a, b, ends, joined[var], steps, 0, a)
            elif var in host:
                names = [x["name"] if x["kind"] == "prop" else "" for x in steps]
                if r.as_field in names:
                    at = names.index(r.as_field)
                    self.access(a, b, ends, [], steps, at + 1, ends[at])

    def access(self, a: int, b: int, ends: dict[int, int], before: list, steps: list, at: int, begin: int) -> None:
        """One place that holds a part of the joined data.

        ``before``: steps that led to its variable; ``at``: how many of its own lead to the joined data; ``begin``: from where the
        text gives way to the duplicate.
        """
        r, rest = self.r, steps[at:]
        field = self.field_at(before + rest)
        if field and field[1] <= len(before):
            return  # a variable that holds the field's value already
        base = "" if at else "".join([r.host.partition("@")[0]] if r.host else [])
        put = lambda name: f"{base}.{r.inside}.{name}" if r.inside and not at else f"{base}.{name}"
        name, several = duplicate_name(r.names), len(r.names) > 1
        if not r.many:
            if field is None:
                raise _Refused(f"{self.text[a:b]} is not a duplicated field")
            f, n = field
            end = ends[at + n - len(before)]
            self.edits.append((begin, end, put(f"{name}.{f}" if several else name)))
            return
        if several and any("." in f for f in r.fields):
            raise _Refused("nested fields in an array")
        if not before:  # the whole array
            method = re.match(r"\s*\??\.\s*[\w$]+\s*\(", self.text[b:]) if not rest else None
            if not (method or rest and (rest[0]["kind"] == "index" or rest[0]["name"] == "length") or not rest and (a, b) in self.loops):
                raise _Refused(f"{self.text[a:b]} is used as a whole")
            self.edits.append((begin, ends[at], put(name)))
            if rest and rest[0]["kind"] == "index":
                if field is None:
                    raise _Refused(f"{self.text[a:b]} is not a duplicated field")
                if not several:
                    self.edits.append((ends[at + 1], ends[at + field[1]], ""))
            return
        if field is None:
            raise _Refused(f"{self.text[a:b]} is not a duplicated field")
        if not several:
            self.edits.append((ends[at], ends[at + field[1] - len(before)], ""))

    def result(self) -> str:
        if self.r.as_field:
            self.drop_stage()
        else:
            self.drop_query()
        self.replace_accesses()
        gone = [(a, b) for a, b, put in self.edits if not put]
        out, done = [], 0
        for a, b, put in sorted(set(self.edits)):
            if put and any(x <= a and b <= y for x, y in gone):
                continue
            if a < done:
                if b <= done:
                    continue
                raise _Refused("two changes meet")
            out += [self.text[done:a], put]
            done = b
        new = "".join([*out, self.text[done:]])
        self.check(new)
        return new

    def check(self, new: str) -> None:
        """The new text can be read, has one query or stage less, and names nothing that is gone."""
        m = _Map(new)
        asked = lambda x: sum(c["container"] is not None for c in x.rows["calls"])
        if not self.r.as_field and asked(m) != asked(self.m) - len([c for c in self.chain if c["container"] is not None]):
            raise _Refused("another query changed")
        name = (self.r.result or "").partition("@")[0]
        if name and any(v == f"{name}@0" for v, _ in m.paths.values()) and not any(v == f"{name}@0" for v, _ in self.m.paths.values()):
            raise _Refused(f"{name} is still used")


def remove_join_text(content: str, r: Removal) -> tuple[str, bool]:
    """(text without the join query, whether it was refused and left as it is).

    A query with a callback gives way to the callback's body, one whose result is assigned goes with its statement, a
    pipeline loses its stage.  Accesses to fields of the result, found by resolved names at their own places, become
    accesses to the host's duplicates; whatever else uses the result makes the change be refused.
    """
    try:
        return _Editor(content, r).result(), False
    except (_Refused, ParseError, LexError):
        return content, True


def apply_to_code(files: DataFrame, plans: DataFrame, ops: DataFrame) -> DataFrame:
    """Files of the plans with their join queries removed: (app_id, version, path, content, lang, review).

    Plans of one file are applied one after the other, the last query first, so places stay right.  ``review``: some plan of
    the file couldn't be applied and its query is still there.  Joins over several functions' files are such plans.
    """
    o = ops.select("app_id", "version", "path", "op", "result_var", "as_field", "multi")
    p = plans.join(o.select("app_id", "version", F.col("path").alias("prev_path"), F.col("op").alias("prev_op"), F.col("result_var").alias("host_var"), F.col("multi").alias("host_many")), ["app_id", "version", "prev_path", "prev_op"])
    p = p.join(o.select("app_id", "version", "path", F.col("op").alias("next_op"), "result_var", "as_field"), ["app_id", "version", "path", "next_op"])
    item = F.struct((-F.col("next_op")).alias("order"), F.floor(F.col("next_op") / 100).cast("int").alias("seq"), "host_var", "result_var", "as_field", ((F.col("prev_path") != F.col("path")) | F.col("host_many") & F.col("as_field").isNull()).alias("apart"), "inside", "fields", "names", F.col("shape").startswith("array").alias("many"))
    grouped = p.groupBy("app_id", "version", "path").agg(F.array_sort(F.collect_list(item)).alias("todo"))
    rows = files.join(grouped, ["app_id", "version", "path"]).select("app_id", "version", "path", "content", "lang", "todo")

    schema = pa.schema([("app_id", pa.string()), ("version", pa.int32()), ("path", pa.string()), ("content", pa.string()), ("lang", pa.string()), ("review", pa.bool_())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = []
            for r in batch.to_pylist():
                text, review = r["content"], False
                for t in r["todo"]:
                    look = t["apart"]
                    if not look:
                        text, look = remove_join_text(text, Removal(t["seq"], t["host_var"], None if t["as_field"] else t["result_var"], t["inside"], tuple(t["fields"]), tuple(t["names"]), t["many"], t["as_field"]))
                    review = review or look
                out.append((r["app_id"], r["version"], r["path"], text, r["lang"], review))
            yield pa.RecordBatch.from_pylist([dict(zip(schema.names, x, strict=True)) for x in out], schema=schema)

    return rows.mapInArrow(run, "app_id string, version int, path string, content string, lang string, review boolean")


def analyze_incremental(previous: DataFrame, files: DataFrame) -> DataFrame:
    """Only files whose content is new or changed since ``previous`` (path and hash): what has to be analysed again."""
    return files.join(previous.select("app_id", "version", "path", "sha"), ["app_id", "version", "path", "sha"], "left_anti")


def merged_models(previous: Models, files: DataFrame) -> Models:
    """The models of ``files`` when ``previous`` is known: new and changed files are parsed, unchanged ones keep their rows,
    deleted ones lose them."""
    key = ["app_id", "version", "path"]
    changed = analyze_incremental(previous.files, files)
    same = files.select(*key, "sha").join(previous.files.select(*key, "sha"), [*key, "sha"], "left_semi").select(*key)
    return Models(files, written(previous.model.join(same, key, "left_semi").unionByName(inject(changed)), "model"))
