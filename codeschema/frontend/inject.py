"""From parsed files to code-model rows: elements, nodes in source order, uses, aliases, calls and their arguments.

Names are resolved to the unit that declares them (``name@unit``), so callbacks that reuse a name stay apart.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql.pandas.types import to_arrow_schema

from ..schema import MODEL
from .parser import INNER, Node, ParseError, Parser
from .shapes import Shapes
from .tokens import LexError

COMPARE = {"==", "===", "!=", "!==", "<", ">", "<=", ">="}
ARITHMETIC = {"*", "/", "-", "**", "%", "*=", "/=", "-="}
#: Methods that hand on the elements of what they are called on, and ones that show a collection.
ITERATES = {"forEach", "map", "filter", "some", "every", "find", "flatMap", "reduce"}
COLLECTS = {"push", "pop", "shift", "unshift", "splice", "join", "sort", "reverse", "at", "entries", "keys", "values", "forEach", "map", "filter", "some", "every", "flatMap", "reduce"}
CURSOR = {"toArray", "next", "sort", "limit", "skip", "project", "exec", "lean", "hasNext"}
TEXT_METHODS = {"toUpperCase", "toLowerCase", "trim", "startsWith", "endsWith", "substring", "charAt", "padStart", "padEnd", "match", "replace"}
_SCRIPT = re.compile(r"<script[^>]*>(.*?)</script>", re.S | re.I)

Steps = list[dict]
MODEL_CHARS = 1_000_000  # of texts whose models are held at once


class Injector:
    def __init__(self, text: str) -> None:
        self.text = text
        parser = Parser(text)
        self.tree, self.tokens, self.inner = parser.program(), parser.tokens, parser.inner
        self.rows: dict[str, list[dict]] = {k: [] for k in ("units", "elements", "nodes", "uses", "aliases", "calls", "args", "resolved")}
        self.scopes: list[tuple[int, dict[str, str]]] = []
        self.constants: dict[str, str] = {}
        self.handles: dict[str, str] = {}
        self.functions: dict[str, int] = {}
        self.modules: set[str] = set()  # variables that hold another file's exports
        self.n_chain = 0
        self.new_unit(-1, "script", "", None, [])
        self.scopes.append((0, {}))
        self.hoist(self.tree.kids)
        self.block(self.tree, 0, -1, [], [])

    # -- rows ----------------------------------------------------------------------------------
    def new_unit(self, parent: int, kind: str, name: str, call: int | None, params: list[str]) -> int:
        self.rows["units"].append({"unit": len(self.rows["units"]), "parent": parent, "kind": kind, "name": name, "call_seq": call, "params": params})
        return len(self.rows["units"]) - 1

    def token(self, i: int):
        return self.tokens[min(max(i, 0), len(self.tokens) - 1)] if i < INNER else self.inner[min(i - INNER, len(self.inner) - 1)]

    def span(self, n: Node) -> tuple[int, int]:
        """Where a node stands in the text."""
        if n.b <= n.a or n.a >= len(self.tokens) and n.a < INNER:
            return 0, 0
        last = self.token(n.b - 1)
        return self.token(n.a).start, last.start + len(last.text)

    def slice(self, n: Node) -> str:
        a, b = self.span(n)
        return self.text[a:b]

    def line(self, i: int) -> int:
        return self.token(i).line if self.tokens else 1

    def element(self, n: Node, parent: int, unit: int, block: int, order: int, kind: str | None = None) -> int:
        e = len(self.rows["elements"])
        lit = n.value if n.kind == "literal" else None
        self.rows["elements"].append({"elem": e, "parent": parent, "unit": unit, "block": block, "ord": order, "kind": kind or n.kind, "name": n.name, "literal": lit, "literal_type": n.name if n.kind == "literal" else None, "line_from": self.line(n.a), "line_to": self.line(n.b - 1), "text": self.slice(n)})
        return e

    def node(self, kind: str, where: dict, n: Node) -> int:
        seq = len(self.rows["nodes"])
        self.rows["nodes"].append({"seq": seq, "unit": where["unit"], "block": where["block"], "elem": where["elem"], "kind": kind, "branch": list(where["branch"]), "loops": list(where["loops"]), "line": self.line(n.a), "text": self.slice(n)[:400]})
        return seq

    # -- names ---------------------------------------------------------------------------------
    def declare(self, name: str, unit: int) -> str:
        for u, names in reversed(self.scopes):
            if u == unit:
                names[name] = f"{name}@{unit}"
                return names[name]
        return f"{name}@{unit}"

    def resolve(self, name: str) -> str:
        for _, names in reversed(self.scopes):
            if name in names:
                return names[name]
        return f"{name}@0"

    def hoist(self, statements: list[Node]) -> None:
        for s in statements:
            if s.kind == "function" and s.name:
                self.declare(s.name, self.scopes[-1][0])

    # -- paths ---------------------------------------------------------------------------------
    def path(self, n: Node) -> tuple[str, Steps] | None:
        """(variable, steps) of a pure access path, else None."""
        if n.kind == "name":
            return self.resolve(n.name), []
        if n.kind in ("member", "index"):
            base = self.path(n.kids[0])
            if base:
                key = n.kids[1] if n.kind == "index" else None
                if key is not None and key.kind == "literal" and key.name == "string":
                    return base[0], [*base[1], {"name": key.value, "kind": "prop"}]
                return base[0], [*base[1], {"name": n.name, "kind": "prop"} if n.kind == "member" else {"name": "[]", "kind": "index"}]
        if n.kind == "await":
            return self.path(n.kids[0])
        if n.kind == "call" and n.kids[0].kind == "member":  # a method on a path goes on as a step
            base = self.path(n.kids[0].kids[0])
            if base:
                return base[0], [*base[1], {"name": n.kids[0].name, "kind": "method"}]
        return None

    def use(self, seq: int, where: dict, found: tuple[str, Steps], role: str, literal_type: str | None = None) -> None:
        self.rows["uses"].append({"seq": seq, "elem": where["elem"], "block": where["block"], "root": found[0], "steps": found[1], "role": role, "literal_type": literal_type})

    def alias(self, seq: int, lhs: str, found: tuple[str, Steps] | None) -> None:
        self.rows["aliases"].append({"seq": seq, "lhs": lhs, "root": found[0] if found else None, "steps": found[1] if found else []})

    # -- statements ----------------------------------------------------------------------------
    def block(self, n: Node, unit: int, parent: int, branch: list[str], loops: list[int]) -> int:
        b = self.element(n, parent, unit, -1, 0, "block")
        self.rows["elements"][b]["block"] = b
        self.hoist(n.kids)
        for i, s in enumerate(n.kids):
            self.statement(s, {"unit": unit, "block": b, "branch": branch, "loops": loops}, b, i)
        return b

    def statement(self, n: Node, where: dict, parent: int, order: int) -> None:
        where = {**where, "elem": self.element(n, parent, where["unit"], where["block"], order)}
        unit, e, branch, loops = where["unit"], where["elem"], where["branch"], where["loops"]
        kind = n.kind
        if kind in ("empty", "break", "continue"):
            self.node("other", where, n)
        elif kind == "block":
            self.block(n, unit, e, branch, loops)
        elif kind == "decl":
            for bind in n.kids:
                self.bind(bind, where)
        elif kind == "function":
            self.callable(n, where, None, n.name)
        elif kind == "class":
            for f in n.kids:
                if f.kind == "function":
                    self.callable(f, where, None, f.name)
        elif kind == "if":
            seq = self.node("selection", where, n.kids[0])
            self.expression(n.kids[0], seq, where, "cond")
            for label, body in zip(("T", "F"), n.kids[1:]):
                self.block(body, unit, e, [*branch, f"{e}:{label}"], loops)
        elif kind in ("while", "for"):
            if kind == "for" and n.kids[0].kind == "decl":
                self.statement(n.kids[0], where, e, 0)
            seq = self.node("loop", where, n)
            for part in n.kids[:-1]:
                if part.kind not in ("none", "decl"):
                    self.expression(part, seq, where, "cond")
            self.block(n.kids[-1], unit, e, branch, [*loops, e])
        elif kind in ("forof", "forin"):
            seq = self.node("loop", where, n.kids[1])
            over = n.kids[1]
            found = self.path(over)
            call = self.expression(over, seq, where, "read")
            var = self.pattern(n.kids[0], seq, where, None if kind == "forin" or not found else (found[0], [*found[1], {"name": "[]", "kind": "index"}]))
            if call is not None and var:
                self.result(call, var, True, seq)
            self.block(n.kids[2], unit, e, branch, [*loops, e])
        elif kind == "return":
            seq = self.node("return", where, n)
            for k in n.kids:
                call, core = self.expression(k, seq, where, "read"), k.kids[0] if k.kind == "await" else k
                if call is not None:
                    self.result(call, f"return@{unit}", False, None)
                elif core.kind in ("name", "member", "index"):
                    self.alias(seq, f"return@{unit}", self.path(core))
        elif kind == "try":
            for body in n.kids:
                self.block(body, unit, e, branch, loops)
        elif kind == "expr" and n.kids[0].kind == "assign":
            self.assign(n.kids[0], where)
        elif kind == "other":
            self.node("other", where, n)
        else:
            inner = n.kids[0] if n.kids else n
            if inner.kind in ("call", "await"):
                self.expression(inner, None, where, "read")
            else:
                self.expression(inner, self.node("other", where, n), where, "read")

    def bind(self, n: Node, where: dict) -> None:
        target, value = n.kids
        self.value(target, value, where, n, "decl")

    def assign(self, n: Node, where: dict) -> None:
        target, value = n.kids
        if target.kind == "member" and value.kind == "function" and n.name == "=":  # a method, or what a file exports
            self.node("assign", where, n)
            self.callable(value, where, None, target.name)
            return
        if target.kind == "name" and n.name == "=":
            self.value(target, value, where, n, "assign")
            return
        seq = self.node("assign", where, n)
        found = self.path(target)
        if found and target.kind != "name":
            self.use(seq, where, found, "write", "double" if n.name in ARITHMETIC else value.name if value.kind == "literal" else None)
        elif found and value.kind != "literal":
            self.alias(seq, found[0], self.path(value))
        self.expression(value, seq, where, "read")

    def value(self, target: Node, value: Node, where: dict, n: Node, kind: str) -> None:
        """A declaration or assignment of a variable."""
        unit = where["unit"]
        core = value.kids[0] if value.kind == "await" else value
        if value.kind == "function":
            name = self.declare(target.name, unit) if target.kind == "name" else ""
            self.callable(value, where, None, name.partition("@")[0])
            return
        handle = self.container_of(core)
        if target.kind == "name" and kind == "decl":
            var = self.declare(target.name, unit)
            if core.kind == "literal" and core.name == "string":
                self.constants[var] = core.value
            if handle is not None and core.kind == "call" and core.kids[0].name == "collection":
                self.handles[var] = handle
            if core.kind == "call" and core.kids[0].kind == "name" and core.kids[0].name == "require":
                self.modules.add(var)
        if core.kind == "call":
            call = self.expression(core, None, where, "read")
            seq = self.node(kind, where, n)
            found = self.path(core)
            tracked = found if found and found[1] and found[1][-1]["kind"] == "method" and not self.op_chain(core) else None
            var = self.pattern(target, seq, where, None if not tracked else (tracked[0], [*tracked[1][:-1], *self.handed(tracked[1][-1])]))
            if call is not None and var:
                self.result(call, var, False, seq)
            return
        seq = self.node(kind, where, n)
        self.expression(value, seq, where, "read")
        self.pattern(target, seq, where, self.path(value) if value.kind != "none" else None)

    @staticmethod
    def handed(step: dict) -> Steps:
        """What a method's result is of the thing it is called on."""
        return [{"name": "[]", "kind": "index"}] if step["name"] in ("find", "pop", "shift", "at") else [] if step["name"] in ("filter", "slice", "sort", "reverse") else [step]

    def pattern(self, target: Node, seq: int, where: dict, found: tuple[str, Steps] | None) -> str | None:
        """Declares the names of a target and links them to what is assigned; the variable, if it is a plain name."""
        unit = where["unit"]
        if target.kind == "name":
            known = self.resolve(target.name)
            var = known if any(target.name in names for _, names in self.scopes) else self.declare(target.name, unit)
            self.alias(seq, var, found)
            return var
        whole = f"#{seq}@{unit}"
        self.alias(seq, whole, found)
        for part in target.kids:
            step = [] if part.name == "..." else [{"name": "[]", "kind": "index"}] if part.name == "[]" else [{"name": part.name, "kind": "prop"}]
            if step:
                self.use(seq, where, (whole, step), "read")
            if part.value:
                self.alias(seq, self.declare(part.value, unit), (whole, step))
            for inner in part.kids:
                self.pattern(inner, seq, where, (whole, step))
        return whole

    def result(self, call: int, var: str, element: bool, seq: int | None) -> None:
        """What a chain's result is held by, and the node at which it is from then on; callbacks have it already."""
        for row in reversed(self.rows["calls"]):
            if row["chain"] == call and (seq is not None or row["result"] is None):
                row["result"], row["element"], row["result_seq"] = var, element, seq

    # -- expressions ---------------------------------------------------------------------------
    def container_of(self, n: Node) -> str | None:
        """The container named by the nearest ``collection(x)`` step of a call chain, or by a variable that holds one;
        ``?`` and the variable where only a caller can know its name."""
        while n.kind in ("call", "member", "await"):
            if n.kind == "call" and n.kids[0].kind == "member" and n.kids[0].name == "collection" and len(n.kids) > 1:
                arg = n.kids[1]
                if arg.kind == "literal":
                    return str(arg.value)
                if arg.kind == "name":
                    var = self.resolve(arg.name)
                    return self.constants.get(var, f"?{var}")
                return "?"
            n = n.kids[0]
        return self.handles.get(self.resolve(n.name)) if n.kind == "name" else None

    def op_chain(self, n: Node) -> bool:
        return self.container_of(n) is not None

    def callable(self, f: Node, where: dict, call: int | None, name: str) -> int:
        unit = self.new_unit(where["unit"], "function" if call is None else "callback", name, call, [p.name for p in f.value])
        if call is None and name:
            self.functions[name] = unit
        self.scopes.append((unit, {}))
        for p in f.value:
            if p.kind == "name":
                self.declare(p.name, unit)
        inner = {**where, "unit": unit}
        for p in f.value:
            if p.kind != "name":
                self.pattern(p, len(self.rows["nodes"]), inner, None)
        self.block(f.kids[0], unit, where["elem"], where["branch"], where["loops"])
        self.scopes.pop()
        return unit

    def expression(self, n: Node, seq: int | None, where: dict, role: str, literal_type: str | None = None) -> int | None:
        """Rows for an expression at node ``seq``; the chain's number if it is a call chain."""
        kind = n.kind
        if kind in ("none", "literal"):
            return None
        if kind == "call":
            return self.chain(n, where)
        if kind == "await":
            return self.expression(n.kids[0], seq, where, role)
        if kind in ("name", "member", "index"):
            found = self.path(n)
            if found is not None:
                self.use(seq if seq is not None else len(self.rows["nodes"]) - 1, where, found, role, literal_type)
                for k in self.indexes(n):
                    self.expression(k, seq, where, "read")
            else:
                for k in n.kids:
                    self.expression(k, seq, where, role)
            return None
        if kind == "binary":
            left, right = n.kids
            for one, other in ((left, right), (right, left)):
                t = None
                if n.name in COMPARE and other.kind == "literal":
                    t = other.name
                elif n.name in ARITHMETIC:
                    t = "double"
                self.expression(one, seq, where, role, t)
            return None
        if kind == "function":
            self.callable(n, where, len(self.rows["nodes"]) - 1, "")
            return None
        if kind == "assign":
            found = self.path(n.kids[0])
            if found and seq is not None:
                self.use(seq, where, found, "write", n.kids[1].name if n.kids[1].kind == "literal" else None)
            return self.expression(n.kids[1], seq, where, "read")
        for k in n.kids:
            self.expression(k, seq, where, role)
        return None

    def indexes(self, n: Node) -> list[Node]:
        out = []
        while n.kind in ("member", "index", "call", "await"):
            if n.kind == "index" and n.kids[1].kind != "literal":
                out.append(n.kids[1])
            n = n.kids[0]
        return out

    def chain(self, n: Node, where: dict) -> int:
        """A node and a call row for each chained call, first call first; callbacks follow their call."""
        steps: list[Node] = []
        base = n
        while base.kind in ("call", "member", "index", "await"):
            if base.kind == "call":
                steps.append(base)
            base = base.kids[0]
        steps.reverse()
        number = self.n_chain
        self.n_chain += 1
        container = self.container_of(n)
        receiver = self.resolve(base.name) if base.kind == "name" else None
        if base.kind not in ("name", "literal"):
            self.expression(base, len(self.rows["nodes"]) - 1 if self.rows["nodes"] else None, where, "read")
        for pos, call in enumerate(steps):
            head = call.kids[0]
            name = head.name if head.kind in ("member", "name") else ""
            seq = self.node("call", where, call)
            row = {"seq": seq, "unit": where["unit"], "chain": number, "pos": pos, "name": name, "n_chain": len(steps), "container": container[:1] if container and container[0] == "?" else container, "container_var": container[1:] or None if container and container[0] == "?" else None, "receiver": receiver, "result": None, "result_seq": None, "element": False, "callback": None, "text": self.slice(call)[:400]}
            self.rows["calls"].append(row)
            inner = head.kids[0] if head.kind == "member" else None
            own = inner is not None and container is None and inner.kind == "name" and (inner.name == "this" or self.resolve(inner.name) in self.modules)
            if head.kind == "name" or own:
                self.rows["resolved"].append({"seq": seq, "callee": name})
            holder = self.path(head.kids[0]) if head.kind == "member" else None
            if holder and container is None:  # a method of a variable that may hold stored objects
                self.use(seq, where, (holder[0], [*holder[1], {"name": name, "kind": "method"}]), "read", "string" if name in TEXT_METHODS else None)
            elif head.kind == "member" and pos == 0:
                for k in self.indexes(head):
                    self.expression(k, seq, where, "read")
            for i, arg in enumerate(call.kids[1:]):
                if arg.kind == "function":
                    self.callback(arg, seq, row, where, holder, container is not None, name, steps[pos - 1].kids[0].name if pos else "")
                else:
                    self.argument(arg, seq, i, "", where)
                    self.expression(arg, seq, where, "arg")
        return number

    def callback(self, f: Node, seq: int, row: dict, where: dict, holder, stored: bool, name: str, before: str) -> None:
        """The unit of a function argument, with its data parameter linked to what it receives."""
        names = [p.name if p.kind == "name" else "" for p in f.value]
        unit = len(self.rows["units"])
        data = None
        if names:
            at = 1 if len(names) > 1 and name not in ITERATES and name != "then" else 0
            if name == "reduce" and len(names) > 1:
                at = 1
            target = f.value[at]
            data = f"{target.name}@{unit}" if target.kind == "name" else f"#{seq}@{unit}"
            if stored:
                if before or name not in ITERATES:
                    row["result"], row["element"], row["callback"] = data, name in ITERATES, unit
                    for other in self.rows["calls"]:
                        if other["chain"] == row["chain"] and other["result"] is None:
                            other["result"], other["element"], other["callback"] = data, name in ITERATES, unit
            elif holder and name in ITERATES:
                self.alias(seq, data, (holder[0], [*holder[1], {"name": "[]", "kind": "index"}]))
        row["callback"] = unit
        made = self.callable(f, where, seq, "")
        if names and data and data.startswith("#"):
            target = f.value[1 if len(names) > 1 and name not in ITERATES else 0]
            for part in target.kids:
                step = [{"name": part.name, "kind": "prop"}]
                self.use(seq, where, (data, step), "read")
                if part.value:
                    self.alias(seq, f"{part.value}@{made}", (data, step))

    def argument(self, n: Node, seq: int, arg: int, key: str, where: dict) -> None:
        """Objects and arrays in arguments, flattened to (key path, access path or literal)."""
        if n.kind == "object":
            for p in n.kids:
                self.argument(p.kids[0], seq, arg, f"{key}.{p.name}".lstrip("."), where)
            return
        if n.kind == "array":
            for i, k in enumerate(n.kids):
                self.argument(k, seq, arg, f"{key}.{i}".lstrip("."), where)
            return
        found = self.path(n) if n.kind != "literal" else None
        literal = str(n.value) if n.kind == "literal" and n.value is not None else None
        if found is None and n.kind == "name":
            found = (self.resolve(n.name), [])
        self.rows["args"].append({"seq": seq, "arg": arg, "key": key, "root": found[0] if found else None, "steps": found[1] if found else [], "literal": literal, "literal_type": n.name if n.kind == "literal" else None})


def inject_text(content: str | None, lang: str | None = "js") -> tuple[dict[str, list[dict]], str | None]:
    """(rows, error) of one file; an HTML page gives the rows of its scripts."""
    text = content or ""
    if lang == "html":
        text = "\n;\n".join(_SCRIPT.findall(text))
    try:
        return Injector(text).rows, None
    except (ParseError, LexError, RecursionError) as e:
        return {k: [] for k in ("units", "elements", "nodes", "uses", "aliases", "calls", "args", "resolved")}, str(e) or type(e).__name__


def inject(files: DataFrame, extra: str = "") -> DataFrame:
    """A model row for each file (``schema.MODEL``): map-only, one file at a time; files of one shape are parsed once a task."""

    schema = to_arrow_schema(files.sparkSession.createDataFrame([], MODEL).schema)
    columns = ("app_id", "version", "path", "content", "lang")
    names = ("app_id", "version", "path", "error")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shapes = Shapes(inject_text, schema)
        out, held, same, at, numbers = [], 0, [], [], []
        for batch in batches:
            for start in range(0, batch.num_rows, 1000):
                some = batch.slice(start, 1000)
                for i, (app, version, path, lang) in enumerate(zip(*(some.column(c).to_pylist() for c in ("app_id", "version", "path", "lang")), strict=True)):
                    text = some.column("content")[i].as_py() or ""  # few texts and models are Python objects at once
                    found = inject_text(text, lang) if lang == "html" else shapes.find(text)
                    if isinstance(found[0], int):
                        same.append((app, version, path, None))
                        at.append(found[0])
                        numbers.append(found[1])
                    else:
                        out.append({"app_id": app, "version": version, "path": path, "error": found[1], **found[0]})
                        held += len(text)
                    if held > MODEL_CHARS or len(out) == 500:
                        yield pa.RecordBatch.from_pylist(out, schema=schema)
                        out, held = [], 0
                    if len(same) == 2000:
                        yield shapes.filled(dict(zip(names, zip(*same))), at, numbers)
                        same, at, numbers = [], [], []
        if same:
            yield shapes.filled(dict(zip(names, zip(*same))), at, numbers)
        if out:
            yield pa.RecordBatch.from_pylist(out, schema=schema)

    return spread(files.select(*columns)).mapInArrow(run, MODEL)


def spread(files: DataFrame, most_bytes: int = 32 << 20) -> DataFrame:
    """The files dealt by hash over enough tasks: one a core at least, and about ``most_bytes`` of text in each.

    Parsing costs far more than moving the texts, and a source may well come in a single partition.
    """
    spark = files.sparkSession
    size = int(str(files._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    known = size if size < 1 << 60 else 0  # sources that can't tell give the greatest number
    tasks = max(spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions")), min(100_000, known // most_bytes))
    return files.repartition(tasks, "app_id", "version", "path")
