"""Recursive-descent parser for the JavaScript subset.

A statement that is not understood becomes one of kind ``other`` that keeps its tokens, so a file with a few
unusual statements is still analysed; only text that cannot be tokenised, or unbalanced brackets, fail.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from .tokens import Token, tokenize, unquote

_BINARY = {"==", "===", "!=", "!==", "<", ">", "<=", ">=", "&&", "||", "??", "+", "-", "*", "/", "%", "**", "&", "|", "^", "in", "instanceof"}
_ASSIGN = {"=", "+=", "-=", "*=", "/=", "%=", "&&=", "||=", "??="}
_OPEN = {"(": ")", "[": "]", "{": "}"}


INNER = 1 << 40  # beyond the number of any token of the text itself


class ParseError(ValueError):
    pass


@dataclass(slots=True)
class Node:
    kind: str
    a: int = 0  # first token
    b: int = 0  # token after the last
    name: str = ""
    value: object = None
    kids: list = field(default_factory=list)


class Parser:
    def __init__(self, text: str) -> None:
        self.tokens: list[Token] = tokenize(text)
        self.inner: list[Token] = []  # tokens of expressions inside template strings; numbered from INNER on
        self.at = 0
        deep = []
        for t in self.tokens:
            if t.kind == "sign" and t.text in _OPEN:
                deep.append(_OPEN[t.text])
            elif t.kind == "sign" and t.text in ")]}":
                if not deep or deep.pop() != t.text:
                    raise ParseError(f"line {t.line}: unbalanced {t.text}")
        if deep:
            raise ParseError(f"{deep[-1]} is missing")

    # -- tokens --------------------------------------------------------------------------------
    def peek(self, n: int = 0) -> str:
        i = self.at + n
        return self.tokens[i].text if i < len(self.tokens) and self.tokens[i].kind in ("sign", "name") else ""

    def take(self, text: str) -> bool:
        if self.peek() == text:
            self.at += 1
            return True
        return False

    def need(self, text: str) -> None:
        if not self.take(text):
            where = self.tokens[self.at] if self.at < len(self.tokens) else None
            raise ParseError(f"line {where.line if where else 'last'}: {text} expected")

    def name(self) -> str:
        if self.at < len(self.tokens) and self.tokens[self.at].kind == "name":
            self.at += 1
            return self.tokens[self.at - 1].text
        raise ParseError("a name is expected")

    def closing(self, at: int) -> int:
        """Where the bracket that opens at ``at`` closes."""
        depth = 0
        for i in range(at, len(self.tokens)):
            t = self.tokens[i]
            if t.kind == "sign":
                depth += (t.text in _OPEN) - (t.text in ")]}")
                if depth == 0:
                    return i
        raise ParseError("a bracket is open")

    # -- statements ----------------------------------------------------------------------------
    def program(self) -> Node:
        kids = []
        while self.at < len(self.tokens):
            kids.append(self.statement())
        return Node("program", 0, len(self.tokens), kids=kids)

    def block(self) -> Node:
        a = self.at
        if self.take("{"):
            kids = []
            while not self.take("}"):
                kids.append(self.statement())
            return Node("block", a, self.at, kids=kids)
        return Node("block", a, self.at, kids=[self.statement()])

    def statement(self) -> Node:
        a = self.at
        try:
            got = self._statement()
            got.a, got.b = a, self.at
            return got
        except ParseError:
            self.at = a
            while self.at < len(self.tokens) and self.peek() not in (";", "}"):
                self.at = self.closing(self.at) + 1 if self.peek() in _OPEN else self.at + 1
                if self.tokens[self.at - 1].text == "}" and self.peek() not in (".", ",", ")", ";"):
                    break
            self.take(";")
            if self.at == a:
                raise
            return Node("other", a, self.at)

    def _statement(self) -> Node:
        word = self.peek()
        if word == ";":
            self.at += 1
            return Node("empty")
        if word == "{":
            return self.block()
        if word in ("const", "let", "var"):
            got = self.declaration()
            self.take(";")
            return got
        if word == "function" or word == "async" and self.peek(1) == "function":
            return self.function(True)
        if word == "class":
            return self.klass()
        if word == "if":
            self.at += 1
            self.need("(")
            kids = [self.expression()]
            self.need(")")
            kids.append(self.block())
            if self.take("else"):
                kids.append(self.block())
            return Node("if", kids=kids)
        if word == "while":
            self.at += 1
            self.need("(")
            kids = [self.expression()]
            self.need(")")
            return Node("while", kids=[*kids, self.block()])
        if word == "do":
            self.at += 1
            body = self.block()
            self.need("while")
            self.need("(")
            test = self.expression()
            self.need(")")
            self.take(";")
            return Node("while", kids=[test, body])
        if word == "for":
            return self.loop()
        if word in ("return", "throw"):
            self.at += 1
            kids = [] if self.peek() in (";", "}") or self.at >= len(self.tokens) else [self.expression()]
            self.take(";")
            return Node(word, kids=kids)
        if word in ("break", "continue"):
            self.at += 1
            self.take(";")
            return Node(word)
        if word == "try":
            self.at += 1
            kids = [self.block()]
            if self.take("catch"):
                if self.take("("):
                    self.pattern()
                    self.need(")")
                kids.append(self.block())
            if self.take("finally"):
                kids.append(self.block())
            return Node("try", kids=kids)
        got = Node("expr", kids=[self.expression()])
        if not self.take(";") and self.at < len(self.tokens) and self.peek() != "}" and self.tokens[self.at].line == self.tokens[self.at - 1].line:
            raise ParseError("the statement goes on")
        return got

    def declaration(self) -> Node:
        kind, kids = self.name(), []
        while True:
            target = self.pattern()
            kids.append(Node("bind", target.a, self.at, kids=[target, self.assignment() if self.take("=") else Node("none")]))
            if not self.take(","):
                return Node("decl", name=kind, kids=kids)

    def pattern(self) -> Node:
        """A name, or an object or array pattern: kids are (property or index, name) pairs as ``part`` nodes."""
        a = self.at
        if self.take("{"):
            kids = []
            while not self.take("}"):
                if self.take("..."):
                    kids.append(Node("part", name="...", value=self.name()))
                else:
                    key = self.name()
                    inner = self.pattern() if self.take(":") else None
                    if self.take("="):
                        self.assignment()
                    kids.append(Node("part", name=key, value=inner.name if inner and inner.kind == "name" else key if inner is None else None, kids=[inner] if inner and inner.kind != "name" else []))
                self.take(",")
            return Node("objectpattern", a, self.at, kids=kids)
        if self.take("["):
            kids = []
            while not self.take("]"):
                if self.peek() == ",":
                    self.at += 1
                    continue
                self.take("...")
                inner = self.pattern()
                kids.append(Node("part", name="[]", value=inner.name if inner.kind == "name" else None, kids=[] if inner.kind == "name" else [inner]))
                self.take(",")
            return Node("arraypattern", a, self.at, kids=kids)
        return Node("name", a, self.at + 1, name=self.name())

    def loop(self) -> Node:
        self.need("for")
        self.take("await")
        self.need("(")
        start = self.at
        if self.peek() in ("const", "let", "var"):
            self.at += 1
            target = self.pattern()
            if self.peek() in ("of", "in"):
                kind = self.name()
                over = self.expression()
                self.need(")")
                return Node("forof" if kind == "of" else "forin", kids=[target, over, self.block()])
            self.at = start
        parts: list[Node] = []
        for end in (";", ";", ")"):
            if self.peek() == end:
                parts.append(Node("none"))
            else:
                parts.append(self.declaration() if self.peek() in ("const", "let", "var") else self.expression())
            self.need(end)
        return Node("for", kids=[*parts, self.block()])

    def params(self) -> list[Node]:
        self.need("(")
        out = []
        while not self.take(")"):
            self.take("...")
            out.append(self.pattern())
            if self.take("="):
                self.assignment()
            self.take(",")
        return out

    def function(self, named: bool) -> Node:
        a = self.at
        self.take("async")
        self.need("function")
        self.take("*")
        name = self.name() if named or self.peek() not in ("(", "") else ""
        params = self.params()
        return Node("function", a, 0, name=name, value=params, kids=[self.block()])

    def klass(self) -> Node:
        self.need("class")
        name, kids = self.name() if self.peek() != "{" else "", []
        if self.take("extends"):
            self.unary()
        self.need("{")
        while not self.take("}"):
            if self.take(";"):
                continue
            a = self.at
            for word in ("static", "async", "get", "set"):
                if self.peek() == word and self.peek(1) not in ("(", "="):
                    self.at += 1
            key = self.name()
            if self.peek() == "(":
                params = self.params()
                kids.append(Node("function", a, 0, name=key, value=params, kids=[self.block()]))
                kids[-1].b = self.at
            elif self.take("="):
                kids.append(Node("bind", a, 0, kids=[Node("name", name=key), self.assignment()]))
                kids[-1].b = self.at
                self.take(";")
        return Node("class", name=name, kids=kids)

    # -- expressions ---------------------------------------------------------------------------
    def expression(self) -> Node:
        got = self.assignment()
        while self.take(","):
            got = Node("seq", got.a, self.at, kids=[got, self.assignment()])
        return got

    def arrow(self) -> Node | None:
        a = self.at
        skip = 1 if self.peek() == "async" and self.peek(1) != "=>" else 0
        first = self.at + skip
        if first >= len(self.tokens):
            return None
        t = self.tokens[first]
        if t.kind == "name" and first + 1 < len(self.tokens) and self.tokens[first + 1].text == "=>":
            self.at = first
            params = [self.pattern()]
        elif t.text == "(" and t.kind == "sign":
            end = self.closing(first)
            if end + 1 >= len(self.tokens) or self.tokens[end + 1].text != "=>":
                return None
            self.at = first
            params = self.params()
        else:
            return None
        self.need("=>")
        if self.peek() == "{":
            body = self.block()
        else:
            value = self.assignment()
            body = Node("block", value.a, self.at, kids=[Node("return", value.a, self.at, name="implicit", kids=[value])])
        return Node("function", a, self.at, value=params, kids=[body])

    def assignment(self) -> Node:
        got = self.arrow()
        if got:
            return got
        a = self.at
        left = self.conditional()
        if self.peek() in _ASSIGN and self.tokens[self.at].kind == "sign":
            op = self.tokens[self.at].text
            self.at += 1
            return Node("assign", a, 0, name=op, kids=[left, self.assignment()])
        return left

    def conditional(self) -> Node:
        a = self.at
        test = self.binary()
        if self.take("?"):
            yes = self.assignment()
            self.need(":")
            return Node("cond", a, self.at, kids=[test, yes, self.assignment()])
        return test

    def binary(self) -> Node:
        a = self.at
        left = self.unary()
        while self.peek() in _BINARY:
            op = self.tokens[self.at].text
            self.at += 1
            left = Node("binary", a, 0, name=op, kids=[left, self.unary()])
            left.b = self.at
        return left

    def unary(self) -> Node:
        a = self.at
        word = self.peek()
        if word in ("!", "-", "+", "~", "typeof", "void", "delete", "await", "++", "--", "..."):
            self.at += 1
            return Node("await" if word == "await" else "spread" if word == "..." else "unary", a, 0, name=word, kids=[self.unary()])
        got = self.postfix(self.primary())
        while self.peek() in ("++", "--"):
            self.at += 1
        return got

    def postfix(self, got: Node) -> Node:
        while True:
            a = got.a
            word = self.peek()
            if word in (".", "?."):
                self.at += 1
                if self.peek() == "(":
                    continue
                if self.peek() == "[":
                    continue
                got = Node("member", a, 0, name=self.name(), kids=[got])
            elif word == "[":
                self.at += 1
                inner = self.expression()
                self.need("]")
                got = Node("index", a, 0, kids=[got, inner])
            elif word == "(":
                got = Node("call", a, 0, kids=[got, *self.arguments()])
            elif self.at < len(self.tokens) and self.tokens[self.at].kind == "template":
                self.at += 1
            else:
                return got
            got.b = self.at

    def arguments(self) -> list[Node]:
        self.need("(")
        out = []
        while not self.take(")"):
            out.append(self.assignment())
            out[-1].b = self.at
            if not self.take(",") and self.peek() != ")":
                raise ParseError("an argument list is not closed")
        return out

    def primary(self) -> Node:
        if self.at >= len(self.tokens):
            raise ParseError("the text ends")
        a, t = self.at, self.tokens[self.at]
        if t.kind == "number":
            self.at += 1
            return Node("literal", a, a + 1, name="long" if t.text.isdigit() else "double", value=t.text)
        if t.kind == "string":
            self.at += 1
            return Node("literal", a, a + 1, name="string", value=unquote(t.text))
        if t.kind == "regex":
            self.at += 1
            return Node("literal", a, a + 1, name="string", value=t.text)
        if t.kind == "template":
            self.at += 1
            return Node("template", a, a + 1, value=t.text, kids=[self.hole(t, at, x) for at, x in holes(t.text)])
        if t.text == "(":
            self.at += 1
            got = self.expression()
            self.need(")")
            got.a, got.b = a, self.at
            return got
        if t.text == "[":
            self.at += 1
            kids = []
            while not self.take("]"):
                kids.append(self.assignment())
                self.take(",")
            return Node("array", a, self.at, kids=kids)
        if t.text == "{":
            return self.object()
        if t.text in ("function", "async") and t.kind == "name" and (t.text == "function" or self.peek(1) == "function"):
            got = self.function(False)
            got.b = self.at
            return got
        if t.text == "class":
            return self.klass()
        if t.text == "new":
            self.at += 1
            what = self.primary()
            while self.take("."):
                what = Node("member", a, self.at, name=self.name(), kids=[what])
            return Node("new", a, self.at, kids=[what, *(self.arguments() if self.peek() == "(" else [])])
        if t.text in ("true", "false"):
            self.at += 1
            return Node("literal", a, a + 1, name="boolean", value=t.text)
        if t.text in ("null", "undefined"):
            self.at += 1
            return Node("literal", a, a + 1, name="null", value=None)
        if t.kind == "name":
            return Node("name", a, a + 1, name=self.name())
        raise ParseError(f"line {t.line}: {t.text}")

    def hole(self, t: Token, at: int, text: str) -> Node:
        """An expression inside a template string, its tokens placed where they stand in the whole text."""
        sub = Parser(text)
        tree, first = sub.expression(), INNER + len(self.inner)
        for x in (*sub.tokens, *sub.inner):
            self.inner.append(Token(x.kind, x.text, t.line + x.line - 1 + t.text[:at].count("\n"), t.start + at + x.start))
        todo = [tree]
        while todo:
            n = todo.pop()
            n.a, n.b = (first + (x if x < INNER else len(sub.tokens) + x - INNER) for x in (n.a, n.b))
            todo += [k for k in n.kids if isinstance(k, Node)]
            todo += [k for k in n.value if isinstance(k, Node)] if isinstance(n.value, list) else []
        return tree

    def object(self) -> Node:
        a = self.at
        self.need("{")
        kids = []
        while not self.take("}"):
            if self.take("..."):
                kids.append(Node("property", name="...", kids=[self.assignment()]))
            else:
                t = self.tokens[self.at]
                if t.text == "[":
                    self.at += 1
                    self.expression()
                    self.need("]")
                    key = "?"
                elif t.kind in ("name", "number", "string"):
                    self.at += 1
                    key = unquote(t.text) if t.kind == "string" else t.text
                else:
                    raise ParseError(f"line {t.line}: a key is expected")
                if self.take(":"):
                    value = self.assignment()
                elif self.peek() == "(":
                    params = self.params()
                    value = Node("function", self.at, 0, name=key, value=params, kids=[self.block()])
                else:
                    value = Node("name", self.at - 1, self.at, name=key)
                kids.append(Node("property", name=key, kids=[value]))
            if not self.take(",") and self.peek() != "}":
                raise ParseError("an object is not closed")
        return Node("object", a, self.at, kids=kids)


def holes(template: str) -> list[tuple[int, str]]:
    """The expressions in a template string, with their places."""
    out, at = [], 0
    while (at := template.find("${", at)) >= 0:
        depth, end = 1, at + 2
        while end < len(template) and depth:
            depth += (template[end] == "{") - (template[end] == "}")
            end += 1
        out.append((at + 2, template[at + 2 : end - 1]))
        at = end
    return out


def parse(text: str) -> tuple[Node, list[Token]]:
    p = Parser(text)
    return p.program(), p.tokens
