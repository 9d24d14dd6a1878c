"""Tokens of the JavaScript subset: strings, templates, comments, regular expressions, numbers, names, signs."""

from __future__ import annotations

import re
from dataclasses import dataclass

_LEX = re.compile(
    r"(?P<space>\s+)|(?P<comment>//[^\n]*|/\*.*?\*/)|(?P<string>'(?:\\.|[^'\\\n])*'|\"(?:\\.|[^\"\\\n])*\")|(?P<template>`(?:\\.|[^`\\])*`)"
    r"|(?P<number>0[xX][0-9a-fA-F]+|(?:\d+\.?\d*|\.\d+)(?:[eE][+-]?\d+)?)|(?P<name>[A-Za-z_$][\w$]*)"
    r"|(?P<sign>=>|\.\.\.|[=!]==?|<=|>=|&&=?|\|\|=?|\?\?=?|\?\.(?!\d)|\+\+|--|\*\*|[-+*/%]=|[{}()\[\];,.<>+\-*/%&|^!~?:=@#])",
    re.S,
)
_REGEX = re.compile(r"/(?![*/])(?:\\.|\[(?:\\.|[^\]\\\n])*\]|[^/\\\[\n])+/[a-z]*")
_OPERAND_ENDS = {"name", "number", "string", "template", "regex"}
_BEFORE_REGEX = {"return", "typeof", "case", "in", "of", "new", "delete", "void", "throw", "await"}


class LexError(ValueError):
    pass


@dataclass(slots=True)
class Token:
    kind: str
    text: str
    line: int
    start: int


def tokenize(text: str, comments: bool = False) -> list[Token]:
    """Tokens without white space; comments only on request.  Raises LexError at a character that starts none."""
    out: list[Token] = []
    at, line, last = 0, 1, None
    while at < len(text):
        m = None
        if text[at] == "/" and (last is None or last.kind not in _OPERAND_ENDS and last.text not in (")", "]", "}") or last.text in _BEFORE_REGEX):
            m = _REGEX.match(text, at)
            kind = "regex"
        if m is None:
            m = _LEX.match(text, at)
            if m is None:
                raise LexError(f"line {line}: {text[at : at + 10]!r}")
            kind = m.lastgroup or ""
        got = m.group()
        if kind not in ("space", "comment"):
            last = Token(kind, got, line, at)
            out.append(last)
        elif kind == "comment" and comments:
            out.append(Token(kind, got, line, at))
        line += got.count("\n")
        at = m.end()
    return out


def unquote(text: str) -> str:
    """The value of a string token (simple escapes)."""
    return re.sub(r"\\(.)", lambda m: {"n": "\n", "t": "\t", "r": "\r"}.get(m.group(1), m.group(1)), text[1:-1], flags=re.S)


def register_code_tokens(spark, name: str = "code_tokens") -> str:
    """Registers the table function ``code_tokens(text)``: (pos, kind, text, line); no rows for a text that can't be read."""
    from pyspark.sql.functions import udtf

    class CodeTokens:
        def eval(self, text: str):
            try:
                found = tokenize(text or "")
            except LexError:
                return
            for i, t in enumerate(found):
                yield i, t.kind, t.text, t.line

    spark.udtf.register(name, udtf(CodeTokens, returnType="pos int, kind string, text string, line int"))
    return name
