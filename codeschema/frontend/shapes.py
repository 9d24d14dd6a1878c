"""Files of one shape: texts that differ in whole numbers only are parsed once, and their models are filled with the numbers.

The parser and the injector copy a number's text and never look at its value, so the model of a text is that of its
shape with the numbers put back.  Each shape is checked against the model that its second text gets from the parser;
one that doesn't agree, longer texts, and texts with template strings are always parsed.
"""

from __future__ import annotations

import re
from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

Model = tuple[dict[str, list[dict]], str | None]
#: Texts up to the length at which the injector cuts what it copies; no number may lie on that edge.
MOST_CHARS, MOST_SHAPES, MOST_NUMBERS = 400, 1_000, 16
_NUMBER = re.compile(r"(?<![\w$.\\])[1-9][0-9]{0,14}(?![\w$.])", re.A)
_STAND_IN = "81900000000"  # with two digits for the number's place
_HELD = re.compile(_STAND_IN + "([0-9]{2})")


def shape_of(text: str) -> tuple[str, list[str]] | None:
    """The text with a stand-in for each whole number, and the numbers; None for a text that has to be parsed."""
    if len(text) > MOST_CHARS or "`" in text or _STAND_IN in text or not text.isascii():
        return None
    numbers = _NUMBER.findall(text)
    if not numbers or len(numbers) > MOST_NUMBERS:
        return None
    places = iter(range(len(numbers)))
    shape = _NUMBER.sub(lambda m: f"{_STAND_IN}{next(places):02d}", text)
    return (shape, numbers) if len(shape) <= MOST_CHARS else None


def _put(x: object, numbers: list[str]) -> object:
    if isinstance(x, str):
        return _HELD.sub(lambda m: numbers[int(m[1])], x) if _STAND_IN in x else x
    if isinstance(x, list):
        return [_put(v, numbers) for v in x]
    return {k: _put(v, numbers) for k, v in x.items()} if isinstance(x, dict) else x


class Shapes:
    """The shapes that a task has met: ``parse`` gives the model of a text, ``schema`` the fields of a model row."""

    def __init__(self, parse: Callable[[str], Model], schema: pa.Schema) -> None:
        self.parse, self.schema = parse, schema
        self.known: dict[str, int | None] = {}  # number of the shape's row; -1: met once; None: does not agree
        self.rows: list[dict] = []
        self.columns: pa.RecordBatch | None = None

    def find(self, text: str) -> tuple[int, list[str]] | Model:
        """Number of the text's shape with the numbers to fill in, or the model of a text that has to be parsed."""
        got = shape_of(text)
        if got is None:
            return self.parse(text)
        shape, numbers = got
        at = self.known.get(shape, -2)
        if at is not None and at >= 0:
            return at, numbers
        model = self.parse(text)
        if at == -2:
            if len(self.known) < MOST_SHAPES:
                self.known[shape] = -1
        elif at == -1:
            rows, error = self.parse(shape)
            if error is None and model[1] is None and _put(rows, numbers) == model[0]:
                self.known[shape] = len(self.rows)
                self.rows.append(rows)
                self.columns = None
            else:
                self.known[shape] = None
        return model

    def filled(self, own: dict[str, list], at: list[int], numbers: list[list[str]]) -> pa.RecordBatch:
        """Model rows with the columns ``own`` and those of shapes ``at``, filled with the numbers."""
        fields = [f for f in self.schema if f.name not in own]
        if self.columns is None:
            self.columns = pa.RecordBatch.from_pylist(self.rows, schema=pa.schema(fields))
        rows, owner = pa.array(at, pa.int64()), np.arange(len(at))
        columns = {f.name: _filled(self.columns.column(f.name).take(rows), owner, numbers) for f in fields}
        columns |= {k: pa.array(v, self.schema.field(k).type) for k, v in own.items()}
        return pa.RecordBatch.from_arrays([columns[f.name] for f in self.schema], schema=self.schema)


def _filled(column: pa.Array, owner: np.ndarray, numbers: list[list[str]]) -> pa.Array:
    """``column`` with stand-ins replaced; ``owner``: the text of each value.  Lists of a model and their structs are never null."""
    kind = column.type
    if pa.types.is_list(kind):
        offsets = column.offsets.to_numpy()
        values = _filled(column.flatten(), np.repeat(owner, np.diff(offsets)), numbers)
        return pa.ListArray.from_arrays(pa.array(offsets - offsets[0], pa.int32()), values, type=kind)
    if pa.types.is_struct(kind):
        parts = [_filled(part, owner, numbers) for part in column.flatten()]
        return pa.StructArray.from_arrays(parts, fields=list(kind))
    if not pa.types.is_string(kind):
        return column
    held = pc.fill_null(pc.match_substring(column, _STAND_IN), False)
    where = np.flatnonzero(held.to_numpy(zero_copy_only=False))
    if not len(where):
        return column
    new = [_put(x, numbers[o]) for x, o in zip(column.take(pa.array(where)).to_pylist(), owner[where].tolist(), strict=True)]
    return pc.replace_with_mask(column, held, pa.array(new, kind))
