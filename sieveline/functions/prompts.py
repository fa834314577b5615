"""Prompt templates compiled to Catalyst, and the output schema language.

Templates know ``{{ name }}`` and ``{{ input.name }}``, ``{% if expr %} ... {% else %} ...
{% endif %}`` with a SQL expression, and ``{% for x in name %} ... {% endfor %}`` over an
array column, inside which ``{{ x }}`` and ``{{ x.field }}`` stand for the element.
"""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T

_PART = re.compile(r"\{\{\s*(.*?)\s*\}\}|\{%\s*(.*?)\s*%\}", re.S)
Render = Callable[[dict[str, Column]], Column]


class Template:
    """A parsed prompt; ``render()`` is a string column, ``variables`` its placeholders."""

    def __init__(self, source: str):
        self.source, self.variables = source, []
        self._parts = [(source[a:b], m) for a, b, m in self._cuts(source)]
        self._at = 0
        self._render, end = self._block(set())
        if end:
            raise ValueError(f"unexpected {end!r} in a prompt")

    @staticmethod
    def _cuts(source):
        at = 0
        for m in _PART.finditer(source):
            yield at, m.start(), m
            at = m.end()
        yield at, len(source), None

    def _name(self, path: str, local: set[str]) -> Render:
        head, _, rest = path.partition(".")
        if head in local:
            return lambda env: (env[head][rest] if rest else env[head]).cast("string")
        path = rest if head in ("input", "left", "right", "input1", "input2") and rest else path
        self.variables.append(path.split(".")[0])
        return lambda env: F.col(path).cast("string")

    def _block(self, local: set[str]) -> tuple[Render, str]:
        pieces: list[Render] = []
        while self._at < len(self._parts):
            text, m = self._parts[self._at]
            self._at += 1
            if text:
                pieces.append(lambda env, text=text: F.lit(text))
            if m is None:
                continue
            if m[1] is not None:
                pieces.append(self._name(m[1], local))
                continue
            word, _, rest = m[2].partition(" ")
            if word == "if":
                yes, end = self._block(local)
                no, end = self._block(local) if end == "else" else (lambda env: F.lit(""), end)
                if end != "endif":
                    raise ValueError("an if is not closed")
                pieces.append(lambda env, test=rest, yes=yes, no=no: F.when(F.expr(test), yes(env)).otherwise(no(env)))
            elif word == "for":
                var, _, name = (x.strip() for x in rest.partition(" in "))
                body, end = self._block(local | {var})
                if end != "endfor":
                    raise ValueError("a for is not closed")
                name = name.split(".", 1)[-1]
                self.variables.append(name)
                pieces.append(lambda env, var=var, name=name, body=body: F.array_join(F.transform(F.col(name), lambda x: body(env | {var: x})), ""))
            else:
                return self._join(pieces), word
        return self._join(pieces), ""

    @staticmethod
    def _join(pieces: list[Render]) -> Render:
        return lambda env: F.concat(F.lit(""), *[F.coalesce(p(env), F.lit("")) for p in pieces])

    def render(self) -> Column:
        return self._render({})

    def check(self, columns: list[str]) -> None:
        """Reject prompts without a document placeholder or with unknown ones."""
        if not self.variables:
            raise ValueError("the prompt has no input placeholder")
        if unknown := [v for v in self.variables if v not in columns]:
            raise ValueError(f"the prompt names unknown attributes: {unknown}")


def fold_prompt(prompt: str, name: str) -> str:
    """The prompt of a fold's later batches, from that of its first: the answer so far stands before the request."""
    return f"The answer so far:\n{{{{ {name} }}}}\nBring it up to date with what follows; keep what still holds.\n{prompt}"


#: Names of simple types in output schemas.
SIMPLE = {"string": T.StringType(), "str": T.StringType(), "text": T.StringType(), "int": T.LongType(), "integer": T.LongType(), "number": T.DoubleType(), "float": T.DoubleType(), "bool": T.BooleanType(), "boolean": T.BooleanType()}


def parse_schema(text: str) -> T.DataType:
    """``string``, ``list[...]`` and ``{name: type, ...}``, nested at will."""
    kind, rest = _type(text.strip())
    if rest.strip():
        raise ValueError(f"cannot read {rest!r} in a schema")
    return kind


def _type(s: str) -> tuple[T.DataType, str]:
    s = s.lstrip()
    if s.startswith("list["):
        kind, rest = _type(s[5:])
        if not rest.lstrip().startswith("]"):
            raise ValueError("a list is not closed")
        return T.ArrayType(kind), rest.lstrip()[1:]
    if s.startswith("{"):
        fields, s = [], s[1:]
        while not s.lstrip().startswith("}"):
            name, _, s = s.partition(":")
            kind, s = _type(s)
            fields.append(T.StructField(name.strip(), kind))
            s = s.lstrip().removeprefix(",")
        return T.StructType(fields), s.lstrip()[1:]
    m = re.match(r"[A-Za-z]+", s)
    if not m or m[0] not in SIMPLE:
        raise ValueError(f"unknown type at {s[:20]!r}")
    return SIMPLE[m[0]], s[m.end() :]


def conform(json: Column, schema: T.DataType) -> Column:
    """A model's JSON text as the schema; null where it does not parse."""
    return F.from_json(json, schema, {"mode": "PERMISSIVE"})
