"""A small template language compiled to Python closures.

Text with tags: {{ expression }} writes a value, {% for x in list %}..{% endfor %}, {% if e %}..{% elif e %}..{% else %}..{% endif %},
{% set x = e %}, {% generation %}..{% endgeneration %} marks what a model is trained to produce. Expressions: strings, integers, true,
false, none, names, item lookup (a.b, a["b"]), + ~ == != < > <= >= in, not, and, or, and filters (e | upper).

The sandbox: names come from the context alone, lookups read mappings and lists only, filters come from a fixed table, there are no calls
and no Python attributes, loops run over lists, and the output is bounded. Unknown names and lookups that fail give none, which writes nothing.

Compilation parses to a syntax tree, folds constant expressions, branches and neighbouring text, and turns each node into a closure
over its compiled children, called with (scope, out).
"""

from __future__ import annotations

import re
from collections.abc import Callable, Mapping
from typing import Any, NamedTuple

MOST_OUTPUT = 1 << 28


class TemplateError(ValueError):
    pass


class Node(NamedTuple):
    """kind and parts: ("text", s), ("const", v), ("name", n), ("item", e, e), ("op", o, e, e), ("not", e), ("filter", f, e), ("write", e), ("for", n, e, body), ("if", [(e, body)]), ("set", n, e), ("gen", body), ("seq", [nodes])."""

    kind: str
    parts: tuple


class Output:
    """Pieces of the text and the code point spans written inside generation blocks."""

    def __init__(self) -> None:
        self.pieces: list[str] = []
        self.length = 0
        self.spans: list[tuple[int, int]] = []

    def write(self, s: str) -> None:
        if s:
            self.pieces.append(s)
            self.length += len(s)
            if self.length > MOST_OUTPUT:
                raise TemplateError("the output is too long")


FILTERS: dict[str, Callable[[Any], Any]] = {
    "upper": lambda v: str(v or "").upper(),
    "lower": lambda v: str(v or "").lower(),
    "trim": lambda v: str(v or "").strip(),
    "length": lambda v: len(v) if isinstance(v, (str, list, Mapping)) else 0,
}

_TAG = re.compile(r"\{\{(.*?)\}\}|\{%(-?)(.*?)(-?)%\}", re.S)
_TOKEN = re.compile(r"\s*(?:(?P<str>\"(?:[^\"\\]|\\.)*\"|'(?:[^'\\]|\\.)*')|(?P<int>\d+)|(?P<name>[A-Za-z_]\w*)|(?P<op>==|!=|<=|>=|[<>+~|.\[\]()]))")
_WORDS = {"true": True, "false": False, "none": None}
_ESCAPES = {"n": "\n", "t": "\t", "r": "\r"}
_BINARY = {
    "or": (1, lambda a, b: a or b),
    "and": (2, lambda a, b: a and b),
    "==": (3, lambda a, b: a == b),
    "!=": (3, lambda a, b: a != b),
    "<": (3, lambda a, b: _ordered(a, b) and a < b),
    ">": (3, lambda a, b: _ordered(a, b) and a > b),
    "<=": (3, lambda a, b: _ordered(a, b) and a <= b),
    ">=": (3, lambda a, b: _ordered(a, b) and a >= b),
    "in": (3, lambda a, b: a in b if isinstance(b, (list, Mapping)) or isinstance(a, str) and isinstance(b, str) else False),
    "~": (4, lambda a, b: shown(a) + shown(b)),
    "+": (4, lambda a, b: a + b if type(a) is type(b) and isinstance(a, (int, str)) else None),
}


def _ordered(a: Any, b: Any) -> bool:
    return type(a) is type(b) and isinstance(a, (int, str))


def shown(v: Any) -> str:
    return "" if v is None else v if isinstance(v, str) else str(v).lower() if isinstance(v, bool) else str(v)


class _Expression:
    """A precedence climbing parser over the tokens of one expression."""

    def __init__(self, source: str):
        self.tokens, at = [], 0
        source = source.rstrip()
        while at < len(source):
            m = _TOKEN.match(source, at)
            if not m:
                raise TemplateError(f"cannot read {source[at:]!r}")
            self.tokens.append((m.lastgroup, m[m.lastgroup]))
            at = m.end()
        self.at = 0

    def peek(self) -> tuple[str, str]:
        return self.tokens[self.at] if self.at < len(self.tokens) else ("end", "")

    def take(self, want: str | None = None) -> tuple[str, str]:
        got = self.peek()
        if want is not None and got[1] != want or got[0] == "end":
            raise TemplateError(f"expected {want or 'a value'}, found {got[1]!r}")
        self.at += 1
        return got

    def whole(self) -> Node:
        e = self.binary(1)
        if self.peek()[0] != "end":
            raise TemplateError(f"unexpected {self.peek()[1]!r}")
        return e

    def binary(self, least: int) -> Node:
        left = self.unary()
        while (op := self.peek()[1]) in _BINARY and self.peek()[0] != "str" and _BINARY[op][0] >= least:
            self.take()
            left = Node("op", (op, left, self.binary(_BINARY[op][0] + 1)))
        return left

    def unary(self) -> Node:
        if self.peek() == ("name", "not"):
            self.take()
            return Node("not", (self.binary(3),))
        e = self.primary()
        while self.peek()[0] == "op" and self.peek()[1] in (".", "[", "|"):
            op = self.take()[1]
            if op == ".":
                e = Node("item", (e, Node("const", (self.take()[1],))))
            elif op == "[":
                e = Node("item", (e, self.binary(1)))
                self.take("]")
            else:
                e = Node("filter", (self.take()[1], e))
        return e

    def primary(self) -> Node:
        kind, value = self.take()
        if kind == "str":
            return Node("const", (re.sub(r"\\(.)", lambda m: _ESCAPES.get(m[1], m[1]), value[1:-1], flags=re.S),))
        if kind == "int":
            return Node("const", (int(value),))
        if kind == "name":
            return Node("const", (_WORDS[value],)) if value in _WORDS else Node("name", (value,))
        if value == "(":
            e = self.binary(1)
            self.take(")")
            return e
        raise TemplateError(f"unexpected {value!r}")


def _tags(source: str) -> list[tuple[str, str]]:
    """("text", s), ("write", e) and ("tag", words) in order; a dash in a tag trims the white space beside it."""
    out, at, trim = [], 0, False
    for m in _TAG.finditer(source):
        text = source[at : m.start()]
        text = text.lstrip() if trim else text
        text = text.rstrip() if m[2] else text
        out += [("text", text), ("write", m[1]) if m[1] is not None else ("tag", m[3].strip())]
        at, trim = m.end(), bool(m[4])
    rest = source[at:]
    return [*out, ("text", rest.lstrip() if trim else rest)]


def parse(source: str) -> Node:
    tags, at = _tags(source), 0

    def body(*ends: str) -> tuple[Node, str]:
        nonlocal at
        nodes = []
        while at < len(tags):
            kind, value = tags[at]
            at += 1
            if kind == "text":
                nodes.append(Node("text", (value,)))
                continue
            if kind == "write":
                nodes.append(Node("write", (_Expression(value).whole(),)))
                continue
            word = value.split(None, 1)[0] if value else ""
            if word in ends:
                return Node("seq", (nodes,)), value
            rest = value[len(word) :].strip()
            if word == "for":
                m = re.fullmatch(r"([A-Za-z_]\w*)\s+in\s+(.+)", rest, re.S)
                if not m:
                    raise TemplateError(f"cannot read for {rest!r}")
                inner, _ = body("endfor")
                nodes.append(Node("for", (m[1], _Expression(m[2]).whole(), inner)))
            elif word == "if":
                arms, test = [], _Expression(rest).whole()
                while True:
                    inner, end = body("elif", "else", "endif")
                    arms.append((test, inner))
                    if end == "endif":
                        break
                    test = _Expression(end[4:]).whole() if end.startswith("elif") else Node("const", (True,))
                nodes.append(Node("if", (arms,)))
            elif word == "set":
                name, eq, value = rest.partition("=")
                if not eq or not name.strip().isidentifier():
                    raise TemplateError(f"cannot read set {rest!r}")
                nodes.append(Node("set", (name.strip(), _Expression(value).whole())))
            elif word == "generation":
                nodes.append(Node("gen", (body("endgeneration")[0],)))
            else:
                raise TemplateError(f"unknown tag {word!r}")
        if ends:
            raise TemplateError(f"no {ends[-1]}")
        return Node("seq", (nodes,)), ""

    return body()[0]


def fold(node: Node, filters: Mapping[str, Callable[[Any], Any]]) -> Node:
    """The same template with constant parts computed."""
    kind, parts = node
    f = lambda x: fold(x, filters)
    const = lambda x: x.kind == "const"
    if kind == "op":
        op, a, b = parts[0], f(parts[1]), f(parts[2])
        return Node("const", (_BINARY[op][1](a.parts[0], b.parts[0]),)) if const(a) and const(b) else Node("op", (op, a, b))
    if kind == "not":
        a = f(parts[0])
        return Node("const", (not a.parts[0],)) if const(a) else Node("not", (a,))
    if kind == "filter":
        if parts[0] not in filters:
            raise TemplateError(f"unknown filter {parts[0]!r}")
        a = f(parts[1])
        return Node("const", (filters[parts[0]](a.parts[0]),)) if const(a) else Node("filter", (parts[0], a))
    if kind == "item":
        return Node("item", (f(parts[0]), f(parts[1])))
    if kind == "write":
        a = f(parts[0])
        return Node("text", (shown(a.parts[0]),)) if const(a) else Node("write", (a,))
    if kind == "set":
        return Node("set", (parts[0], f(parts[1])))
    if kind == "for":
        return Node("for", (parts[0], f(parts[1]), f(parts[2])))
    if kind == "gen":
        return Node("gen", (f(parts[0]),))
    if kind == "if":
        arms = []
        for test, inner in ((f(t), f(b)) for t, b in parts[0]):
            if const(test) and not test.parts[0]:
                continue
            arms.append((test, inner))
            if const(test):
                break
        if arms and const(arms[0][0]):
            return arms[0][1]
        return Node("if", (arms,)) if arms else Node("text", ("",))
    if kind == "seq":
        flat: list[Node] = []
        for x in map(f, parts[0]):
            for y in x.parts[0] if x.kind == "seq" else [x]:
                if y.kind == "text" and flat and flat[-1].kind == "text":
                    flat[-1] = Node("text", (flat[-1].parts[0] + y.parts[0],))
                elif y != Node("text", ("",)):
                    flat.append(y)
        return flat[0] if len(flat) == 1 else Node("seq", (flat,))
    return node


def _value(node: Node, filters: Mapping[str, Callable[[Any], Any]]) -> Callable[[dict], Any]:
    kind, parts = node
    if kind == "const":
        constant = parts[0]
        return lambda scope: constant
    if kind == "name":
        name = parts[0]
        return lambda scope: scope.get(name)
    if kind == "item":
        whole, key = _value(parts[0], filters), _value(parts[1], filters)

        def item(scope: dict) -> Any:
            w, k = whole(scope), key(scope)
            if isinstance(w, Mapping):
                return w.get(k)
            return w[k] if isinstance(w, list) and type(k) is int and -len(w) <= k < len(w) else None

        return item
    if kind == "op":
        a, b, op = _value(parts[1], filters), _value(parts[2], filters), _BINARY[parts[0]][1]
        return lambda scope: op(a(scope), b(scope))
    if kind == "not":
        a = _value(parts[0], filters)
        return lambda scope: not a(scope)
    a, apply = _value(parts[1], filters), filters[parts[0]]
    return lambda scope: apply(a(scope))


def _writer(node: Node, filters: Mapping[str, Callable[[Any], Any]]) -> Callable[[dict, Output], None]:
    kind, parts = node
    if kind == "text":
        s = parts[0]
        return lambda scope, out: out.write(s)
    if kind == "write":
        value = _value(parts[0], filters)
        return lambda scope, out: out.write(shown(value(scope)))
    if kind == "seq":
        writers = [_writer(x, filters) for x in parts[0]]

        def seq(scope: dict, out: Output) -> None:
            for w in writers:
                w(scope, out)

        return seq
    if kind == "set":
        name, value = parts[0], _value(parts[1], filters)
        return lambda scope, out: scope.__setitem__(name, value(scope))
    if kind == "if":
        arms = [(_value(t, filters), _writer(b, filters)) for t, b in parts[0]]

        def branch(scope: dict, out: Output) -> None:
            for test, inner in arms:
                if test(scope):
                    return inner(scope, out)
            return None

        return branch
    if kind == "gen":
        inner = _writer(parts[0], filters)

        def generation(scope: dict, out: Output) -> None:
            start = out.length
            inner(scope, out)
            if out.length > start:
                out.spans.append((start, out.length))

        return generation
    name, value, inner = parts[0], _value(parts[1], filters), _writer(parts[2], filters)

    def loop(scope: dict, out: Output) -> None:
        rows = value(scope)
        own = dict(scope)
        for i, row in enumerate(rows if isinstance(rows, list) else []):
            own[name], own["loop"] = row, {"index": i + 1, "first": i == 0, "last": i + 1 == len(rows)}
            inner(own, out)

    return loop


class Template:
    """render(context) gives the text and the spans of its generation blocks, in code points."""

    def __init__(self, source: str, filters: Mapping[str, Callable[[Any], Any]] | None = None):
        filters = {**FILTERS, **(filters or {})}
        self.tree = fold(parse(source), filters)
        self._write = _writer(self.tree, filters)

    def render(self, context: Mapping[str, Any]) -> tuple[str, list[tuple[int, int]]]:
        out = Output()
        self._write(dict(context), out)
        return "".join(out.pieces), out.spans
