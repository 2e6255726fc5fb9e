"""A sandboxed template language compiled to Python closures.

Source -> syntax tree -> folded tree -> closures. The language has ``{{ expr }}``,
``{% for x in expr %}``, ``{% if %}/{% elif %}/{% else %}``, ``{% set x = expr %}`` and
``{% generation %}``; expressions have literals, names, item access on mappings, ``loop``,
``+ == != < > <= >= in and or not`` and named filters. Nothing else can be reached: there is no
attribute access on Python objects and no call but the registered filters. A dash inside a tag's
braces takes the white space on that side. Whatever fails is a :class:`TemplateError`.
"""

from __future__ import annotations

import re
from collections.abc import Callable
from dataclasses import dataclass, field
from typing import Any


class TemplateError(ValueError):
    """The template text is not in the language, or uses a name that is not defined."""


_PARTS = re.compile(r"\{\{-?(.*?)-?\}\}|\{%-?(.*?)-?%\}|\{#-?.*?-?#\}", re.DOTALL)
_LEXEMES = re.compile(r"\s*(?:(?P<str>'(?:[^'\\]|\\.)*'|\"(?:[^\"\\]|\\.)*\")|(?P<int>\d+)|(?P<name>[A-Za-z_]\w*)|(?P<op>==|!=|<=|>=|[-+<>|.\[\]()]))")
_ESCAPES = {"n": "\n", "t": "\t", "r": "\r"}
_WORDS = {"true": True, "false": False, "none": None}

FILTERS: dict[str, Callable[[Any], Any]] = {"trim": lambda s: s.strip(), "upper": str.upper, "lower": str.lower, "length": len}


@dataclass
class Output:
    """Rendered pieces, and the spans (in code points) that the model is to generate."""

    pieces: list[str] = field(default_factory=list)
    size: int = 0
    spans: list[tuple[int, int]] = field(default_factory=list)

    def put(self, text: str) -> None:
        self.pieces.append(text)
        self.size += len(text)


# ---- expressions: ("const", v) ("name", n) ("item", e, e) ("filter", f, e) ("op", o, a, b) ("not", e)


class _Expression:
    def __init__(self, source: str):
        self.items: list[tuple[str, str]] = []
        at = 0
        source = source.strip()
        while at < len(source):
            m = _LEXEMES.match(source, at)
            if not m:
                raise TemplateError(f"cannot read {source[at:]!r}")
            self.items.append((m.lastgroup, m[m.lastgroup]))
            at = m.end()
        self.at = 0

    def peek(self) -> str | None:
        return self.items[self.at][1] if self.at < len(self.items) else None

    def take(self, wanted: str | None = None) -> tuple[str, str]:
        if self.at >= len(self.items) or wanted is not None and self.items[self.at][1] != wanted:
            raise TemplateError(f"expected {wanted or 'more'} at {self.peek()!r}")
        self.at += 1
        return self.items[self.at - 1]

    def whole(self) -> tuple:
        tree = self.chain(0)
        if self.peek() is not None:
            raise TemplateError(f"unexpected {self.peek()!r}")
        return tree

    _LEVELS = (("or",), ("and",), ("==", "!=", "<", ">", "<=", ">=", "in", "not"), ("+",))

    def chain(self, level: int) -> tuple:
        if level == len(self._LEVELS):
            return self.unary()
        tree = self.chain(level + 1)
        while self.peek() in self._LEVELS[level]:
            op = self.take()[1]
            if op == "not":
                self.take("in")
                tree = ("not", ("op", "in", tree, self.chain(level + 1)))
            else:
                tree = ("op", op, tree, self.chain(level + 1))
        return tree

    def unary(self) -> tuple:
        if self.peek() == "not":
            self.take()
            return ("not", self.chain(2))
        kind, text = self.take()
        if kind == "str":
            tree = ("const", re.sub(r"\\(.)", lambda m: _ESCAPES.get(m[1], m[1]), text[1:-1], flags=re.DOTALL))
        elif kind == "int":
            tree = ("const", int(text))
        elif text == "(":
            tree = self.chain(0)
            self.take(")")
        elif kind == "name":
            tree = ("const", _WORDS[text]) if text in _WORDS else ("name", text)
        else:
            raise TemplateError(f"unexpected {text!r}")
        while self.peek() in (".", "[", "|"):
            op = self.take()[1]
            if op == ".":
                tree = ("item", tree, ("const", self.take()[1]))
            elif op == "[":
                tree = ("item", tree, self.chain(0))
                self.take("]")
            else:
                tree = ("filter", self.take()[1], tree)
        return tree


_OPS: dict[str, Callable[[Any, Any], Any]] = {
    "+": lambda a, b: a + b,
    "==": lambda a, b: a == b,
    "!=": lambda a, b: a != b,
    "<": lambda a, b: a < b,
    ">": lambda a, b: a > b,
    "<=": lambda a, b: a <= b,
    ">=": lambda a, b: a >= b,
    "in": lambda a, b: a in b,
    "and": lambda a, b: a and b,
    "or": lambda a, b: a or b,
}


def _item(held: Any, key: Any) -> Any:
    if not isinstance(held, (dict, list, tuple, str)):
        raise TemplateError(f"no item {key!r}")
    try:
        return held[key]
    except (KeyError, IndexError, TypeError) as e:
        raise TemplateError(f"no item {key!r}") from e


def fold(tree: tuple, filters: dict) -> tuple:
    """Replace parts without names by their values."""
    kind = tree[0]
    if kind in ("const", "name"):
        return tree
    if kind == "filter":
        inner = fold(tree[2], filters)
        if tree[1] not in filters:
            raise TemplateError(f"no filter {tree[1]!r}")
        return ("const", filters[tree[1]](inner[1])) if inner[0] == "const" else ("filter", tree[1], inner)
    if kind == "not":
        inner = fold(tree[1], filters)
        return ("const", not inner[1]) if inner[0] == "const" else ("not", inner)
    a, b = fold(tree[-2], filters), fold(tree[-1], filters)
    if a[0] == b[0] == "const":
        return ("const", _item(a[1], b[1]) if kind == "item" else _OPS[tree[1]](a[1], b[1]))
    return (*tree[:-2], a, b)


def evaluator(tree: tuple, filters: dict) -> Callable[[dict], Any]:
    kind = tree[0]
    if kind == "const":
        value = tree[1]
        return lambda env: value
    if kind == "name":
        name = tree[1]

        def look(env: dict) -> Any:
            if name not in env:
                raise TemplateError(f"{name!r} is not defined")
            return env[name]

        return look
    if kind == "filter":
        inner, apply = evaluator(tree[2], filters), filters[tree[1]]
        return lambda env: apply(inner(env))
    if kind == "not":
        inner = evaluator(tree[1], filters)
        return lambda env: not inner(env)
    a, b = evaluator(tree[-2], filters), evaluator(tree[-1], filters)
    if kind == "item":
        return lambda env: _item(a(env), b(env))
    if tree[1] == "and":
        return lambda env: a(env) and b(env)
    if tree[1] == "or":
        return lambda env: a(env) or b(env)
    op = _OPS[tree[1]]
    return lambda env: op(a(env), b(env))


# ---- statements: ("text", s) ("emit", e) ("for", n, e, body) ("if", [(e, body)]) ("set", n, e) ("generation", body)


class _Statements:
    def __init__(self, source: str):
        self.parts: list[tuple[str, str]] = []
        last = 0
        for m in _PARTS.finditer(source):
            text = source[last : m.start()]
            self.parts.append(("text", text.rstrip() if m[0][2] == "-" else text))
            last = m.end()
            if m[0][-3] == "-":  # a dash takes the white space on its side
                last += len(source[last:]) - len(source[last:].lstrip())
            if m[1] is not None:
                self.parts.append(("emit", m[1]))
            elif m[2] is not None:
                self.parts.append(("tag", m[2].strip()))
        self.parts.append(("text", source[last:]))
        self.at = 0

    def block(self, *ends: str) -> tuple[list[tuple], str]:
        body: list[tuple] = []
        while self.at < len(self.parts):
            kind, text = self.parts[self.at]
            self.at += 1
            if kind == "text":
                if text:
                    body.append(("text", text))
            elif kind == "emit":
                body.append(("emit", _Expression(text).whole()))
            else:
                word, _, rest = text.partition(" ")
                if word in ends:
                    return body, text
                body.append(self.tag(word, rest))
        if ends:
            raise TemplateError(f"missing {' or '.join(ends)}")
        return body, ""

    def tag(self, word: str, rest: str) -> tuple:
        if word == "for" and (m := re.fullmatch(r"\s*([A-Za-z_]\w*)\s+in\s+(.*)", rest, re.DOTALL)):
            return ("for", m[1], _Expression(m[2]).whole(), self.block("endfor")[0])
        if word == "set" and (m := re.fullmatch(r"\s*([A-Za-z_]\w*)\s*=(?!=)(.*)", rest, re.DOTALL)):
            return ("set", m[1], _Expression(m[2]).whole())
        if word == "generation":
            return ("generation", self.block("endgeneration")[0])
        if word == "if":
            arms, test = [], _Expression(rest).whole()
            while True:
                body, end = self.block("elif", "else", "endif")
                arms.append((test, body))
                if end == "endif":
                    return ("if", arms)
                test = ("const", True) if end == "else" else _Expression(end.partition(" ")[2]).whole()
        raise TemplateError(f"unknown tag {word!r}")


def fold_block(body: list[tuple], filters: dict) -> list[tuple]:
    """Fold expressions, drop arms that cannot be taken, join neighbouring texts."""
    out: list[tuple] = []

    def add(node: tuple) -> None:
        if node[0] == "text" and out and out[-1][0] == "text":
            out[-1] = ("text", out[-1][1] + node[1])
        else:
            out.append(node)

    for node in body:
        if node[0] == "emit":
            e = fold(node[1], filters)
            add(("text", str(e[1])) if e[0] == "const" else ("emit", e))
        elif node[0] == "for":
            add(("for", node[1], fold(node[2], filters), fold_block(node[3], filters)))
        elif node[0] == "set":
            add(("set", node[1], fold(node[2], filters)))
        elif node[0] == "generation":
            add(("generation", fold_block(node[1], filters)))
        elif node[0] == "if":
            arms = []
            for test, inner in node[1]:
                test = fold(test, filters)
                if test[0] == "const" and not test[1]:
                    continue
                arms.append((test, fold_block(inner, filters)))
                if test[0] == "const":
                    break
            if arms and arms[0][0][0] == "const":
                for inner_node in arms[0][1]:
                    add(inner_node)
            elif arms:
                add(("if", arms))
        else:
            add(node)
    return out


_Step = Callable[[dict, Output], None]


def _run_all(steps: list[_Step]) -> _Step:
    if len(steps) == 1:
        return steps[0]

    def run(env: dict, out: Output) -> None:
        for step in steps:
            step(env, out)

    return run


def _step(node: tuple, filters: dict) -> _Step:
    kind = node[0]
    if kind == "text":
        text = node[1]
        return lambda env, out: out.put(text)
    if kind == "emit":
        value = evaluator(node[1], filters)
        return lambda env, out: out.put(str(value(env)))
    if kind == "set":
        name, value = node[1], evaluator(node[2], filters)
        return lambda env, out: env.__setitem__(name, value(env))
    inner = _run_all([_step(x, filters) for x in node[-1]]) if kind != "if" else None
    if kind == "generation":

        def generation(env: dict, out: Output) -> None:
            start = out.size
            inner(env, out)
            out.spans.append((start, out.size))

        return generation
    if kind == "for":
        name, value = node[1], evaluator(node[2], filters)

        def loop(env: dict, out: Output) -> None:
            items = value(env)
            last = len(items) - 1
            for i, item in enumerate(items):
                inner(env | {name: item, "loop": {"index0": i, "index": i + 1, "first": i == 0, "last": i == last}}, out)

        return loop
    arms = [(evaluator(test, filters), _run_all([_step(x, filters) for x in body])) for test, body in node[1]]

    def choose(env: dict, out: Output) -> None:
        for test, body in arms:
            if test(env):
                body(env, out)
                return

    return choose


def parse(source: str) -> list[tuple]:
    return _Statements(source).block()[0]


def compile_template(source: str, filters: dict[str, Callable[[Any], Any]] | None = None) -> Callable[..., Output]:
    """A function from named values to the rendered :class:`Output`."""
    known = FILTERS | (filters or {})
    try:
        run = _run_all([_step(node, known) for node in fold_block(parse(source), known)])
    except (TypeError, AttributeError) as e:  # of constants
        raise TemplateError(str(e)) from e

    def render(**values: Any) -> Output:
        out = Output()
        try:
            run(dict(values), out)
        except (TypeError, AttributeError) as e:
            raise TemplateError(str(e)) from e
        return out

    return render
