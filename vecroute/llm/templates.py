"""Chat formatting with a template compiler.

Templates are text with ``{{ expression }}``, ``{% statement %}`` and ``{# comment #}``.
A template is parsed into a syntax tree, constant parts are folded, and the tree
becomes nested Python closures. The language is sandboxed: names come from the
context, members are keys of mappings, calls go to a fixed set of filters and
functions, loops run over lists only; no Python attribute or builtin can be reached.
``generation`` blocks mark what a model is to learn; rendering returns the text and
the spans of code points that such blocks produced.

Statements: ``for x in e`` / ``endfor`` (with ``loop.index0``, ``index``, ``first``,
``last``, ``length``), ``if`` / ``elif`` / ``else`` / ``endif``, ``set x = e``,
``generation`` / ``endgeneration``. A dash inside a delimiter strips white space there.
Expressions: literals, lists, names, ``a.b``, ``a[b]``, ``not``, ``and``, ``or``,
comparisons, ``in``, ``+ - * / // %``, ``~``, ``a if c else b``, filters, ``is [not] defined``.

Defined cases: rows are taken by turn (equal turns by role, then text); null text and
role count as empty; a null conversation id is a conversation of its own; repeated
rows are turns of their own; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from typing import Any

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

TURN, END = "<|turn|>", "<|end|>"
CHAT = "{% for m in messages %}{{ '<|turn|>' ~ (m.role | label) ~ '\\n' }}{% if m.role == 'assistant' %}{% generation %}{{ m.text | escape }}{% endgeneration %}{% else %}{{ m.text | escape }}{% endif %}{{ '<|end|>' ~ '\\n' }}{% endfor %}"

#: What follows the first character of a control string; any run of backslashes may stand between.
_AFTER = r"(?=\||/?s>|/?INST\]|</?SYS>>|/?bos>|/?eos>|/?unk>|/?pad>|/?think>|/?tool_call>|start_of_turn>|end_of_turn>)"
_CONTROL = re.compile(r"([<\[])(\\*)" + _AFTER)
_ESCAPED = re.compile(r"([<\[])\\(\\*)" + _AFTER)


def escape(text: str) -> str:
    """Puts one more backslash after the first character of every control string."""
    return _CONTROL.sub(r"\1\\\2", text)


def unescape(text: str) -> str:
    return _ESCAPED.sub(r"\1\2", text)


def label(role: str) -> str:
    """A role on one line, escaped."""
    return escape(role.replace("\\", "\\\\").replace("\n", "\\n"))


def unlabel(text: str) -> str:
    return re.sub(r"\\(.)", lambda m: "\n" if m[1] == "n" else m[1], unescape(text), flags=re.S)


class TemplateError(ValueError):
    """The template is malformed, or asked for what the sandbox has not."""


Out = list  # (text, under the loss mask)
Value = Callable[[dict], Any]

_TOKEN = re.compile(r"""\s*(?:(?P<num>\d+(?:\.\d+)?)|(?P<str>'(?:[^'\\]|\\.)*'|"(?:[^"\\]|\\.)*")|(?P<name>[A-Za-z_]\w*)|(?P<op>==|!=|<=|>=|//|[-+*/%~<>()\[\]{}.,|:=]))""", re.S)
_PIECE = re.compile(r"\{(?P<kind>[{%#])(?P<left>-?)(?P<body>.*?)(?P<right>-?)(?:[}%#])\}", re.S)
_ESCAPES = {"n": "\n", "t": "\t", "r": "\r"}


@dataclass(frozen=True)
class Node:
    """One node of the syntax tree."""

    kind: str
    parts: tuple = ()
    value: Any = None


def _lex(source: str) -> list[tuple[str, str]]:
    out, at = [], 0
    source = source.strip()
    while at < len(source):
        m = _TOKEN.match(source, at)
        if not m or m.end() == at:
            raise TemplateError(f"unreadable expression: {source[at:]!r}")
        kind = m.lastgroup
        out.append((kind, m[kind]))
        at = m.end()
        while at < len(source) and source[at].isspace():
            at += 1
    return out


class _Expression:
    """Recursive descent over the tokens of one expression."""

    LEVELS = (("or",), ("and",), None, ("==", "!=", "<", "<=", ">", ">=", "in", "not in", "is"), ("~",), ("+", "-"), ("*", "/", "//", "%"))

    def __init__(self, tokens: list[tuple[str, str]]):
        self.tokens, self.at = tokens, 0

    def peek(self, k: int = 0) -> str | None:
        t = self.tokens[self.at + k] if self.at + k < len(self.tokens) else None
        return t[1] if t and t[0] in ("op", "name") else None

    def take(self, text: str) -> bool:
        if self.peek() == text:
            self.at += 1
            return True
        return False

    def need(self, text: str) -> None:
        if not self.take(text):
            raise TemplateError(f"expected {text!r}")

    def whole(self) -> Node:
        node = self.choice()
        if self.at != len(self.tokens):
            raise TemplateError(f"unexpected {self.tokens[self.at][1]!r}")
        return node

    def choice(self) -> Node:
        node = self.level(0)
        if self.take("if"):
            test = self.level(0)
            other = self.choice() if self.take("else") else Node("const", value="")
            return Node("choose", (test, node, other))
        return node

    def level(self, k: int) -> Node:
        if k == len(self.LEVELS):
            return self.unary()
        operators = self.LEVELS[k]
        if operators is None:
            return Node("not", (self.level(k),)) if self.take("not") else self.level(k + 1)
        node = self.level(k + 1)
        while True:
            op = self.peek()
            if op == "not" and self.peek(1) == "in" and "not in" in operators:
                self.at += 2
                node = Node("not", (Node("binary", (node, self.level(k + 1)), "in"),))
            elif op == "is" and "is" in operators:
                self.at += 1
                negated = self.take("not")
                self.need("defined")
                node = Node("defined", (node,))
                node = Node("not", (node,)) if negated else node
            elif op in operators:
                self.at += 1
                node = Node("binary", (node, self.level(k + 1)), op)
            else:
                return node

    def unary(self) -> Node:
        if self.take("-"):
            return Node("binary", (Node("const", value=0), self.unary()), "-")
        node = self.atom()
        while True:
            if self.take("."):
                kind, name = self.tokens[self.at] if self.at < len(self.tokens) else ("", "")
                if kind != "name" or name.startswith("_"):
                    raise TemplateError(f"no member {name!r}")
                self.at += 1
                node = Node("member", (node, Node("const", value=name)))
            elif self.take("["):
                node = Node("member", (node, self.choice()))
                self.need("]")
            elif self.take("|"):
                name = self.tokens[self.at][1] if self.at < len(self.tokens) else ""
                if name not in FILTERS:
                    raise TemplateError(f"no filter {name!r}")
                self.at += 1
                node = Node("filter", (node, *(self.arguments(")") if self.take("(") else ())), name)
            else:
                return node

    def arguments(self, close: str) -> tuple[Node, ...]:
        out: list[Node] = []
        while not self.take(close):
            if out:
                self.need(",")
            out.append(self.choice())
        return tuple(out)

    def atom(self) -> Node:
        if self.at >= len(self.tokens):
            raise TemplateError("expression ends early")
        kind, text = self.tokens[self.at]
        self.at += 1
        if kind == "num":
            return Node("const", value=float(text) if "." in text else int(text))
        if kind == "str":
            return Node("const", value=re.sub(r"\\(.)", lambda m: _ESCAPES.get(m[1], m[1]), text[1:-1], flags=re.S))
        if kind == "name":
            if text.lower() in ("true", "false", "none"):
                return Node("const", value={"true": True, "false": False, "none": None}[text.lower()])
            if self.peek() == "(":
                if text not in FUNCTIONS:
                    raise TemplateError(f"no function {text!r}")
                self.at += 1
                return Node("call", self.arguments(")"), text)
            if text.startswith("_"):
                raise TemplateError(f"no name {text!r}")
            return Node("name", value=text)
        if text == "(":
            node = self.choice()
            self.need(")")
            return node
        if text == "[":
            return Node("list", self.arguments("]"))
        raise TemplateError(f"unexpected {text!r}")


def _text(x: Any) -> str:
    return "" if x is None else "true" if x is True else "false" if x is False else str(x)


def _stop(message: Any = "") -> None:
    raise TemplateError(_text(message))


#: Everything a template can call; none but ``stop`` has an effect.
FILTERS: dict[str, Callable] = {
    "escape": lambda x: escape(_text(x)), "label": lambda x: label(_text(x)), "trim": lambda x: _text(x).strip(), "upper": lambda x: _text(x).upper(), "lower": lambda x: _text(x).lower(),
    "length": lambda x: len(x) if isinstance(x, (str, list, dict)) else 0, "default": lambda x, d="": d if x is None else x, "join": lambda x, by="": by.join(map(_text, x)), "first": lambda x: x[0] if x else None, "last": lambda x: x[-1] if x else None,
}
FUNCTIONS: dict[str, Callable] = {"stop": _stop, "range": lambda n: list(range(min(int(n), 100_000)))}
PURE_FUNCTIONS = frozenset({"range"})


def _add(a: Any, b: Any) -> Any:
    if isinstance(a, str) != isinstance(b, str):
        raise TemplateError("text and number cannot be added")
    return a + b


def _times(a: Any, b: Any) -> Any:
    if isinstance(a, (str, list)) or isinstance(b, (str, list)):
        raise TemplateError("only numbers are multiplied")
    return a * b


BINARY: dict[str, Callable[[Any, Any], Any]] = {
    "==": lambda a, b: a == b, "!=": lambda a, b: a != b, "<": lambda a, b: a < b, "<=": lambda a, b: a <= b, ">": lambda a, b: a > b, ">=": lambda a, b: a >= b, "in": lambda a, b: a in b,
    "~": lambda a, b: _text(a) + _text(b), "+": _add, "-": lambda a, b: a - b, "*": _times, "/": lambda a, b: a / b, "//": lambda a, b: a // b, "%": lambda a, b: a % b if not isinstance(a, str) else _stop("no text formatting"),
}


def _member(of: Any, key: Any) -> Any:
    if isinstance(of, dict):
        return of.get(key)
    if isinstance(of, (list, str)) and isinstance(key, int) and not isinstance(key, bool):
        return of[key] if -len(of) <= key < len(of) else None
    return None


def fold(node: Node) -> Node:
    """The same tree with constant expressions worked out and constant text merged."""
    parts = tuple(fold(p) if isinstance(p, Node) else p for p in node.parts)
    node = Node(node.kind, parts, node.value)
    constant = bool(parts) and all(isinstance(p, Node) and p.kind == "const" for p in parts)
    if node.kind == "choose" and parts[0].kind == "const":
        return parts[1] if parts[0].value else parts[2]
    if node.kind == "binary" and node.value in ("and", "or") and parts[0].kind == "const":
        return parts[1] if bool(parts[0].value) == (node.value == "and") else parts[0]
    if constant and (node.kind in ("not", "member", "filter", "list") or node.kind == "binary" and node.value not in ("and", "or") or node.kind == "call" and node.value in PURE_FUNCTIONS):
        try:
            return Node("const", value=_value(node)({}))
        except (TemplateError, ArithmeticError, TypeError):
            return node  # fails when, and only if, it is rendered
    if node.kind == "emit" and parts[0].kind == "const":
        return Node("text", value=_text(parts[0].value))
    if node.kind == "if":
        kept = []
        for test, body in zip(parts[::2], parts[1::2], strict=True):
            if test.kind == "const" and not test.value:
                continue
            kept += [test, body]
            if test.kind == "const":
                break
        if not kept:
            return Node("text", value="")
        return kept[1] if kept[0].kind == "const" else Node("if", tuple(kept))
    if node.kind == "body":
        merged: list[Node] = []
        for p in (q for part in parts for q in (part.parts if part.kind == "body" else (part,))):
            if p.kind == "text" and merged and merged[-1].kind == "text":
                merged[-1] = Node("text", value=merged[-1].value + p.value)
            elif p.kind != "text" or p.value:
                merged.append(p)
        return merged[0] if len(merged) == 1 else Node("body", tuple(merged))
    return node


def _value(node: Node) -> Value:
    """A closure that works an expression out."""
    kind, v = node.kind, node.value
    if kind == "const":
        return lambda c: v
    if kind == "name":
        return lambda c: c.get(v)
    parts = [_value(p) for p in node.parts]
    if kind == "member":
        of, key = parts
        return lambda c: _member(of(c), key(c))
    if kind == "list":
        return lambda c: [p(c) for p in parts]
    if kind == "not":
        return lambda c: not parts[0](c)
    if kind == "defined":
        return lambda c: parts[0](c) is not None
    if kind == "choose":
        test, yes, no = parts
        return lambda c: yes(c) if test(c) else no(c)
    if kind in ("filter", "call"):
        f = (FILTERS if kind == "filter" else FUNCTIONS)[v]
        if len(parts) == 1:
            only = parts[0]
            return lambda c: f(only(c))
        return lambda c: f(*[p(c) for p in parts])
    a, b = parts
    if v == "and":
        return lambda c: a(c) and b(c)
    if v == "or":
        return lambda c: a(c) or b(c)
    f = BINARY[v]
    return lambda c: f(a(c), b(c))


def _action(node: Node) -> Callable[[dict, Out, bool], None]:
    """A closure that writes a statement's output."""
    kind, v = node.kind, node.value
    if kind == "text":
        return lambda c, out, learn: out.append((v, learn))
    if kind == "emit":
        value = _value(node.parts[0])
        return lambda c, out, learn: out.append((_text(value(c)), learn))
    if kind == "set":
        value = _value(node.parts[0])

        def put(c: dict, out: Out, learn: bool) -> None:
            c[v] = value(c)

        return put
    if kind == "generation":
        body = _action(node.parts[0])
        return lambda c, out, learn: body(c, out, True)
    if kind == "if":
        arms = [(_value(t), _action(b)) for t, b in zip(node.parts[::2], node.parts[1::2], strict=True)]

        def branch(c: dict, out: Out, learn: bool) -> None:
            for test, body in arms:
                if test(c):
                    return body(c, out, learn)
            return None

        return branch
    if kind == "for":
        source, body = _value(node.parts[0]), _action(node.parts[1])

        def loop(c: dict, out: Out, learn: bool) -> None:
            items = source(c)
            if not isinstance(items, list):
                raise TemplateError("loops run over lists")
            inner = dict(c)
            for i, item in enumerate(items):
                inner[v] = item
                inner["loop"] = {"index0": i, "index": i + 1, "first": i == 0, "last": i == len(items) - 1, "length": len(items)}
                body(inner, out, learn)

        return loop
    actions = [_action(p) for p in node.parts]

    def run(c: dict, out: Out, learn: bool) -> None:
        for a in actions:
            a(c, out, learn)

    return run


def parse(source: str) -> Node:
    """The syntax tree of a template."""
    items: list[tuple[str, str]] = []
    at, strip = 0, False
    for m in _PIECE.finditer(source):
        before = source[at : m.start()]
        before = before.lstrip() if strip else before
        before = before.rstrip() if m["left"] else before
        if before:
            items.append(("text", before))
        if m["kind"] != "#":
            items.append(("emit" if m["kind"] == "{" else "do", m["body"].strip()))
        at, strip = m.end(), bool(m["right"])
    rest = source[at:].lstrip() if strip else source[at:]
    if rest:
        items.append(("text", rest))
    place = 0

    def body(*ends: str) -> tuple[Node, str]:
        nonlocal place
        parts: list[Node] = []
        while place < len(items):
            kind, text = items[place]
            place += 1
            if kind == "text":
                parts.append(Node("text", value=text))
            elif kind == "emit":
                parts.append(Node("emit", (_Expression(_lex(text)).whole(),)))
            else:
                word = text.split(None, 1)[0] if text else ""
                if word in ends:
                    return Node("body", tuple(parts)), text
                parts.append(statement(word, text[len(word) :].strip()))
        if ends:
            raise TemplateError(f"missing {ends[-1]}")
        return Node("body", tuple(parts)), ""

    def statement(word: str, rest: str) -> Node:
        if word == "for":
            m = re.fullmatch(r"([A-Za-z]\w*)\s+in\s+(.*)", rest, re.S)
            if not m:
                raise TemplateError(f"unreadable loop: {rest!r}")
            inner, _ = body("endfor")
            return Node("for", (_Expression(_lex(m[2])).whole(), inner), m[1])
        if word == "if":
            parts, test = [], rest
            while True:
                inner, end = body("elif", "else", "endif")
                parts += [_Expression(_lex(test)).whole(), inner]
                if end == "endif":
                    return Node("if", tuple(parts))
                if end == "else":
                    inner, _ = body("endif")
                    return Node("if", (*parts, Node("const", value=True), inner))
                test = end[len("elif") :]
        if word == "set":
            m = re.fullmatch(r"([A-Za-z]\w*)\s*=\s*(.*)", rest, re.S)
            if not m:
                raise TemplateError(f"unreadable set: {rest!r}")
            return Node("set", (_Expression(_lex(m[2])).whole(),), m[1])
        if word == "generation":
            inner, _ = body("endgeneration")
            return Node("generation", (inner,))
        raise TemplateError(f"no statement {word!r}")

    return body()[0]


@dataclass
class Template:
    """A compiled template."""

    source: str
    tree: Node = field(init=False)

    def __post_init__(self) -> None:
        self.tree = fold(parse(self.source))
        self._run = _action(self.tree)

    def render(self, **context: Any) -> tuple[str, list[tuple[int, int]]]:
        """The text, and the spans of it that generation blocks wrote; adjoining spans stay apart only if text lies between."""
        out: Out = []
        self._run(dict(context), out, False)
        spans: list[tuple[int, int]] = []
        at = 0
        for text, learn in out:
            if learn and text:
                if spans and spans[-1][1] == at:
                    spans[-1] = (spans[-1][0], at + len(text))
                else:
                    spans.append((at, at + len(text)))
            at += len(text)
        return "".join(t for t, _ in out), spans


def read_back(text: str) -> list[tuple[str, str]]:
    """(role, text) of every turn of a conversation rendered with CHAT."""
    turns = []
    for piece in text.split(TURN)[1:]:
        head, _, rest = piece.partition("\n")
        turns.append((unlabel(head), unescape(rest.removesuffix("\n").removesuffix(END))))
    return turns


def format_conversations(rows: DataFrame, template: str = CHAT) -> DataFrame:
    """``conv_id, n_rows, text, loss_spans`` of every conversation in ``conv_id, turn, role, text``."""
    Template(template)  # a malformed one fails here

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        compiled, held, key, done = Template(template), [], None, []
        spans_type = pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))
        id_type = pa.int64()

        def emit() -> pa.RecordBatch:
            columns = list(zip(*done, strict=True))
            done.clear()
            return pa.RecordBatch.from_arrays([pa.array(columns[0], id_type), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.string()), pa.array([[{"start": a, "stop": b} for a, b in s] for s in columns[3]], spans_type)], ["conv_id", "n_rows", "text", "loss_spans"])

        def finish() -> None:
            if held:
                text, spans = compiled.render(messages=held)
                done.append((key, len(held), text, spans))

        size = 0
        for batch in batches:
            id_type = batch.schema.field(0).type
            for conv, role, text in zip(*(batch.column(k).to_pylist() for k in range(3)), strict=True):
                if held and conv != key:
                    finish()
                    held = []
                    if size > 4_000_000:
                        yield emit()
                        size = 0
                key = conv
                held.append({"role": role or "", "text": text or ""})
                size += len(text or "")
        finish()
        if done:
            yield emit()

    kind = rows.schema["conv_id"].dataType.simpleString()
    dealt = rows.select("conv_id", F.col("role").cast("string").alias("role"), F.col("text").cast("string").alias("text"), "turn").repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    return dealt.drop("turn").mapInArrow(run, f"conv_id {kind}, n_rows long, text string, loss_spans array<struct<start: bigint, stop: bigint>>")


def digests(formatted: DataFrame) -> DataFrame:
    """What can be read back from the formatted texts and their loss spans."""

    def run(texts: pa.Array, spans: pa.Array) -> pa.Array:
        out = []
        for text, marked in zip(texts.to_pylist(), spans.to_pylist(), strict=True):
            turns = read_back(text)
            learned = "".join(unescape(text[s["start"] : s["stop"]]) for s in marked)
            whole = "".join(f"{r}\n{t}\n" for r, t in turns)
            sha = lambda s: hashlib.sha256(s.encode("utf-8", "surrogatepass")).hexdigest()
            out.append({"n_turns": len(turns), "turns_sha256": sha(whole), "loss_chars": len(learned), "loss_sha256": sha(learned), "formatted_chars": len(text)})
        return pa.array(out, pa.struct([("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64())]))

    d = F.arrow_udf(run, "n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")("text", "loss_spans")
    return formatted.select("conv_id", d.alias("d")).select("conv_id", "d.*")
