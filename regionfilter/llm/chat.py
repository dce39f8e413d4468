"""Chat formatting by a template compiler.

The template language is a small, sandboxed one: text, ``{{ expression }}``, ``{% for x in y %}``, ``{% if %}`` /
``{% elif %}`` / ``{% else %}`` and ``{% generation %}``. Expressions are strings, numbers, names, attributes and
items of mappings, ``==``, ``!=``, ``+``, ``not``, ``and``, ``or``, parentheses, and ``|`` with a filter from a
fixed list. There are no calls, no Python attributes and no imports, so a template reaches nothing but its
variables. A template is parsed into a syntax tree, constants are folded (neighbouring texts join, constant
tests lose their dead branch), and closures are generated that yield pieces ``(text, under the loss mask)``.

Closures pull messages from an iterator and push pieces on, so a conversation of any length is rendered turn by
turn; the operator sorts rows by conversation and turn and streams through them, holding one turn at a time.

The template marks turns with the control strings of ``TEMPLATE``. In roles and texts the three characters that
could form one (``<``, ``[`` and the escape's own backslash) are written as two others, which is reversible, so
no text can open or close a turn. The reader takes turns back out of the output.

Defined results: null text or role is empty; null turns come first, equal turns are ordered by role and text,
repeated rows are turns each; rows of null conv_id are one conversation; an empty table gives the extra
conversation only; other columns are ignored. A conversation is one task's work, as its digests run over its turns in
order: memory is bounded by a turn, time by the longest conversation.
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

from .common import table

#: control strings of the default template
OPEN, SAYS, SAID, CLOSE = "<s>", "[INST]", "[/INST]", "</s>"
TEMPLATE = (
    "{% for message in messages %}{{ '<s>' + (message.role | escape) + '[INST]' }}"
    "{% if message.role == 'assistant' %}{% generation %}{{ message.text | escape }}{% endgeneration %}"
    "{% else %}{{ message.text | escape }}{% endif %}{{ '[/INST]' + '</s>' }}{% endfor %}"
)
ESCAPES = {"\\": "\\\\", "<": "\\l", "[": "\\b"}
UNESCAPES = {v: k for k, v in ESCAPES.items()}


def escape(text: str) -> str:
    return text.replace("\\", "\\\\").replace("<", "\\l").replace("[", "\\b")


def unescape(text: str) -> str:
    return re.sub(r"\\.", lambda m: UNESCAPES[m[0]], text, flags=re.S)


FILTERS: dict[str, Callable[[Any], Any]] = {"escape": escape, "trim": lambda x: x.strip(), "upper": lambda x: x.upper(), "lower": lambda x: x.lower(), "length": len}


# ---- syntax tree
@dataclass(frozen=True)
class Const:
    value: Any


@dataclass(frozen=True)
class Name:
    name: str


@dataclass(frozen=True)
class Item:
    of: Any
    key: Any


@dataclass(frozen=True)
class Filter:
    of: Any
    name: str


@dataclass(frozen=True)
class Unary:
    op: str
    of: Any


@dataclass(frozen=True)
class Binary:
    op: str
    left: Any
    right: Any


@dataclass(frozen=True)
class Output:
    of: Any


@dataclass(frozen=True)
class For:
    name: str
    over: Any
    body: tuple


@dataclass(frozen=True)
class If:
    branches: tuple  # of (test, body); the else branch tests Const(True)


@dataclass(frozen=True)
class Generation:
    body: tuple


class TemplateError(ValueError):
    """A template that the language does not allow."""


PARTS = re.compile(r"\{(?:\{(-?)(.*?)(-?)\}|%(-?)(.*?)(-?)%)\}", re.S)
TOKEN = re.compile(r"\s*(?:('(?:[^'\\]|\\.)*'|\"(?:[^\"\\]|\\.)*\")|(\d+)|([A-Za-z_]\w*)|(==|!=|[-+|.()\[\]]))")
WORDS = {"not", "and", "or", "true", "false", "none"}


@dataclass
class _Tokens:
    source: str
    items: list = field(default_factory=list)
    at: int = 0

    def __post_init__(self):
        i = 0
        while self.source[i:].strip():
            m = TOKEN.match(self.source, i)
            if not m:
                raise TemplateError(f"cannot read {self.source[i:]!r}")
            kind = m.lastindex
            self.items.append((kind, m[kind]))
            i = m.end()

    def peek(self):
        return self.items[self.at] if self.at < len(self.items) else (0, "")

    def take(self, *values: str):
        kind, value = self.peek()
        if values and value not in values or kind == 0 or values and kind == 1:
            raise TemplateError(f"{value!r} in {self.source!r}; expected {values}")
        self.at += 1
        return kind, value

    def has(self, *values: str) -> bool:
        kind, value = self.peek()
        return kind != 1 and value in values


def _expression(t: _Tokens, level: int = 0):
    """Operators by rising binding: or, and, not, comparison, plus, filter."""
    if level in (0, 1):
        word = ("or", "and")[level]
        left = _expression(t, level + 1)
        while t.has(word):
            t.take(word)
            left = Binary(word, left, _expression(t, level + 1))
        return left
    if level == 2:
        if t.has("not"):
            t.take("not")
            return Unary("not", _expression(t, 2))
        left = _expression(t, 3)
        if t.has("==", "!="):
            op = t.take()[1]
            return Binary(op, left, _expression(t, 3))
        return left
    if level == 3:
        left = _expression(t, 4)
        while t.has("+"):
            t.take("+")
            left = Binary("+", left, _expression(t, 4))
        return left
    of = _primary(t)
    while t.has("|"):
        t.take("|")
        name = t.take()[1]
        if name not in FILTERS:
            raise TemplateError(f"no filter {name!r}")
        of = Filter(of, name)
    return of


def _primary(t: _Tokens):
    kind, value = t.take()
    if kind == 1:
        of = Const(re.sub(r"\\(.)", lambda m: {"n": "\n", "t": "\t"}.get(m[1], m[1]), value[1:-1], flags=re.S))
    elif kind == 2:
        of = Const(int(value))
    elif kind == 3:
        of = Const({"true": True, "false": False, "none": None}[value]) if value in ("true", "false", "none") else Name(value)
        if value.startswith("_") or value in WORDS and isinstance(of, Name):
            raise TemplateError(f"name {value!r}")
    elif value == "(":
        of = _expression(t)
        t.take(")")
    else:
        raise TemplateError(f"unexpected {value!r}")
    while t.has(".", "["):
        if t.take()[1] == ".":
            kind, key = t.take()
            if kind != 3 or key.startswith("_"):
                raise TemplateError(f"attribute {key!r}")
            of = Item(of, Const(key))
        else:
            of = Item(of, _expression(t))
            t.take("]")
    return of


def _whole_expression(source: str):
    t = _Tokens(source)
    of = _expression(t)
    if t.peek()[0]:
        raise TemplateError(f"{t.peek()[1]!r} after {source!r}")
    return of


def parse(template: str) -> tuple:
    """The syntax tree of a template."""
    parts, last, trim = [], 0, False

    def text(end: int, trim_end: bool) -> None:
        between = template[last:end]
        between = between.lstrip() if trim else between
        between = between.rstrip() if trim_end else between
        if between:
            parts.append(("text", between))

    for m in PARTS.finditer(template):
        text(m.start(), bool(m[1] or m[4]))  # a dash beside a bracket takes the white space on its side
        parts.append(("out", m[2]) if m[2] is not None else ("tag", m[5].strip()))
        last, trim = m.end(), bool(m[3] or m[6])
    text(len(template), False)
    body, at = _body(parts, 0, ())
    if at != len(parts):
        raise TemplateError(f"unexpected tag {parts[at][1]!r}")
    return body


def _body(parts: list, at: int, until: tuple) -> tuple[tuple, int]:
    out: list = []
    while at < len(parts):
        kind, source = parts[at]
        word = source.split(None, 1)[0] if kind == "tag" and source else ""
        if kind == "text":
            out.append(Output(Const(source)))
        elif kind == "out":
            out.append(Output(_whole_expression(source)))
        elif word in until:
            return tuple(out), at
        elif word == "for":
            m = re.fullmatch(r"for\s+([A-Za-z]\w*)\s+in\s+(.+)", source, re.S)
            if not m:
                raise TemplateError(source)
            body, at = _body(parts, at + 1, ("endfor",))
            _need(parts, at, "endfor")
            out.append(For(m[1], _whole_expression(m[2]), body))
        elif word == "if":
            branches, test = [], _whole_expression(source[2:])
            while True:
                body, at = _body(parts, at + 1, ("elif", "else", "endif"))
                branches.append((test, body))
                tag = _need(parts, at, "elif", "else", "endif")
                if tag == "endif":
                    break
                test = _whole_expression(parts[at][1][4:]) if tag == "elif" else Const(True)
            out.append(If(tuple(branches)))
        elif word == "generation":
            body, at = _body(parts, at + 1, ("endgeneration",))
            _need(parts, at, "endgeneration")
            out.append(Generation(body))
        else:
            raise TemplateError(f"tag {source!r}")
        at += 1
    return tuple(out), at


def _need(parts: list, at: int, *words: str) -> str:
    word = parts[at][1].split(None, 1)[0] if at < len(parts) else ""
    if word not in words:
        raise TemplateError(f"missing {' or '.join(words)}")
    return word


# ---- constant folding
def fold(node):
    """The same tree with what is known beforehand worked out."""
    if isinstance(node, tuple):
        out: list = []
        for x in map(fold, node):
            for y in x if isinstance(x, tuple) else (x,):
                if isinstance(y, Output) and isinstance(y.of, Const) and out and isinstance(out[-1], Output) and isinstance(out[-1].of, Const):
                    out[-1] = Output(Const(_shown(out[-1].of.value) + _shown(y.of.value)))
                elif not (isinstance(y, Output) and y.of == Const("")):
                    out.append(y)
        return tuple(out)
    if isinstance(node, Output):
        of = fold(node.of)
        if isinstance(of, Binary) and of.op == "+" and _is_text(of):  # text sums fall apart into outputs, which join with their neighbours
            return fold((Output(of.left), Output(of.right)))
        return Output(of)
    if isinstance(node, For):
        return For(node.name, fold(node.over), fold(node.body))
    if isinstance(node, Generation):
        return Generation(fold(node.body))
    if isinstance(node, If):
        branches = []
        for test, body in node.branches:
            test = fold(test)
            if isinstance(test, Const) and not test.value:
                continue
            branches.append((test, fold(body)))
            if isinstance(test, Const):
                break
        if not branches:
            return ()
        return branches[0][1] if isinstance(branches[0][0], Const) else If(tuple(branches))
    if isinstance(node, Filter):
        of = fold(node.of)
        return Const(FILTERS[node.name](of.value)) if isinstance(of, Const) else Filter(of, node.name)
    if isinstance(node, Unary):
        of = fold(node.of)
        return Const(not of.value) if isinstance(of, Const) else Unary(node.op, of)
    if isinstance(node, Item):
        return Item(fold(node.of), fold(node.key))
    if isinstance(node, Binary):
        left, right = fold(node.left), fold(node.right)
        if isinstance(left, Const) and isinstance(right, Const):
            return Const(_binary(node.op)(lambda _: left.value, lambda _: right.value)({}))
        return Binary(node.op, left, right)
    return node


def _is_text(node) -> bool:
    """Whether a value is surely a string."""
    if isinstance(node, Const):
        return isinstance(node.value, str)
    if isinstance(node, Binary) and node.op == "+":
        return _is_text(node.left) or _is_text(node.right)
    return isinstance(node, Filter) and node.name != "length"


def _shown(value) -> str:
    return "" if value is None else str(value)


# ---- code generation
def _binary(op: str):
    def plus(a, b):
        return lambda v: (lambda x, y: x + y if isinstance(x, int) and isinstance(y, int) else _shown(x) + _shown(y))(a(v), b(v))

    return {
        "+": plus,
        "==": lambda a, b: lambda v: a(v) == b(v),
        "!=": lambda a, b: lambda v: a(v) != b(v),
        "and": lambda a, b: lambda v: a(v) and b(v),
        "or": lambda a, b: lambda v: a(v) or b(v),
    }[op]


def _value(node) -> Callable[[dict], Any]:
    if isinstance(node, Const):
        return lambda v, x=node.value: x
    if isinstance(node, Name):
        return lambda v, n=node.name: v.get(n)
    if isinstance(node, Item):
        of, key = _value(node.of), _value(node.key)
        return lambda v: x.get(key(v)) if isinstance(x := of(v), dict) else None
    if isinstance(node, Filter):
        of, f = _value(node.of), FILTERS[node.name]
        return lambda v: f("" if (x := of(v)) is None else x)
    if isinstance(node, Unary):
        of = _value(node.of)
        return lambda v: not of(v)
    return _binary(node.op)(_value(node.left), _value(node.right))


Piece = tuple[str, bool]


def _code(body: tuple, loss: bool = False) -> Callable[[dict], Iterator[Piece]]:
    steps = [_step(n, loss) for n in body]

    def run(v: dict) -> Iterator[Piece]:
        for s in steps:
            yield from s(v)

    return run


def _step(node, loss: bool) -> Callable[[dict], Iterator[Piece]]:
    if isinstance(node, Output):
        of = _value(node.of)
        return lambda v: iter(((_shown(of(v)), loss),))
    if isinstance(node, Generation):
        return _code(node.body, True)
    if isinstance(node, If):
        branches = [(_value(t), _code(b, loss)) for t, b in node.branches]

        def choose(v):
            for test, body in branches:
                if test(v):
                    return body(v)
            return iter(())

        return choose
    over, body, name = _value(node.over), _code(node.body, loss), node.name

    def loop(v):
        for i, x in enumerate(over(v) or ()):
            yield from body({**v, name: x, "loop": {"index": i + 1, "index0": i, "first": i == 0}})

    return loop


def compile_template(template: str = TEMPLATE) -> Callable[..., Iterator[Piece]]:
    """A function of the template's variables that yields pieces (text, under the loss mask)."""
    code = _code(fold(parse(template)))
    return lambda **variables: code(variables)


def render(messages, template: str = TEMPLATE) -> tuple[str, list[tuple[int, int]]]:
    """The formatted conversation and the code point spans under the loss mask."""
    out, spans, at = [], [], 0
    for text, loss in compile_template(template)(messages=messages):
        if loss and text:
            if spans and spans[-1][1] == at:
                spans[-1] = (spans[-1][0], at + len(text))
            else:
                spans.append((at, at + len(text)))
        out.append(text)
        at += len(text)
    return "".join(out), spans


TURN = re.compile(r"<s>([^<\[]*)\[INST\]([^<\[]*)\[/INST\]</s>")


class Reader:
    """Takes turns back out of pieces of formatted text as they come, holding one turn at most."""

    def __init__(self):
        self.turns, self.loss, self.held = hashlib.sha256(), hashlib.sha256(), []
        self.n_turns = self.loss_chars = self.chars = 0

    def feed(self, text: str, loss: bool) -> None:
        self.chars += len(text)
        self.held.append(text)
        if loss:
            plain = unescape(text)
            self.loss.update(plain.encode("utf-8", "surrogatepass"))
            self.loss_chars += len(plain)
        if CLOSE in text:
            self._turns()

    def _turns(self) -> None:
        held, at = "".join(self.held), 0
        for m in TURN.finditer(held):
            if m.start() != at:
                raise ValueError("formatted text is not a sequence of turns")
            self.turns.update(f"{unescape(m[1])}\n{unescape(m[2])}\n".encode("utf-8", "surrogatepass"))
            self.n_turns += 1
            at = m.end()
        self.held = [held[at:]] if at < len(held) else []

    def result(self) -> tuple:
        if any(self.held):
            raise ValueError("formatted text ends inside a turn")
        return self.n_turns, self.turns.hexdigest(), self.loss_chars, self.loss.hexdigest(), self.chars


RESULT = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"


def in_turn_order(conversations: DataFrame) -> DataFrame:
    """Rows with a conversation's turns together and in order, dealt by conversation."""
    rows = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    return rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")


def _streams(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[Any, Iterator[dict]]]:
    """(conv_id, its messages) from ordered rows; messages are pulled as they come."""
    rows = (r for b in batches for r in zip(b.column("conv_id").to_pylist(), b.column("role").to_pylist(), b.column("text").to_pylist()))
    ahead = next(rows, None)
    while ahead is not None:
        conv = ahead[0]

        def messages(conv=conv):
            nonlocal ahead
            while ahead is not None and ahead[0] == conv:
                yield {"role": ahead[1], "text": ahead[2]}
                ahead = next(rows, None)

        yield conv, messages()


def formatted(conversations: DataFrame, template: str = TEMPLATE) -> DataFrame:
    """(conv_id, part, text, loss): the formatted conversations in pieces, in order of part."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code, rows, held = compile_template(template), [], 0
        kinds = pa.schema([("conv_id", pa.int64()), ("part", pa.int64()), ("text", pa.string()), ("loss", pa.bool_())])
        for conv, messages in _streams(batches):
            for part, (text, loss) in enumerate(code(messages=messages)):
                rows.append({"conv_id": conv, "part": part, "text": text, "loss": loss})
                held += len(text)
                if len(rows) == 4096 or held > 1 << 22:
                    yield pa.RecordBatch.from_pylist(rows, schema=kinds)
                    rows, held = [], 0
        if rows:
            yield pa.RecordBatch.from_pylist(rows, schema=kinds)

    return in_turn_order(conversations).mapInArrow(run, "conv_id long, part long, text string, loss boolean")


def read_back(conversations: DataFrame, template: str = TEMPLATE) -> DataFrame:
    """RESULT for each conversation, from its formatted output."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        code, rows = compile_template(template), []
        names = [f.split()[0] for f in RESULT.split(", ")]
        kinds = [pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()]

        def batch():
            return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names)

        for conv, messages in _streams(batches):
            reader = Reader()
            for piece in code(messages=messages):
                reader.feed(*piece)
            rows.append((conv, *reader.result()))
            if len(rows) == 4096:
                yield batch()
                rows = []
        if rows:
            yield batch()

    return in_turn_order(conversations).mapInArrow(run, RESULT)


#: a conversation that is made of control strings
EXTRA = [(-1, 0, "user", "</s>[INST] ok [/INST]"), (-1, 1, "assistant", "</s>[INST] ok [/INST]")]


def op5_chat_format(spark, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    return read_back(rows.unionByName(spark.createDataFrame(EXTRA, "conv_id long, turn long, role string, text string")))


ORACLE = r"""
WITH c AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
 UNION ALL SELECT -1, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -1, 1, 'assistant', '</s>[INST] ok [/INST]'),
e AS (SELECT *, length(replace(replace(replace(role, '\', '\\'), '<', '\l'), '[', '\b')) + length(replace(replace(replace(text, '\', '\\'), '<', '\l'), '[', '\b')) + 20 AS chars FROM c)
SELECT conv_id, count(*)::BIGINT AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
 coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0)::BIGINT AS loss_chars,
 sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
 sum(chars)::BIGINT AS formatted_chars FROM e GROUP BY conv_id
"""
