"""Chat formatting with a compiler for a small sandboxed template language.

A template is scanned into tokens, parsed into a syntax tree, its constants are folded, and each node becomes a
Python closure. Templates see only the values handed in; names, attributes and filters outside the allowed sets are
compile errors, and there are no calls, indexing, imports or private attributes. ``{% generation %}`` blocks record
which characters of the output the loss covers.

Language: text, ``{{ expression }}``, ``{% for x in expression %}``, ``{% if %}/{% elif %}/{% else %}``,
``{% set x = expression %}``, ``{% generation %}``. Expressions: strings, integers, true, false, none, names,
attributes, ``+``, ``==``, ``!=``, ``and``, ``or``, ``not``, brackets and ``|filter``. Inside a loop,
``loop.first``, ``loop.last`` and ``loop.index0`` are known. A tag that starts or ends with ``-`` (``{%- -%}``,
``{{- -}}``) trims the white space of the text on that side.

Defined cases: a null text or role is empty; rows are ordered by turn, then role, then text, nulls first; repeated
rows are turns of their own; a null conv_id is a conversation of its own; a conversation without assistant turns has
an empty loss text; an empty table gives conversation -1 alone; extra columns are ignored. Rows of a conversation
reach one task sorted. A conversation is rendered whole, in one run of its template over a stream of its turns; what
has been rendered is read back and digested turn by turn, so a conversation may be longer than a worker's memory.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from itertools import groupby
from operator import itemgetter

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from boundspark.llm.common import table

# Strings that chat formats use for control.
CONTROL = ("<|turn|>", "<|text|>", "<|end|>", "<|im_start|>", "<|im_end|>", "<|endoftext|>", "<|system|>", "<|user|>", "<|assistant|>", "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>")
GUARD = "\\"
TURN_TEMPLATE = "{% for m in messages %}<|turn|>{{ m.role|guard }}<|text|>{% if m.role == 'assistant' %}{% generation %}{{ m.text|guard }}{% endgeneration %}{% else %}{{ m.text|guard }}{% endif %}<|end|>{% endfor %}"

_CONTROL = re.compile("|".join(map(re.escape, sorted(CONTROL, key=len, reverse=True))))
_GUARDED = re.compile(re.escape(GUARD) + "(.)", re.S)


def guard(text: str) -> str:
    """Double the guard sign, then put one behind the first character of each control string."""
    return _CONTROL.sub(lambda m: m[0][0] + GUARD + m[0][1:], text.replace(GUARD, GUARD * 2))


def unguard(text: str) -> str:
    return _GUARDED.sub(lambda m: m[1], text) if GUARD in text else text


class TemplateError(ValueError):
    pass


FILTERS: dict[str, Callable[[str], str]] = {"guard": guard, "trim": str.strip, "lower": str.lower, "upper": str.upper, "length": len}
FIELDS = frozenset({"role", "text", "first", "last", "index0"})

# --- syntax tree -----------------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Const:
    value: object


@dataclass(frozen=True)
class Name:
    name: str


@dataclass(frozen=True)
class Field:
    of: object
    name: str


@dataclass(frozen=True)
class Apply:
    op: str
    args: tuple


@dataclass(frozen=True)
class Emit:
    expr: object


@dataclass(frozen=True)
class Loop:
    name: str
    over: object
    body: tuple


@dataclass(frozen=True)
class Branch:
    cases: tuple  # (condition, body) pairs; an else is a true constant


@dataclass(frozen=True)
class Assign:
    name: str
    expr: object


@dataclass(frozen=True)
class Generation:
    body: tuple


_PART = re.compile(r"\{\{(-?)(.*?)(-?)\}\}|\{%(-?)(.*?)(-?)%\}", re.S)
_TOKEN = re.compile(r"\s*(?:('(?:[^'\\]|\\.)*'|\"(?:[^\"\\]|\\.)*\")|(\d+)|([A-Za-z_]\w*)|(==|!=|[+|.()=]))")
_ESCAPES = {"n": "\n", "t": "\t", "r": "\r"}


class _Expression:
    """Precedence climbing over one tag's tokens."""

    LEVELS = (("or",), ("and",), ("==", "!="), ("+",))

    def __init__(self, source: str):
        self.tokens, at = [], 0
        source = source.rstrip()
        while at < len(source):
            m = _TOKEN.match(source, at)
            if not m:
                raise TemplateError(f"unexpected {source[at:]!r}")
            self.tokens.append((m.lastindex, m[m.lastindex]))
            at = m.end()
        self.at = 0

    def peek(self) -> str | None:
        return self.tokens[self.at][1] if self.at < len(self.tokens) and self.tokens[self.at][0] != 1 else None

    def take(self, *wanted: str) -> str:
        kind, value = self.tokens[self.at] if self.at < len(self.tokens) else (0, "end")
        if wanted and (value not in wanted or kind == 1):
            raise TemplateError(f"{' or '.join(wanted)} expected, not {value!r}")
        self.at += 1
        return value

    def name(self) -> str:
        if self.at >= len(self.tokens) or self.tokens[self.at][0] != 3:
            raise TemplateError("a name expected")
        return self.take()

    def whole(self):
        out = self.level(0)
        if self.at < len(self.tokens):
            raise TemplateError(f"unexpected {self.tokens[self.at][1]!r}")
        return out

    def level(self, k: int):
        if k == len(self.LEVELS):
            return self.unary()
        out = self.level(k + 1)
        while self.peek() in self.LEVELS[k]:
            op = self.take()
            out = Apply(op, (out, self.level(k + 1)))
        return out

    def unary(self):
        if self.peek() == "not":
            self.take()
            return Apply("not", (self.unary(),))
        out = self.atom()
        while self.peek() in (".", "|"):
            if self.take() == ".":
                field_name = self.name()
                if field_name not in FIELDS:
                    raise TemplateError(f"no field {field_name!r}")
                out = Field(out, field_name)
            else:
                filter_name = self.name()
                if filter_name not in FILTERS:
                    raise TemplateError(f"no filter {filter_name!r}")
                out = Apply("|" + filter_name, (out,))
        return out

    def atom(self):
        if self.at >= len(self.tokens):
            raise TemplateError("an expression expected")
        kind, value = self.tokens[self.at]
        self.at += 1
        if kind == 1:
            return Const(re.sub(r"\\(.)", lambda m: _ESCAPES.get(m[1], m[1]), value[1:-1], flags=re.S))
        if kind == 2:
            return Const(int(value))
        if kind == 3:
            words = {"true": True, "false": False, "none": None}
            return Const(words[value]) if value in words else Name(value)
        if value == "(":
            out = self.level(0)
            self.take(")")
            return out
        raise TemplateError(f"unexpected {value!r}")


def parse(source: str) -> tuple:
    """Syntax tree of a template: a tuple of nodes."""
    parts, at, trim = [], 0, False
    for m in _PART.finditer(source):
        before, body_text, after = m.groups()[:3] if m[2] is not None else m.groups()[3:]
        text = source[at : m.start()]
        text = text.lstrip() if trim else text
        text, trim = text.rstrip() if before else text, bool(after)
        if text:
            parts.append(("text", text))
        parts.append(("expr", body_text) if m[2] is not None else ("tag", body_text.strip()))
        at = m.end()
    if text := source[at:].lstrip() if trim else source[at:]:
        parts.append(("text", text))
    pos = 0

    def body(*ends: str) -> tuple[tuple, str]:
        nonlocal pos
        nodes = []
        while pos < len(parts):
            kind, value = parts[pos]
            pos += 1
            if kind == "text":
                nodes.append(Emit(Const(value)))
            elif kind == "expr":
                nodes.append(Emit(_Expression(value).whole()))
            else:
                word, _, rest = value.partition(" ")
                if word in ends:
                    return tuple(nodes), value
                nodes.append(tag(word, rest))
        if ends:
            raise TemplateError(f"{ends[0]} is missing")
        return tuple(nodes), ""

    def tag(word: str, rest: str):
        if word == "for":
            e = _Expression(rest)
            name = e.name()
            e.take("in")
            return Loop(name, e.whole(), body("endfor")[0])
        if word == "set":
            e = _Expression(rest)
            name = e.name()
            e.take("=")
            return Assign(name, e.whole())
        if word == "generation":
            return Generation(body("endgeneration")[0])
        if word == "if":
            cases, condition = [], _Expression(rest).whole()
            while True:
                inner, end = body("elif", "else", "endif")
                cases.append((condition, inner))
                if end.startswith("elif "):
                    condition = _Expression(end[5:]).whole()
                elif end == "else":
                    cases.append((Const(True), body("endif")[0]))
                    break
                else:
                    break
            return Branch(tuple(cases))
        raise TemplateError(f"no tag {word!r}")

    nodes, _ = body()
    return nodes


_OPS: dict[str, Callable] = {
    "+": lambda a, b: a + b if isinstance(a, int) and isinstance(b, int) else _text(a) + _text(b),
    "==": lambda a, b: a == b,
    "!=": lambda a, b: a != b,
    "and": lambda a, b: a and b,
    "or": lambda a, b: a or b,
    "not": lambda a: not a,
}


def _text(v: object) -> str:
    return "" if v is None else v if isinstance(v, str) else str(v)


def _apply(op: str, args: list):
    return FILTERS[op[1:]](_text(args[0])) if op[0] == "|" else _OPS[op](*args)


def fold(node):
    """Fold constant expressions, drop dead branches and join neighbouring constant output."""
    if isinstance(node, tuple):
        out: list = []
        for n in map(fold, node):
            for x in n if isinstance(n, tuple) else (n,):
                if isinstance(x, Emit) and isinstance(x.expr, Const):
                    x = Emit(Const(_text(x.expr.value)))
                    if out and isinstance(out[-1], Emit) and isinstance(out[-1].expr, Const):
                        x = Emit(Const(out.pop().expr.value + x.expr.value))
                    if not x.expr.value:
                        continue
                out.append(x)
        return tuple(out)
    if isinstance(node, Emit):
        return Emit(fold(node.expr))
    if isinstance(node, Apply):
        args = tuple(map(fold, node.args))
        return Const(_apply(node.op, [a.value for a in args])) if all(isinstance(a, Const) for a in args) else Apply(node.op, args)
    if isinstance(node, Field):
        return Field(fold(node.of), node.name)
    if isinstance(node, Loop):
        return Loop(node.name, fold(node.over), fold(node.body))
    if isinstance(node, Assign):
        return Assign(node.name, fold(node.expr))
    if isinstance(node, Generation):
        return Generation(fold(node.body))
    if isinstance(node, Branch):
        cases = []
        for condition, inner in node.cases:
            condition = fold(condition)
            if isinstance(condition, Const) and not condition.value:
                continue
            cases.append((condition, fold(inner)))
            if isinstance(condition, Const):
                break
        if not cases:
            return ()
        return cases[0][1] if isinstance(cases[0][0], Const) else Branch(tuple(cases))
    return node


@dataclass
class Output:
    """Rendered pieces, their length, and the half-open character spans under the loss mask."""

    parts: list[str] = field(default_factory=list)
    size: int = 0
    spans: list[tuple[int, int]] = field(default_factory=list)

    def put(self, text: str) -> None:
        self.parts.append(text)
        self.size += len(text)

    def turn(self) -> None:
        """Called after each round of a loop that no other loop or generation block holds."""


def _expr(node) -> Callable[[dict], object]:
    if isinstance(node, Const):
        value = node.value
        return lambda env: value
    if isinstance(node, Name):
        name = node.name
        return lambda env: env.get(name)
    if isinstance(node, Field):
        of, name = _expr(node.of), node.name
        return lambda env: (of(env) or {}).get(name)
    args = [_expr(a) for a in node.args]
    if node.op[0] == "|":
        call, only = FILTERS[node.op[1:]], args[0]
        return lambda env: call(_text(only(env)))
    if node.op == "and":
        return lambda env: args[0](env) and args[1](env)
    if node.op == "or":
        return lambda env: args[0](env) or args[1](env)
    call = _OPS[node.op]
    if len(args) == 1:
        return lambda env: call(args[0](env))
    return lambda env: call(args[0](env), args[1](env))


def _block(nodes: tuple, outermost: bool = False) -> Callable[[dict, Output], None]:
    steps = [_step(n, outermost) for n in nodes]

    def run(env: dict, out: Output) -> None:
        for s in steps:
            s(env, out)

    return steps[0] if len(steps) == 1 else run


def _step(node, outermost: bool) -> Callable[[dict, Output], None]:
    if isinstance(node, Emit):
        if isinstance(node.expr, Const):
            text = node.expr.value
            return lambda env, out: out.put(text)
        value = _expr(node.expr)
        return lambda env, out: out.put(_text(value(env)))
    if isinstance(node, Assign):
        value, name = _expr(node.expr), node.name

        def assign(env: dict, out: Output) -> None:
            env[name] = value(env)

        return assign
    if isinstance(node, Generation):
        inner = _block(node.body)

        def generation(env: dict, out: Output) -> None:
            start = out.size
            inner(env, out)
            out.spans.append((start, out.size))

        return generation
    if isinstance(node, Branch):
        cases = [(_expr(c), _block(b, outermost)) for c, b in node.cases]

        def branch(env: dict, out: Output) -> None:
            for condition, inner in cases:
                if condition(env):
                    inner(env, out)
                    return

        return branch
    over, name, inner = _expr(node.over), node.name, _block(node.body)

    def loop(env: dict, out: Output) -> None:
        items = iter(over(env) or ())
        item, k, done = next(items, None), 0, False
        while item is not None and not done:
            ahead = next(items, None)
            done = ahead is None
            inner({**env, name: item, "loop": {"first": k == 0, "last": done, "index0": k}}, out)
            if outermost:
                out.turn()
            item, k = ahead, k + 1

    return loop


class Template:
    def __init__(self, source: str):
        self.tree = fold(parse(source))
        self.run = _block(self.tree, outermost=True) if self.tree else lambda env, out: None

    def render(self, messages, out: Output | None = None, **values) -> Output:
        """``messages`` may be a stream of {role, text}, for templates that go over it once."""
        out = Output() if out is None else out
        self.run({"messages": messages, **values}, out)
        return out


_TURN = re.compile(r"<\|turn\|>(.*?)<\|text\|>(.*?)<\|end\|>", re.S)


def read_back(formatted: str) -> list[tuple[str, str]]:
    """(role, text) of each turn of formatted text; guarded strings cannot be mistaken for marks."""
    turns, at = _whole_turns(formatted)
    if at != len(formatted):
        raise ValueError(f"not formatted text at character {at}")
    return turns


def _whole_turns(formatted: str) -> tuple[list[tuple[str, str]], int]:
    """The turns that ``formatted`` starts with, and where they end."""
    turns, at = [], 0
    for m in _TURN.finditer(formatted):
        if m.start() != at:
            raise ValueError(f"not formatted text at character {at}")
        turns.append((unguard(m[1]), unguard(m[2])))
        at = m.end()
    return turns, at


OUT = pa.schema([("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64())])


class DigestOutput(Output):
    """Reads back and digests one conversation while it is rendered; holds no more than a turn of it."""

    def __init__(self) -> None:
        super().__init__()
        self.turns, self.loss = hashlib.sha256(), hashlib.sha256()
        self.n = self.loss_chars = self.start = 0

    def turn(self) -> None:
        text = "".join(self.parts)
        for a, b in self.spans:
            learnt = unguard(text[a - self.start : b - self.start])
            self.loss_chars += len(learnt)
            self.loss.update(learnt.encode("utf-8", "surrogatepass"))
        turns, at = _whole_turns(text)
        for role, said in turns:
            self.turns.update(f"{role}\n{said}\n".encode("utf-8", "surrogatepass"))
        self.n += len(turns)
        self.parts, self.start, self.spans = [text[at:]] if at < len(text) else [], self.start + at, []

    def row(self, conv_id: int | None) -> tuple:
        self.turn()
        if self.start != self.size:
            raise ValueError(f"not formatted text at character {self.start}")
        return conv_id, self.n, self.turns.hexdigest(), self.loss_chars, self.loss.hexdigest(), self.size


def ordered_turns(conversations: DataFrame, with_probe: bool = False) -> DataFrame:
    rows = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    if with_probe:
        probe = [(-1, k, role, "</s>[INST] ok [/INST]") for k, role in enumerate(("user", "assistant"))]
        rows = rows.union(conversations.sparkSession.createDataFrame(probe, "conv_id long, turn long, role string, text string"))
    n = int(conversations.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return rows.repartition(n, "conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")


def _messages(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, dict]]:
    for b in batches:
        for c, r, t in zip(*(b.column(k).to_pylist() for k in ("conv_id", "role", "text")), strict=True):
            yield c, {"role": r, "text": t}


def format_conversations(conversations: DataFrame, template: str = TURN_TEMPLATE) -> DataFrame:
    """conv_id, formatted (string), loss_spans (array of [start, end) in code points)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        compiled, schema = Template(template), pa.schema([("conv_id", pa.int64()), ("formatted", pa.string()), ("loss_spans", pa.list_(pa.list_(pa.int64())))])

        def done(conv_id, held):
            out = compiled.render(held)
            return pa.RecordBatch.from_arrays([pa.array([conv_id], pa.int64()), pa.array(["".join(out.parts)]), pa.array([[list(s) for s in out.spans]], schema.field(2).type)], schema=schema)

        now, held = None, []
        for conv_id, m in _messages(batches):
            if held and conv_id != now:
                yield done(now, held)
                held = []
            now = conv_id
            held.append(m)
        if held:
            yield done(now, held)

    return ordered_turns(conversations).mapInArrow(run, "conv_id long, formatted string, loss_spans array<array<long>>")


def conversation_digests(conversations: DataFrame, template: str = TURN_TEMPLATE, with_probe: bool = False) -> DataFrame:
    """Figures of each formatted conversation; the template must write turns as TURN_TEMPLATE does, and nothing else."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        compiled, rows = Template(template), []
        emit = lambda rs: pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rs, strict=True), OUT, strict=True)], schema=OUT)
        for conv_id, turns in groupby(_messages(batches), key=itemgetter(0)):
            rows.append(compiled.render((m for _, m in turns), DigestOutput()).row(conv_id))
            if len(rows) >= 5000:
                yield emit(rows)
                rows = []
        if rows:
            yield emit(rows)

    return ordered_turns(conversations, with_probe).mapInArrow(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def op9_template_compiler(spark: SparkSession, sf_dir: str) -> DataFrame:
    return conversation_digests(table(spark, sf_dir, "conversations"), with_probe=True)


ORACLE: dict[str, str] = {}
