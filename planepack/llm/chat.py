"""Chat formatting: a compiler for a small sandboxed template language.

Template text is parsed into a syntax tree, constants are folded, and the tree becomes Python closures that yield
(piece of output, is it under the loss mask).  The language has ``{{ expression }}``, ``{% for x in y %}``, ``{% if %}/{% elif %}/
{% else %}``, ``{% set x = e %}`` and ``{% generation %}``, which marks what the model is trained on.  Expressions: strings,
integers, ``true/false/none``, names, ``a.b`` and ``a['b']`` (keys of mappings only: the sandbox reaches no Python attribute and
calls nothing), ``+ ~ == != < > and or not in``, ``x if c else y`` and filters from a fixed list.

Loops take any iterator, so a conversation streams: rows come sorted by turn, one turn is held at a time, and a conversation of any
length needs constant memory.  The output is read back turn by turn from the formatted text alone.

Texts are escaped reversibly: ``\\``, ``<``, ``[`` and ``|`` become ``\\\\``, ``\\l``, ``\\b`` and ``\\p``, so none of the control
strings (all begin with ``<`` or ``[``) can occur inside a text.  Defined results: null role or text is empty; turns order by turn (null first), role, text; repeated rows are turns of their own;
a null conv_id is a conversation.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common as C

TEMPLATE = (
    "{% for m in messages %}<|turn|>{{ m.role | escape }}<|text|>"
    "{% if m.role == 'assistant' %}{% generation %}{{ m.text | escape }}{% endgeneration %}"
    "{% else %}[INST] {{ m.text | escape }} [/INST]{% endif %}"
    "<|end|>{{ '\\n' }}{% endfor %}"
)
_ESCAPES = {"\\": "\\\\", "<": "\\l", "[": "\\b", "|": "\\p"}
_BACK = {"\\": "\\", "l": "<", "b": "[", "p": "|"}
_TABLE = str.maketrans(_ESCAPES)


def escape(s: str) -> str:
    return s.translate(_TABLE)


def unescape(s: str) -> str:
    return re.sub(r"\\(.)", lambda m: _BACK[m[1]], s, flags=re.S) if "\\" in s else s


class TemplateError(ValueError):
    pass


def _on_text(f: Callable) -> Callable:
    return lambda v: f(v if isinstance(v, str) else "" if v is None else str(v))


def _length(v) -> int:
    try:
        return len(v)
    except TypeError as e:
        raise TemplateError(f"{type(v).__name__} has no length") from e


FILTERS: dict[str, Callable] = {**{k: _on_text(f) for k, f in (("escape", escape), ("trim", str.strip), ("upper", str.upper), ("lower", str.lower), ("string", str))}, "length": _length}


# ---------------------------------------------------------------- parsing

#: A minus inside a tag's brace takes the white space of the text on that side away.
_TAG = re.compile(r"(?:\s*\{\{-|\{\{)(.*?)(?:-\}\}\s*|\}\})|(?:\s*\{%-|\{%)(.*?)(?:-%\}\s*|%\})|(?:\s*\{#-|\{#).*?(?:-#\}\s*|#\})", re.S)
_TOKEN = re.compile(r"""\s*(?:(\d+)|('(?:[^'\\]|\\.)*'|"(?:[^"\\]|\\.)*")|([A-Za-z_]\w*)|(==|!=|[-+~<>.\[\]()|]))""", re.S)
_CHARS = {"n": "\n", "t": "\t", "r": "\r"}


def _tokens(s: str) -> list[tuple[str, object]]:
    out, at = [], 0
    while s[at:].strip():
        m = _TOKEN.match(s, at)
        if not m:
            raise TemplateError(f"unexpected {s[at:].strip()[:10]!r}")
        if m[1]:
            out.append(("const", int(m[1])))
        elif m[2]:
            out.append(("const", re.sub(r"\\(.)", lambda x: _CHARS.get(x[1], x[1]), m[2][1:-1], flags=re.S)))
        else:
            out.append(("name", m[3]) if m[3] else ("op", m[4]))
        at = m.end()
    return out


class _Expression:
    """Recursive descent; nodes are tuples (kind, ...)."""

    def __init__(self, text: str):
        self.t, self.i = _tokens(text), 0

    def peek(self, *values) -> bool:
        return self.i < len(self.t) and self.t[self.i][0] != "const" and self.t[self.i][1] in values

    def take(self, *values):
        if self.peek(*values):
            self.i += 1
            return self.t[self.i - 1][1]
        return None

    def need(self, value):
        if not self.take(value):
            raise TemplateError(f"{value!r} is missing")

    def whole(self):
        e = self.choice()
        if self.i < len(self.t):
            raise TemplateError(f"unexpected {self.t[self.i][1]!r}")
        return e

    def choice(self):
        e = self.binary(0)
        if self.take("if"):
            c = self.binary(0)
            self.need("else")
            return ("choice", c, e, self.choice())
        return e

    LEVELS = (("or",), ("and",), ("==", "!=", "<", ">", "in"), ("+", "-", "~"))

    def binary(self, level):
        if level == len(self.LEVELS):
            return self.postfix()
        if level == 2 and self.take("not"):
            return ("not", self.binary(2))
        e = self.binary(level + 1)
        while True:
            if level == 2 and self.peek("not") and self.i + 1 < len(self.t) and self.t[self.i + 1] == ("name", "in"):
                self.i += 2
                e = ("not", ("binary", "in", e, self.binary(level + 1)))
            elif op := self.take(*self.LEVELS[level]):
                e = ("binary", op, e, self.binary(level + 1))
            else:
                return e

    def postfix(self):
        e = self.atom()
        while True:
            if self.take("."):
                kind, name = self.t[self.i] if self.i < len(self.t) else ("", "")
                if kind != "name":
                    raise TemplateError("a key is missing after '.'")
                self.i += 1
                e = ("key", e, ("const", name))
            elif self.take("["):
                k = self.choice()
                self.need("]")
                e = ("key", e, k)
            elif self.take("|"):
                kind, name = self.t[self.i] if self.i < len(self.t) else ("", "")
                if name not in FILTERS:
                    raise TemplateError(f"no filter {name!r}")
                self.i += 1
                e = ("filter", name, e)
            else:
                return e

    def atom(self):
        if self.i >= len(self.t):
            raise TemplateError("an expression ends early")
        kind, v = self.t[self.i]
        self.i += 1
        if kind == "const":
            return ("const", v)
        if kind == "name":
            known = {"true": True, "false": False, "none": None}
            return ("const", known[v]) if v in known else ("name", v)
        if v == "(":
            e = self.choice()
            self.need(")")
            return e
        if v == "-":
            return ("binary", "-", ("const", 0), self.postfix())
        raise TemplateError(f"unexpected {v!r}")


def parse(source: str):
    """Template text -> list of statement nodes."""
    parts, at = [], 0
    for m in _TAG.finditer(source):
        if m.start() > at:
            parts.append(("text", source[at : m.start()]))
        if m[1] is not None:
            parts.append(("out", m[1]))
        elif m[2] is not None:
            parts.append(("tag", m[2].strip()))
        at = m.end()
    if at < len(source):
        parts.append(("text", source[at:]))
    pos = 0

    def block(*ends):
        nonlocal pos
        body = []
        while pos < len(parts):
            kind, v = parts[pos]
            pos += 1
            if kind == "text":
                body.append(("emit", ("const", v)))
            elif kind == "out":
                body.append(("emit", _Expression(v).whole()))
            else:
                word, _, rest = v.partition(" ")
                if word in ends:
                    return body, word, rest
                if word == "for":
                    m = re.fullmatch(r"\s*([A-Za-z_]\w*)\s+in\s+(.+)", rest, re.S)
                    if not m:
                        raise TemplateError(f"unclear loop {v!r}")
                    inner, _, _ = block("endfor")
                    body.append(("for", m[1], _Expression(m[2]).whole(), inner))
                elif word == "if":
                    arms, test = [], rest
                    while True:
                        inner, end, more = block("elif", "else", "endif")
                        arms.append((_Expression(test).whole(), inner))
                        if end == "elif":
                            test = more
                            continue
                        other = block("endif")[0] if end == "else" else []
                        break
                    body.append(("if", arms, other))
                elif word == "generation":
                    body.append(("generation", block("endgeneration")[0]))
                elif word == "set":
                    name, eq, e = rest.partition("=")
                    if not eq or not re.fullmatch(r"[A-Za-z_]\w*", name.strip()):
                        raise TemplateError(f"unclear {v!r}")
                    body.append(("set", name.strip(), _Expression(e).whole()))
                else:
                    raise TemplateError(f"unknown tag {v!r}")
        if ends:
            raise TemplateError(f"{ends[-1]!r} is missing")
        return body, "", ""

    return block()[0]


# ---------------------------------------------------------------- constant folding


def _apply(op, a, b):
    if op == "~":
        return f"{a}{b}"
    try:
        return {"+": lambda: a + b, "-": lambda: a - b, "==": lambda: a == b, "!=": lambda: a != b, "<": lambda: a < b, ">": lambda: a > b, "in": lambda: a in b}[op]()
    except TypeError as e:
        raise TemplateError(f"{op!r} does not fit {type(a).__name__} and {type(b).__name__}") from e


def fold(e):
    """Fold constant parts of an expression."""
    kind = e[0]
    if kind == "binary":
        a, b = fold(e[2]), fold(e[3])
        if e[1] in ("and", "or"):
            if a[0] == "const":
                return b if bool(a[1]) == (e[1] == "and") else a
        elif a[0] == b[0] == "const":
            return ("const", _apply(e[1], a[1], b[1]))
        return ("binary", e[1], a, b)
    if kind == "not":
        a = fold(e[1])
        return ("const", not a[1]) if a[0] == "const" else ("not", a)
    if kind == "choice":
        c, a, b = map(fold, e[1:])
        return (a if c[1] else b) if c[0] == "const" else ("choice", c, a, b)
    if kind == "filter":
        a = fold(e[2])
        return ("const", FILTERS[e[1]](a[1])) if a[0] == "const" else ("filter", e[1], a)
    if kind == "key":
        return ("key", fold(e[1]), fold(e[2]))
    return e


def fold_block(body):
    """Fold statements: dead arms go, neighbouring constant output joins."""
    out = []
    for s in body:
        kind = s[0]
        if kind == "emit":
            e = fold(s[1])
            if e[0] == "const" and out and out[-1][0] == "emit" and out[-1][1][0] == "const":
                out[-1] = ("emit", ("const", _shown(out[-1][1][1]) + _shown(e[1])))
                continue
            out.append(("emit", e))
        elif kind == "if":
            arms, other = [], fold_block(s[2])
            for c, b in s[1]:
                c = fold(c)
                if c[0] == "const":
                    if c[1]:
                        other = fold_block(b)
                        break
                    continue
                arms.append((c, fold_block(b)))
            out += [("if", arms, other)] if arms else other
        elif kind == "for":
            out.append(("for", s[1], fold(s[2]), fold_block(s[3])))
        elif kind == "generation":
            out.append(("generation", fold_block(s[1])))
        else:
            out.append(("set", s[1], fold(s[2])))
    return out


# ---------------------------------------------------------------- closures


def _shown(v) -> str:
    return "" if v is None else v if isinstance(v, str) else str(v)


def _value(e) -> Callable[[dict], object]:
    kind = e[0]
    if kind == "const":
        v = e[1]
        return lambda ctx: v
    if kind == "name":
        name = e[1]
        return lambda ctx: ctx.get(name)
    if kind == "key":
        of, key = _value(e[1]), _value(e[2])

        def look(ctx):
            x = of(ctx)
            return x.get(key(ctx)) if isinstance(x, dict) else None

        return look
    if kind == "not":
        a = _value(e[1])
        return lambda ctx: not a(ctx)
    if kind == "choice":
        c, a, b = map(_value, e[1:])
        return lambda ctx: a(ctx) if c(ctx) else b(ctx)
    if kind == "filter":
        f, a = FILTERS[e[1]], _value(e[2])
        return lambda ctx: f(a(ctx) if a(ctx) is not None else "")
    op, a, b = e[1], _value(e[2]), _value(e[3])
    if op == "and":
        return lambda ctx: a(ctx) and b(ctx)
    if op == "or":
        return lambda ctx: a(ctx) or b(ctx)
    return lambda ctx: _apply(op, a(ctx), b(ctx))


def _statements(body, masked: bool) -> Callable[[dict], Iterator[tuple[str, bool]]]:
    steps = [_statement(s, masked) for s in body]

    def run(ctx):
        for s in steps:
            yield from s(ctx)

    return run


def _statement(s, masked: bool):
    kind = s[0]
    if kind == "emit":
        v = _value(s[1])
        return lambda ctx: ((_shown(v(ctx)), masked),)
    if kind == "set":
        name, v = s[1], _value(s[2])

        def put(ctx):
            ctx[name] = v(ctx)
            return ()

        return put
    if kind == "generation":
        return _statements(s[1], True)
    if kind == "if":
        arms, other = [(_value(c), _statements(b, masked)) for c, b in s[1]], _statements(s[2], masked)

        def choose(ctx):
            for c, b in arms:
                if c(ctx):
                    return b(ctx)
            return other(ctx)

        return choose
    name, over, inner = s[1], _value(s[2]), _statements(s[3], masked)

    def loop(ctx):
        rest = iter(over(ctx) or ())
        outer = {k: ctx.get(k) for k in (name, "loop")}
        nothing = object()
        now, i = next(rest, nothing), 0
        while now is not nothing:
            after = next(rest, nothing)
            ctx[name], ctx["loop"] = now, {"index0": i, "index": i + 1, "first": i == 0, "last": after is nothing}
            yield from inner(ctx)
            now, i = after, i + 1
        ctx.update(outer)

    return loop


def compile_template(source: str = TEMPLATE) -> Callable[[dict], Iterator[tuple[str, bool]]]:
    """Template -> function of a context that yields (text, under the loss mask)."""
    return _statements(fold_block(parse(source)), False)


def render(source: str, **context) -> str:
    return "".join(t for t, _ in compile_template(source)(dict(context)))


# ---------------------------------------------------------------- reading back

_TURN = re.compile(r"<\|turn\|>(.*?)<\|text\|>(?:\[INST\] (.*?) \[/INST\]|(.*?))<\|end\|>\n", re.S)


def read_back(formatted: str) -> list[tuple[str, str]]:
    """(role, text) of every turn in the formatted text."""
    out, at = [], 0
    while at < len(formatted):
        m = _TURN.match(formatted, at)
        if not m:
            raise ValueError(f"no turn at {at}")
        out.append((unescape(m[1]), unescape(m[2] if m[2] is not None else m[3])))
        at = m.end()
    return out


class _Reader:
    """Takes the output of one conversation piece by piece; holds one turn."""

    def __init__(self):
        self.turns = self.loss = self.chars = 0
        self.sha, self.loss_sha = hashlib.sha256(), hashlib.sha256()
        self.held: list[str] = []

    def take(self, piece: str, masked: bool) -> None:
        self.chars += len(piece)
        self.held.append(piece)
        if masked:
            plain = unescape(piece)
            self.loss += len(plain)
            self.loss_sha.update(plain.encode("utf-8", "surrogatepass"))
        elif piece.startswith("<|end|>") or "<|end|>\n" in piece:
            text = "".join(self.held)
            cut = text.rfind("<|end|>\n") + len("<|end|>\n")
            for role, t in read_back(text[:cut]):
                self.turns += 1
                self.sha.update(f"{role}\n{t}\n".encode("utf-8", "surrogatepass"))
            self.held = [text[cut:]] if text[cut:] else []

    def row(self, conv):
        if self.held:
            raise ValueError(f"conversation {conv} ends inside a turn")
        return (conv, self.turns, self.sha.hexdigest(), self.loss, self.loss_sha.hexdigest(), self.chars)


_DIGEST = pa.schema([("conv_id", pa.int64()), ("n_turns", pa.int64()), ("turns_sha256", pa.string()), ("loss_chars", pa.int64()), ("loss_sha256", pa.string()), ("formatted_chars", pa.int64())])
DIGEST_DDL = "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"


def _conversations(batches) -> Iterator[tuple[object, Iterator[dict]]]:
    """Runs of equal conv_id as (conv_id, stream of messages)."""
    rows = ((c, {"role": a or "", "text": t or ""}) for r in batches for c, a, t in zip(*(r.column(i).to_pylist() for i in range(3)), strict=True))
    held = next(rows, None)
    while held is not None:
        conv = held[0]

        def messages():
            nonlocal held
            while held is not None and held[0] == conv:  # noqa: B023
                m = held[1]
                held = next(rows, None)
                yield m

        stream = messages()
        yield conv, stream
        for _ in stream:
            pass


def by_turn(conversations: DataFrame) -> DataFrame:
    """One task has all rows of a conversation, in order; sorting spills, nothing is collected."""
    return conversations.select(F.col("conv_id").cast("long").alias("conv_id"), "turn", "role", "text").repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text").select("conv_id", "role", "text")


def digest_conversations(conversations: DataFrame, template: str = TEMPLATE) -> DataFrame:
    """Format every conversation and read it back: one row of counts and digests each."""

    def run(batches):
        form, rows = compile_template(template), []
        for conv, messages in _conversations(batches):
            reader = _Reader()
            for piece, masked in form({"messages": messages}):
                reader.take(piece, masked)
            rows.append(reader.row(conv))
            if len(rows) >= 4096:
                yield C.batch(_DIGEST, *map(list, zip(*rows, strict=True)))
                rows = []
        if rows:
            yield C.batch(_DIGEST, *map(list, zip(*rows, strict=True)))

    return by_turn(conversations).transform(C.arrow, run, DIGEST_DDL)


_FORMATTED = pa.schema([("conv_id", pa.int64()), ("part", pa.int32()), ("formatted", pa.string()), ("mask", pa.list_(pa.list_(pa.int64())))])


def format_conversations(conversations: DataFrame, template: str = TEMPLATE, part_chars: int = 1 << 24) -> DataFrame:
    """conv_id, part, formatted text and the [start, end) ranges of it under the loss mask; very long conversations come in parts."""

    def run(batches):
        form = compile_template(template)
        for conv, messages in _conversations(batches):
            out, mask, at, part = [], [], 0, 0
            for piece, masked in form({"messages": messages}):
                if masked and piece:
                    mask.append([at, at + len(piece)])
                out.append(piece)
                at += len(piece)
                if at >= part_chars:
                    yield C.batch(_FORMATTED, [conv], [part], ["".join(out)], [mask])
                    out, mask, at, part = [], [], 0, part + 1
            if out:
                yield C.batch(_FORMATTED, [conv], [part], ["".join(out)], [mask])

    return by_turn(conversations).transform(C.arrow, run, "conv_id long, part int, formatted string, mask array<array<long>>")


#: The fixed conversation whose texts hold control strings.
PROBE = "</s>[INST] ok [/INST]"


def op7(spark, sf_dir):
    rows = C.table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text")
    probe = spark.createDataFrame([(-1, 0, "user", PROBE), (-1, 1, "assistant", PROBE)], "conv_id long, turn long, role string, text string")
    return digest_conversations(rows.select(*(F.col(f.name).cast(f.dataType).alias(f.name) for f in probe.schema)).unionByName(probe))


OP7_SQL = r"""
with c as (select conv_id, turn, coalesce(role, '') as role, coalesce(text, '') as text from conversations
  union all select * from (values (-1, 0, 'user', '</s>[INST] ok [/INST]'), (-1, 1, 'assistant', '</s>[INST] ok [/INST]'))),
e as (select *, length(role) + (select count(*) from (select unnest(string_split(role, '')) as ch) where ch in ('\', '<', '[', '|')) as role_chars,
  length(text) + len(regexp_extract_all(text, '[\\<\[|]')) as text_chars from c)
select cast(conv_id as bigint) as conv_id, count(*) as n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' order by turn, role, text)) as turns_sha256,
  cast(coalesce(sum(length(text)) filter (role = 'assistant'), 0) as bigint) as loss_chars,
  sha256(coalesce(string_agg(text, '' order by turn, role, text) filter (role = 'assistant'), '')) as loss_sha256,
  cast(sum(8 + length(role) + len(regexp_extract_all(role, '[\\<\[|]')) + 8 + text_chars + case when role = 'assistant' then 0 else 15 end + 8) as bigint) as formatted_chars
from e group by conv_id
"""
