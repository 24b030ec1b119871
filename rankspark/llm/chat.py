"""Chat formatting: a compiler for a small sandboxed template language.

The language has output `{{ expression }}`, `{% for x in xs %}`, `{% if %}/{% elif %}/{% else %}`, and
`{% generation %}...{% endgeneration %}`, which marks what a model is trained on. Expressions are strings, numbers,
names, `x.field`, comparison, `and`, `or`, `not`, `+`, and filters `| name`. There are no calls, no attributes of
Python objects, no imports: a name is a template variable and a field is a key of a mapping.

`compile_template` parses to a syntax tree, folds constants (constant expressions, branches of constant conditions,
neighbouring literal text) and turns each node into a Python closure. Rendering writes pieces to a sink and walks its
loops lazily, so a conversation of any number of turns streams through in bounded memory, and so does reading it back.

Defined cases of `digests`: null text and null role count as empty; turns come in order of (turn, role, text), nulls
first, and repeated rows all count; a null conv_id is a conversation of its own; an empty table gives no rows; other
columns are ignored; a field that is missing renders as an empty string, an unknown name or filter is an error."""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterable, Iterator
from itertools import groupby

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common


class TemplateError(ValueError):
    pass


# ---- control strings -------------------------------------------------------------------------------------------

START, END = "<|im_start|>", "<|im_end|>"
OPENS, ESCAPED = re.compile(r"<(\\*)\|"), re.compile(r"<\\(\\*)\|")


def escape(text: str) -> str:
    """No `<|` is left: each `<`, backslashes, `|` gets one more backslash."""
    return OPENS.sub(r"<\1\\|", text) if "<" in text else text


def unescape(text: str) -> str:
    return ESCAPED.sub(r"<\1|", text) if "<\\" in text else text


def escape_line(text: str) -> str:
    return escape(text.replace("&", "&amp;").replace("\n", "&nl;"))


def unescape_line(text: str) -> str:
    return unescape(text).replace("&nl;", "\n").replace("&amp;", "&")


FILTERS: dict[str, Callable[[object], object]] = {"escape": lambda v: escape(_text(v)), "line": lambda v: escape_line(_text(v)), "trim": lambda v: _text(v).strip(), "upper": lambda v: _text(v).upper(), "lower": lambda v: _text(v).lower(), "length": lambda v: len(v)}  # type: ignore[arg-type]


def _text(value: object) -> str:
    return "" if value is None else str(value)


# ---- from text to tree -----------------------------------------------------------------------------------------

TAGS = re.compile(r"(\{\{-?.*?-?\}\}|\{%-?.*?-?%\})", re.S)
TOKEN = re.compile(r"""\s*(?:(?P<text>'(?:[^'\\]|\\.)*'|"(?:[^"\\]|\\.)*")|(?P<number>\d+)|(?P<name>[A-Za-z_]\w*)|(?P<mark>==|!=|<=|>=|[<>+|.()]))""")
ESCAPES = {"n": "\n", "t": "\t", "\\": "\\", "'": "'", '"': '"'}


class Expression:
    """Recursive descent over one expression; each level returns a tuple (kind, ...)."""

    def __init__(self, source: str):
        self.items, at, source = [], 0, source.rstrip()
        while at < len(source):
            if not (m := TOKEN.match(source, at)):
                raise TemplateError(f"cannot read {source[at:]!r}")
            self.items.append((m.lastgroup, m[m.lastgroup or 0]))
            at = m.end()
        self.at = 0

    def tree(self) -> tuple:
        node = self.either()
        if self.at < len(self.items):
            raise TemplateError(f"unexpected {self.items[self.at][1]!r}")
        return node

    def take(self, *wanted: str) -> str | None:
        if self.at < len(self.items) and self.items[self.at][0] != "text" and self.items[self.at][1] in wanted:
            self.at += 1
            return self.items[self.at - 1][1]
        return None

    def either(self) -> tuple:
        node = self.both()
        while self.take("or"):
            node = ("or", node, self.both())
        return node

    def both(self) -> tuple:
        node = self.inverse()
        while self.take("and"):
            node = ("and", node, self.inverse())
        return node

    def inverse(self) -> tuple:
        return ("not", self.inverse()) if self.take("not") else self.compared()

    def compared(self) -> tuple:
        node = self.summed()
        while op := self.take("==", "!=", "<", ">", "<=", ">="):
            node = (op, node, self.summed())
        return node

    def summed(self) -> tuple:
        node = self.filtered()
        while self.take("+"):
            node = ("+", node, self.filtered())
        return node

    def filtered(self) -> tuple:
        node = self.single()
        while self.take("|"):
            node = ("filter", self.word(), node)
            if node[1] not in FILTERS:
                raise TemplateError(f"no filter {node[1]!r}")
        return node

    def word(self) -> str:
        if self.at < len(self.items) and self.items[self.at][0] == "name":
            self.at += 1
            return self.items[self.at - 1][1]
        raise TemplateError("a name is missing")

    def single(self) -> tuple:
        if self.take("("):
            node = self.either()
            if not self.take(")"):
                raise TemplateError("a ) is missing")
            return node
        if self.at >= len(self.items):
            raise TemplateError("an expression ends early")
        kind, value = self.items[self.at]
        self.at += 1
        if kind == "text":
            return ("constant", re.sub(r"\\(.)", lambda m: ESCAPES.get(m[1], m[0]), value[1:-1], flags=re.S))
        if kind == "number":
            return ("constant", int(value))
        if kind != "name":
            raise TemplateError(f"unexpected {value!r}")
        node: tuple = ("constant", value == "true") if value in ("true", "false") else ("name", value)
        while self.take("."):
            node = ("field", self.word(), node)
        return node


def parse(source: str) -> tuple:
    """("block", nodes) of the whole template."""
    pieces, strip = [], False
    for k, piece in enumerate(TAGS.split(source)):
        if k % 2 == 0:
            pieces.append(("text", piece.lstrip() if strip else piece))
            continue
        if piece[2] == "-" and pieces:
            pieces[-1] = ("text", pieces[-1][1].rstrip())
        strip = piece[-3] == "-"
        pieces.append(("out" if piece[1] == "{" else "tag", piece[2:-2].strip("-").strip()))
    node, at, end = _block(pieces, 0, ())
    return node


def _block(pieces: list, at: int, ends: tuple[str, ...]) -> tuple[tuple, int, str]:
    nodes: list[tuple] = []
    while at < len(pieces):
        kind, body = pieces[at]
        at += 1
        if kind == "text":
            nodes.append(("emit", ("constant", body)))
            continue
        if kind == "out":
            nodes.append(("emit", Expression(body).tree()))
            continue
        word, _, rest = body.partition(" ")
        if word in ends:
            return ("block", nodes), at, body
        if word == "for":
            if not (m := re.fullmatch(r"([A-Za-z_]\w*)\s+in\s+(.+)", rest.strip(), re.S)):
                raise TemplateError(f"cannot read {body!r}")
            inner, at, _ = _block(pieces, at, ("endfor",))
            nodes.append(("for", m[1], Expression(m[2]).tree(), inner))
        elif word == "generation":
            inner, at, _ = _block(pieces, at, ("endgeneration",))
            nodes.append(("generation", inner))
        elif word == "if":
            arms, test, end = [], Expression(rest).tree(), ""
            while end != "endif":
                inner, at, end = _block(pieces, at, ("elif", "else", "endif"))
                arms.append((test, inner))
                test = Expression(end[4:]).tree() if end.startswith("elif") else ("constant", True)
            nodes.append(("if", arms))
        else:
            raise TemplateError(f"no tag {word!r}")
    if ends:
        raise TemplateError(f"{ends[-1]} is missing")
    return ("block", nodes), at, ""


# ---- folding ---------------------------------------------------------------------------------------------------

BINARY: dict[str, Callable] = {"==": lambda a, b: a == b, "!=": lambda a, b: a != b, "<": lambda a, b: a < b, ">": lambda a, b: a > b, "<=": lambda a, b: a <= b, ">=": lambda a, b: a >= b, "+": lambda a, b: a + b if isinstance(a, int) and isinstance(b, int) else _text(a) + _text(b)}


def fold(node: tuple) -> tuple:
    """The same tree with everything that is known beforehand worked out."""
    kind = node[0]
    if kind == "block":
        nodes: list[tuple] = []
        for n in map(fold, node[1]):
            for x in n[1] if n[0] == "block" else [n]:
                if x[0] == "emit" and x[1][0] == "constant":
                    text = _text(x[1][1])
                    if nodes and nodes[-1][0] == "emit" and nodes[-1][1][0] == "constant":
                        text = _text(nodes.pop()[1][1]) + text
                    if not text:
                        continue
                    x = ("emit", ("constant", text))
                nodes.append(x)
        return ("block", nodes)
    if kind == "emit":
        return ("emit", fold(node[1]))
    if kind == "for":
        return ("for", node[1], fold(node[2]), fold(node[3]))
    if kind == "generation":
        return ("generation", fold(node[1]))
    if kind == "if":
        arms = []
        for test, inner in ((fold(t), fold(b)) for t, b in node[1]):
            if test[0] == "constant" and not test[1]:
                continue
            arms.append((test, inner))
            if test[0] == "constant":
                break
        if not arms or arms[0][0][0] == "constant":
            return arms[0][1] if arms else ("block", [])
        return ("if", arms)
    if kind in ("constant", "name"):
        return node
    if kind in ("filter", "field"):
        inner = fold(node[2])
        return ("constant", FILTERS[node[1]](inner[1])) if kind == "filter" and inner[0] == "constant" else (kind, node[1], inner)
    parts = [fold(n) for n in node[1:]]
    if kind == "not":
        return ("constant", not parts[0][1]) if parts[0][0] == "constant" else ("not", parts[0])
    a, b = parts
    if kind in ("and", "or"):
        if a[0] == "constant":
            return b if bool(a[1]) == (kind == "and") else a
        return (kind, a, b)
    return ("constant", BINARY[kind](a[1], b[1])) if a[0] == b[0] == "constant" else (kind, a, b)


# ---- closures --------------------------------------------------------------------------------------------------

Sink = Callable[[str, bool], None]  # a piece of output; whether it is under the generation mark


def _value(node: tuple) -> Callable[[dict], object]:
    kind = node[0]
    if kind == "constant":
        return lambda scope, v=node[1]: v
    if kind == "name":

        def name(scope, key=node[1]):
            if key not in scope:
                raise TemplateError(f"no variable {key!r}")
            return scope[key]

        return name
    if kind == "field":

        def field(scope, key=node[1], of=_value(node[2])):
            v = of(scope)
            return v.get(key) if isinstance(v, dict) else None

        return field
    if kind == "filter":
        return lambda scope, f=FILTERS[node[1]], of=_value(node[2]): f(of(scope))
    if kind == "not":
        return lambda scope, of=_value(node[1]): not of(scope)
    left, right = _value(node[1]), _value(node[2])
    if kind == "and":
        return lambda scope: left(scope) and right(scope)
    if kind == "or":
        return lambda scope: left(scope) or right(scope)
    return lambda scope, f=BINARY[kind]: f(left(scope), right(scope))


def _action(node: tuple) -> Callable[[dict, Sink, bool], None]:
    kind = node[0]
    if kind == "block":
        steps = [_action(n) for n in node[1]]

        def block(scope, sink, marked):
            for step in steps:
                step(scope, sink, marked)

        return block
    if kind == "emit":
        return lambda scope, sink, marked, of=_value(node[1]): sink(_text(of(scope)), marked)
    if kind == "generation":
        return lambda scope, sink, marked, inner=_action(node[1]): inner(scope, sink, True)
    if kind == "for":

        def loop(scope, sink, marked, key=node[1], over=_value(node[2]), inner=_action(node[3])):
            own = dict(scope)
            for item in over(scope) or ():
                own[key] = item
                inner(own, sink, marked)

        return loop
    arms = [(_value(t), _action(b)) for t, b in node[1]]

    def choose(scope, sink, marked):
        for test, inner in arms:
            if test(scope):
                inner(scope, sink, marked)
                return

    return choose


def compile_template(source: str) -> Callable[[dict, Sink], None]:
    run = _action(fold(parse(source)))
    return lambda scope, sink: run(scope, sink, False)


#: Each turn is one marked block; the text of an assistant is what is learned.
TEMPLATE = """{% for m in messages %}{{ '<|im_' + 'start|>' }}{{ m.role | line }}
{% if m.role == 'assistant' %}{% generation %}{{ m.text | escape }}{% endgeneration %}{% else %}{{ m.text | escape }}{% endif %}<|im_end|>
{% endfor %}"""


class Reader:
    """Reads formatted output back, a piece at a time; holds one turn at most."""

    def __init__(self):
        self.rest = ""

    def feed(self, piece: str) -> Iterator[tuple[str, str]]:
        self.rest += piece
        while (stop := self.rest.find(END + "\n")) >= 0:
            if not self.rest.startswith(START):
                raise ValueError("a turn does not begin with its mark")
            role, _, text = self.rest[len(START) : stop].partition("\n")
            yield unescape_line(role), unescape(text)
            self.rest = self.rest[stop + len(END) + 1 :]


def render(messages: Iterable[dict], template: str = TEMPLATE) -> tuple[str, list[tuple[int, int]]]:
    """The whole output and the spans under the generation mark, for texts that fit in memory."""
    pieces, spans, at = [], [], 0

    def sink(piece: str, marked: bool) -> None:
        nonlocal at
        pieces.append(piece)
        at += len(piece)
        if marked:
            spans.append((at - len(piece), at))

    compile_template(template)({"messages": messages}, sink)
    return "".join(pieces), spans


def digest(messages: Iterator[dict], run: Callable[[dict, Sink], None]) -> tuple[int, str, int, str, int]:
    """Format, read the output back, and digest what was read."""
    reader, turns, loss = Reader(), hashlib.sha256(), hashlib.sha256()
    n = learned = size = 0

    def sink(piece: str, marked: bool) -> None:
        nonlocal n, learned, size
        size += len(piece)
        if marked:
            plain = unescape(piece)
            learned += len(plain)
            loss.update(plain.encode("utf-8", "surrogatepass"))
        for role, text in reader.feed(piece):
            n += 1
            turns.update(f"{role}\n{text}\n".encode("utf-8", "surrogatepass"))

    run({"messages": messages}, sink)
    if reader.rest:
        raise ValueError("the output does not end with a whole turn")
    return n, turns.hexdigest(), learned, loss.hexdigest(), size


def digests(conversations: DataFrame, template: str = TEMPLATE) -> DataFrame:
    """One row per conversation. Rows are dealt by conv_id and sorted in their task, then stream through the renderer:
    a task holds one turn at a time, whatever the length of a conversation. (A digest of a whole conversation is a
    chain over its turns, so one conversation is read by one task.)"""

    def run(batches):
        format_all = compile_template(template)

        def rows():
            for b in common.slices(batches):
                yield from zip(*(c.to_pylist() for c in b.columns), strict=True)

        out: list[tuple] = []
        for key, group in groupby(rows(), key=lambda r: r[0]):
            messages = ({"role": role or "", "text": text or ""} for _, role, text in group)
            out.append((key, *digest(messages, format_all)))
            if len(out) == 1000:
                yield _batch(out)
                out = []
        if out:
            yield _batch(out)

    rows = conversations.select(F.col("conv_id").cast("long").alias("conv_id"), "turn", "role", "text")
    rows = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    return common.mapped(rows.select("conv_id", "role", "text"), run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
    names = ("conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars")
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)], list(names))
