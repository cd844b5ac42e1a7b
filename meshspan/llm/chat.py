"""Chat formatting: a template compiler.

A template is parsed to a syntax tree, constants are folded (literal arithmetic, conditions that
are known, neighbouring texts), and the tree becomes Python closures. The language is sandboxed: it
has literals, names, fields of conversation records, comparisons, conditions, loops and a fixed set of
filters, and neither calls nor Python attributes.

    {{ expression }}   {% if e %}..{% elif e %}..{% else %}..{% endif %}   {% set name = e %}
    {% for name in e %}..{% endfor %} (with loop.first, loop.last, loop.index)
    {% generation %}..{% endgeneration %}   marks what a model is trained to say
    {# comment #}      a dash inside a tag's mark trims white space on that side

Rendering gives the text and the spans of the generation marks. The ``guard`` filter writes
control strings inside texts reversibly: a backslash doubles, and the k-th control string becomes a
backslash and the digit k, so that no text can end its turn or open another.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshspan.llm.common import shuffle_partitions

# Control strings of public chat formats, in the order of their digits.
CONTROLS = ("<|im_start|>", "<|im_end|>", "<s>", "</s>", "[INST]", "[/INST]", "<<SYS>>", "<</SYS>>", "<|endoftext|>")

CHAT_TEMPLATE = """{% for m in messages %}<|im_start|>{{ m.role | guard_line }}
{% if m.role == 'assistant' %}{% generation %}{{ m.text | guard }}{% endgeneration %}{% else %}{{ m.text | guard }}{% endif %}<|im_end|>
{% endfor %}{% if add_prompt %}<|im_start|>assistant
{% endif %}"""

_CONTROL = re.compile("|".join(re.escape(c) for c in CONTROLS))


def guard(text: str) -> str:
    return _CONTROL.sub(lambda m: f"\\{CONTROLS.index(m[0])}", text.replace("\\", "\\\\"))


def unguard(text: str) -> str:
    return re.sub(r"\\([\\n0-9])", lambda m: {"\\": "\\", "n": "\n"}.get(m[1]) or CONTROLS[int(m[1])], text)


FILTERS: dict[str, Callable] = {
    "guard": lambda v: guard(str(v)),
    "guard_line": lambda v: guard(str(v)).replace("\n", "\\n"),
    "trim": lambda v: str(v).strip(),
    "upper": lambda v: str(v).upper(),
    "lower": lambda v: str(v).lower(),
    "length": len,
}


class TemplateError(ValueError):
    """The template does not parse, or asks for something the sandbox does not have."""


# ---------------------------------------------------------------- syntax tree: tuples (kind, ...)

_MARK = re.compile(r"\{\{-?|\{%-?|\{#")
_LEXEME = re.compile(r"\s*(?:(\d+)|('(?:[^'\\]|\\.)*'|\"(?:[^\"\\]|\\.)*\")|([A-Za-z_]\w*)|(==|!=|<=|>=|[<>+~|.\[\]()-]|=))")
_ESCAPES = {"n": "\n", "t": "\t", "r": "\r"}


def _pieces(source: str) -> list[tuple[str, str]]:
    """(kind, body) with kind text, print or tag; white space control is applied."""
    out, at, trim = [], 0, False
    while True:
        mark = _MARK.search(source, at)
        text = source[at : mark.start()] if mark else source[at:]
        if trim:
            text = text.lstrip()
        if mark and mark[0].endswith("-"):
            text = text.rstrip()
        if text:
            out.append(("text", text))
        if not mark:
            return out
        close = {"{{": "}}", "{%": "%}", "{#": "#}"}[mark[0][:2]]
        end, quote, i = -1, "", mark.end()
        while i < len(source):  # the closing mark outside string literals
            if quote:
                if source[i] == "\\":
                    i += 1
                elif source[i] == quote:
                    quote = ""
            elif source[i] in "'\"" and close != "#}":
                quote = source[i]
            elif source.startswith(close, i):
                end = i
                break
            i += 1
        if end < 0:
            raise TemplateError(f"{mark[0]} is not closed")
        body = source[mark.end() : end]
        trim = body.endswith("-")
        if close != "#}":
            out.append(("print" if close == "}}" else "tag", body[:-1] if trim else body))
        at = end + 2


class _Expression:
    """Recursive descent over the lexemes of one expression."""

    def __init__(self, body: str):
        self.tokens: list[tuple[str, str]] = []
        at = 0
        while body[at:].strip():
            m = _LEXEME.match(body, at)
            if not m:
                raise TemplateError(f"unexpected {body[at:].strip()[:12]!r}")
            kind = ("number", "string", "name", "sign")[m.lastindex - 1]
            self.tokens.append((kind, m[m.lastindex]))
            at = m.end()
        self.at = 0

    def peek(self, *values: str) -> bool:
        return self.at < len(self.tokens) and self.tokens[self.at][0] in ("name", "sign") and self.tokens[self.at][1] in values

    def take(self, *values: str) -> bool:
        found = self.peek(*values)
        self.at += found
        return found

    def name(self) -> str:
        if self.at < len(self.tokens) and self.tokens[self.at][0] == "name":
            self.at += 1
            return self.tokens[self.at - 1][1]
        raise TemplateError("a name is missing")

    def need(self, value: str) -> None:
        if not self.take(value):
            raise TemplateError(f"{value!r} is missing")

    def done(self, node: tuple) -> tuple:
        if self.at != len(self.tokens):
            raise TemplateError(f"unexpected {self.tokens[self.at][1]!r}")
        return node

    def choice(self) -> tuple:
        node = self.either()
        if self.take("if"):
            test = self.either()
            self.need("else")
            return ("choose", test, node, self.choice())
        return node

    def either(self) -> tuple:
        node = self.both()
        while self.take("or"):
            node = ("or", node, self.both())
        return node

    def both(self) -> tuple:
        node = self.negated()
        while self.take("and"):
            node = ("and", node, self.negated())
        return node

    def negated(self) -> tuple:
        return ("not", self.negated()) if self.take("not") else self.compared()

    def compared(self) -> tuple:
        node = self.told()
        for sign in ("==", "!=", "<=", ">=", "<", ">", "in"):
            if self.take(sign):
                return ("compare", sign, node, self.told())
        return node

    def told(self) -> tuple:
        node = self.joined()
        while self.take("~"):
            node = ("join", "~", node, self.joined())
        return node

    def joined(self) -> tuple:
        node = self.filtered()
        while self.peek("+", "-"):
            sign = self.tokens[self.at][1]
            self.at += 1
            node = ("join", sign, node, self.filtered())
        return node

    def filtered(self) -> tuple:
        node = self.field()
        while self.take("|"):
            name = self.name()
            if name not in FILTERS:
                raise TemplateError(f"no filter {name!r}")
            node = ("filter", name, node)
        return node

    def field(self) -> tuple:
        node = self.atom()
        while True:
            if self.take("."):
                node = ("field", node, ("value", self.name()))
            elif self.take("["):
                node = ("field", node, self.choice())
                self.need("]")
            else:
                return node

    def atom(self) -> tuple:
        if self.take("("):
            node = self.choice()
            self.need(")")
            return node
        if self.at >= len(self.tokens):
            raise TemplateError("an expression ends early")
        kind, text = self.tokens[self.at]
        self.at += 1
        if kind == "number":
            return ("value", int(text))
        if kind == "string":
            return ("value", re.sub(r"\\(.)", lambda m: _ESCAPES.get(m[1], m[1]), text[1:-1], flags=re.S))
        if kind == "name":
            fixed = {"true": True, "false": False, "none": None}
            return ("value", fixed[text.lower()]) if text.lower() in fixed else ("name", text)
        raise TemplateError(f"unexpected {text!r}")


def parse(source: str) -> tuple:
    """Syntax tree of a template."""
    pieces = _pieces(source)
    at = 0

    def body(ends: tuple[str, ...]) -> tuple[tuple, str, str]:
        nonlocal at
        nodes = []
        while at < len(pieces):
            kind, text = pieces[at]
            at += 1
            if kind == "text":
                nodes.append(("text", text))
            elif kind == "print":
                e = _Expression(text)
                nodes.append(("print", e.done(e.choice())))
            else:
                word, _, rest = text.strip().partition(" ")
                if word in ends:
                    return ("all", nodes), word, rest
                nodes.append(statement(word, rest))
        if ends:
            raise TemplateError(f"{ends[-1]} is missing")
        return ("all", nodes), "", ""

    def statement(word: str, rest: str) -> tuple:
        if word == "if":
            e = _Expression(rest)
            test = e.done(e.choice())
            then, end, more = body(("elif", "else", "endif"))
            if end == "elif":
                return ("when", test, then, ("all", [statement("if", more)]))
            other = body(("endif",))[0] if end == "else" else ("all", [])
            return ("when", test, then, other)
        if word == "for":
            e = _Expression(rest)
            name = e.name()
            e.need("in")
            return ("each", name, e.done(e.choice()), body(("endfor",))[0])
        if word == "set":
            e = _Expression(rest)
            name = e.name()
            e.need("=")
            return ("set", name, e.done(e.choice()))
        if word == "generation":
            return ("generation", body(("endgeneration",))[0])
        raise TemplateError(f"no tag {word!r}")

    return body(())[0]


def _truth(value) -> bool:
    return bool(value)


def _said(value) -> str:
    return "" if value is None else {True: "true", False: "false"}.get(value, str(value)) if isinstance(value, bool) else str(value)


_COMPARE: dict[str, Callable] = {
    "==": lambda a, b: a == b, "!=": lambda a, b: a != b, "<": lambda a, b: a < b, ">": lambda a, b: a > b,
    "<=": lambda a, b: a <= b, ">=": lambda a, b: a >= b, "in": lambda a, b: a in b,
}
_JOIN: dict[str, Callable] = {"+": lambda a, b: a + b, "-": lambda a, b: a - b, "~": lambda a, b: _said(a) + _said(b)}


def fold(node: tuple) -> tuple:
    """The same tree with known parts computed."""
    kind, *rest = node
    if kind == "all":
        out: list[tuple] = []
        for child in map(fold, rest[0]):
            for part in child[1] if child[0] == "all" else [child]:
                if part[0] == "text" and out and out[-1][0] == "text":
                    out[-1] = ("text", out[-1][1] + part[1])
                elif part != ("text", ""):
                    out.append(part)
        return ("all", out)
    if kind in ("text", "value", "name"):
        return node
    if kind == "print":
        inner = fold(rest[0])
        return ("text", _said(inner[1])) if inner[0] == "value" else ("print", inner)
    node = (kind, *(fold(x) if isinstance(x, tuple) else x for x in rest))
    values = [x for x in node[1:] if isinstance(x, tuple)]
    known = [x[1] for x in values if x[0] == "value"]
    if kind == "when" and node[1][0] == "value":
        return node[2] if _truth(node[1][1]) else node[3]
    if kind == "choose" and node[1][0] == "value":
        return node[2] if _truth(node[1][1]) else node[3]
    if kind in ("and", "or") and node[1][0] == "value":
        return node[2] if _truth(node[1][1]) == (kind == "and") else node[1]
    if kind in ("not", "compare", "join", "filter") and len(known) == len(values):
        try:
            return ("value", compile_expression(node)({}))
        except TypeError:  # a sum of unlike things fails when it is rendered, if ever
            return node
    return node


def compile_expression(node: tuple) -> Callable[[dict], object]:
    kind = node[0]
    if kind == "value":
        value = node[1]
        return lambda scope: value
    if kind == "name":
        name = node[1]
        return lambda scope: scope.get(name)
    if kind == "field":
        owner, key = compile_expression(node[1]), compile_expression(node[2])

        def field(scope):
            of, at = owner(scope), key(scope)
            if isinstance(of, dict):
                return of.get(at)
            if isinstance(of, (list, tuple, str)) and isinstance(at, int) and not isinstance(at, bool):
                return of[at] if -len(of) <= at < len(of) else None
            return None

        return field
    if kind == "filter":
        apply, inner = FILTERS[node[1]], compile_expression(node[2])
        return lambda scope: apply("" if (v := inner(scope)) is None else v)
    if kind == "not":
        inner = compile_expression(node[1])
        return lambda scope: not inner(scope)
    if kind == "choose":
        test, yes, no = map(compile_expression, node[1:])
        return lambda scope: yes(scope) if test(scope) else no(scope)
    if kind in ("compare", "join"):
        apply, a, b = (_COMPARE if kind == "compare" else _JOIN)[node[1]], compile_expression(node[2]), compile_expression(node[3])
        return lambda scope: apply(a(scope), b(scope))
    a, b = compile_expression(node[1]), compile_expression(node[2])
    return (lambda scope: a(scope) and b(scope)) if kind == "and" else (lambda scope: a(scope) or b(scope))


class _Page:
    """What has been written: parts, length in code points, and generation spans."""

    def __init__(self):
        self.parts: list[str] = []
        self.length = 0
        self.spans: list[tuple[int, int]] = []

    def write(self, text: str) -> None:
        self.parts.append(text)
        self.length += len(text)


def compile_body(node: tuple) -> Callable[[dict, _Page], None]:
    kind = node[0]
    if kind == "all":
        parts = [compile_body(x) for x in node[1]]

        def every(scope, page):
            for part in parts:
                part(scope, page)

        return every
    if kind == "text":
        text = node[1]
        return lambda scope, page: page.write(text)
    if kind == "print":
        inner = compile_expression(node[1])
        return lambda scope, page: page.write(_said(inner(scope)))
    if kind == "when":
        test, yes, no = compile_expression(node[1]), compile_body(node[2]), compile_body(node[3])
        return lambda scope, page: yes(scope, page) if test(scope) else no(scope, page)
    if kind == "set":
        name, inner = node[1], compile_expression(node[2])
        return lambda scope, page: scope.__setitem__(name, inner(scope))
    if kind == "generation":
        inside = compile_body(node[1])

        def marked(scope, page):
            start = page.length
            inside(scope, page)
            page.spans.append((start, page.length))

        return marked
    name, items, inside = node[1], compile_expression(node[2]), compile_body(node[3])

    def each(scope, page):
        rows = list(items(scope) or [])
        for i, row in enumerate(rows):
            inside(scope | {name: row, "loop": {"first": i == 0, "last": i == len(rows) - 1, "index": i + 1}}, page)

    return each


def compiled(source: str) -> Callable[..., tuple[str, list[tuple[int, int]]]]:
    """Renderer of a template: called with names, gives the text and the generation spans."""
    run = compile_body(fold(parse(source)))

    def render(**scope):
        page = _Page()
        run(scope, page)
        return "".join(page.parts), page.spans

    return render


# ---------------------------------------------------------------- conversations

_TURN = re.compile(r"<\|im_start\|>([^\n]*)\n(.*?)<\|im_end\|>\n", re.S)


def turns_of(formatted: str) -> list[tuple[str, str]]:
    """Roles and texts read back from the output of :data:`CHAT_TEMPLATE`."""
    return [(unguard(role), unguard(text)) for role, text in _TURN.findall(formatted)]


_ROWS = pa.schema([("conv_id", pa.int64()), ("formatted", pa.string()), ("starts", pa.list_(pa.int64())), ("ends", pa.list_(pa.int64()))])


def formatted_conversations(rows: DataFrame, template: str = CHAT_TEMPLATE, add_prompt: bool = False) -> DataFrame:
    """One row per conversation of ``rows(conv_id, turn, role, text)``: conv_id, formatted, and the
    generation spans as starts and ends in code points.

    Turns go by turn, then role, then text, nulls first; null roles and texts are empty; repeated rows
    are turns of their own; rows of a null conv_id form one conversation; an empty table gives no rows.
    Rows reach a task sorted, so that it holds one conversation at a time.
    """
    compiled(template)  # errors show on the driver

    def run(batches):
        render = compiled(template)
        out = {n: [] for n in _ROWS.names}
        state = {"id": None, "turns": []}

        def close():
            text, spans = render(messages=state["turns"], add_prompt=add_prompt)
            for name, value in zip(out, (state["id"], text, [s[0] for s in spans], [s[1] for s in spans]), strict=True):
                out[name].append(value)
            state["turns"] = []

        for batch in batches:
            for conv, role, text in zip(*(batch.column(c).to_pylist() for c in ("conv_id", "role", "text")), strict=True):
                if state["turns"] and conv != state["id"]:
                    close()
                state["id"] = conv
                state["turns"].append({"role": role or "", "text": text or ""})
            if len(out["conv_id"]) > 1000:
                yield pa.RecordBatch.from_pydict(out, schema=_ROWS)
                out = {n: [] for n in _ROWS.names}
        if state["turns"]:
            close()
        yield pa.RecordBatch.from_pydict(out, schema=_ROWS)

    ordered = (
        rows.select(F.col("conv_id").cast("long").alias("conv_id"), F.col("turn").cast("long").alias("turn"), "role", "text")
        .repartition(shuffle_partitions(rows.sparkSession), "conv_id")
        .sortWithinPartitions("conv_id", "turn", "role", "text")
    )
    return ordered.mapInArrow(run, "conv_id long, formatted string, starts array<long>, ends array<long>")


def digests(formatted: DataFrame) -> DataFrame:
    """Counts and digests of conversations, all read back from the formatted text and its spans."""
    names = ("conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars")
    types = pa.schema(list(zip(names, (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64()), strict=True)))

    def digest(parts: list[str]) -> str:
        return hashlib.sha256("".join(parts).encode("utf-8", "surrogatepass")).hexdigest()

    def run(batches):
        for batch in batches:
            out = {n: [] for n in names}
            for conv, text, starts, ends in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                turns = turns_of(text)
                loss = [unguard(text[s:e]) for s, e in zip(starts, ends, strict=True)]
                values = (conv, len(turns), digest([x for role, said in turns for x in (role, "\n", said, "\n")]), sum(map(len, loss)), digest(loss), len(text))
                for name, value in zip(names, values, strict=True):
                    out[name].append(value)
            yield pa.RecordBatch.from_pydict(out, schema=types)

    return formatted.mapInArrow(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")
