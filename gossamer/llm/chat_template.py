"""Chat formatting by compiled templates.

A template is parsed into a syntax tree, constants are folded, and every node becomes a Python closure
that yields pieces of text and marks where generation begins and ends. The language is sandboxed: it
has literals, names, item access, arithmetic, comparison, logic, the filters and tests registered here,
``for``, ``if``, ``set`` and ``generation`` blocks; it has no calls, no Python attributes, no imports.

Rendering is lazy. A conversation's rows are pulled one by one from a sorted partition and finished text
leaves in segments, so a conversation of any length takes bounded memory.

Control strings inside texts are escaped with backslashes, and reading back undoes it exactly.

Cases: null text and null role are empty strings; rows come by turn, ties by role, then text; repeated
rows stay; null conv_ids form one conversation; an empty table gives no rows; other columns are not read.
"""

from __future__ import annotations

import hashlib
import itertools
import operator
import re
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SEGMENT_CHARS = 1 << 16

TEMPLATE = """\
{%- for message in messages -%}
### {{ message.role | label }}: {% if message.role == "assistant" %}{% generation %}{{ message.text | control }}{% endgeneration %}{% else %}{{ message.text | control }}{% endif %}</turn>
{% endfor -%}
"""


class TemplateError(ValueError):
    pass


# --- control strings ------------------------------------------------------------------------------------

_CONTROL = re.compile(r"\\|###|</turn>")
_LABEL = re.compile(r"\\|###|</turn>|:")
_ESCAPED = re.compile(r"\\(.)", re.DOTALL)
_TURN = re.compile(r"### ((?:[^\\:]|\\.)*+): ((?:[^\\<]++|\\.|<(?!/turn>))*+)</turn>\n", re.DOTALL)


def control(text: str) -> str:
    return _CONTROL.sub(lambda m: "\\" + m[0], text)


def label(text: str) -> str:
    return _LABEL.sub(lambda m: "\\" + m[0], text)


def unescaped(text: str) -> str:
    return _ESCAPED.sub(r"\1", text) if "\\" in text else text


FILTERS: dict[str, Callable] = {
    "control": control,
    "label": label,
    "trim": lambda s: s.strip(),
    "upper": lambda s: s.upper(),
    "lower": lambda s: s.lower(),
    "length": len,
    "string": str,
    "default": lambda v, other="": other if v is None else v,
    "replace": lambda s, a, b: s.replace(a, b),
    "join": lambda many, by="": by.join(map(str, many)),
    "first": lambda many: next(iter(many), None),
}
TESTS: dict[str, Callable] = {
    "defined": lambda v: v is not None,
    "none": lambda v: v is None,
    "string": lambda v: isinstance(v, str),
    "odd": lambda v: v % 2 == 1,
    "even": lambda v: v % 2 == 0,
}
_OPERATORS = {"+": operator.add, "-": operator.sub, "*": operator.mul, "/": operator.truediv, "//": operator.floordiv, "%": operator.mod, "==": operator.eq, "!=": operator.ne, "<": operator.lt, "<=": operator.le, ">": operator.gt, ">=": operator.ge, "in": lambda a, b: a in b, "not in": lambda a, b: a not in b, "~": lambda a, b: str(a) + str(b)}
_BINDING = [{"==", "!=", "<", "<=", ">", ">=", "in", "not in"}, {"~"}, {"+", "-"}, {"*", "/", "//", "%"}]


# --- syntax tree ------------------------------------------------------------------------------------------


@dataclass(frozen=True)
class Const:
    value: object


@dataclass(frozen=True)
class Name:
    name: str


@dataclass(frozen=True)
class Item:
    of: object
    key: object


@dataclass(frozen=True)
class Binary:
    op: str
    left: object
    right: object


@dataclass(frozen=True)
class Logic:
    op: str
    parts: tuple


@dataclass(frozen=True)
class Filter:
    name: str
    of: object
    args: tuple


@dataclass(frozen=True)
class Test:
    name: str
    of: object
    negated: bool


@dataclass(frozen=True)
class Choose:
    condition: object
    then: object
    other: object


@dataclass(frozen=True)
class ListOf:
    items: tuple


@dataclass(frozen=True)
class Text:
    text: str


@dataclass(frozen=True)
class Put:
    value: object


@dataclass(frozen=True)
class For:
    name: str
    of: object
    body: tuple


@dataclass(frozen=True)
class If:
    branches: tuple  # (condition, body); a condition of Const(True) is the else branch


@dataclass(frozen=True)
class Set:
    name: str
    value: object


@dataclass(frozen=True)
class Generation:
    body: tuple


_TAGS = re.compile(r"(\{\{-?|\{%-?|\{#)(.*?)(-?\}\}|-?%\}|#\})", re.DOTALL)
_TOKENS = re.compile(r"""\s*(?:(?P<num>\d+\.\d+|\d+)|(?P<str>"(?:[^"\\]|\\.)*"|'(?:[^'\\]|\\.)*')|(?P<name>[A-Za-z_]\w*)|(?P<op>==|!=|<=|>=|//|[-+*/%~<>()\[\].,|=]))""", re.DOTALL)
_STRING_ESCAPES = {"n": "\n", "t": "\t", "r": "\r"}


class _Expression:
    def __init__(self, source: str):
        self.tokens, at = [], 0
        source = source.rstrip()
        while at < len(source):
            m = _TOKENS.match(source, at)
            if not m:
                raise TemplateError(f"cannot read {source[at:]!r}")
            self.tokens.append((m.lastgroup, m[m.lastgroup]))
            at = m.end()
        self.at = 0

    def peek(self) -> str | None:
        kind, value = self.tokens[self.at] if self.at < len(self.tokens) else (None, None)
        return value if kind != "str" else None

    def take(self, *values: str) -> bool:
        if self.peek() in values and self.at < len(self.tokens):
            self.at += 1
            return True
        return False

    def need(self, value: str) -> None:
        if not self.take(value):
            raise TemplateError(f"{value!r} is missing")

    def name(self) -> str:
        kind, value = self.tokens[self.at] if self.at < len(self.tokens) else (None, None)
        if kind != "name" or value.startswith("_"):
            raise TemplateError(f"not a name: {value!r}")
        self.at += 1
        return value

    def done(self, node):
        if self.at != len(self.tokens):
            raise TemplateError(f"unexpected {self.tokens[self.at][1]!r}")
        return node

    def choice(self):
        node = self.either()
        if self.take("if"):
            condition = self.either()
            node = Choose(condition, node, self.choice() if self.take("else") else Const(None))
        return node

    def either(self, op: str = "or"):
        below = (lambda: self.either("and")) if op == "or" else self.negation
        parts = [below()]
        while self.take(op):
            parts.append(below())
        return parts[0] if len(parts) == 1 else Logic(op, tuple(parts))

    def negation(self):
        return Logic("not", (self.negation(),)) if self.take("not") else self.binary(0)

    def binary(self, level: int):
        if level == len(_BINDING):
            return self.unary()
        node = self.binary(level + 1)
        while True:
            op = self.peek()
            if op == "not" and self.tokens[self.at + 1 : self.at + 2] == [("name", "in")] and level == 0:
                self.at += 2
                op = "not in"
            elif op in _BINDING[level]:
                self.at += 1
            else:
                return node
            node = Binary(op, node, self.binary(level + 1))

    def unary(self):
        return Binary("-", Const(0), self.unary()) if self.take("-") else self.postfix()

    def postfix(self):
        node = self.atom()
        while True:
            if self.take("."):
                node = Item(node, Const(self.name()))
            elif self.take("["):
                node = Item(node, self.choice())
                self.need("]")
            elif self.take("|"):
                name, args = self.name(), ()
                if name not in FILTERS:
                    raise TemplateError(f"no filter {name!r}")
                if self.take("("):
                    args = self.many(")")
                node = Filter(name, node, args)
            elif self.take("is"):
                negated = self.take("not")
                name = self.name()
                if name not in TESTS:
                    raise TemplateError(f"no test {name!r}")
                node = Test(name, node, negated)
            else:
                return node

    def many(self, close: str) -> tuple:
        items = []
        while not self.take(close):
            items.append(self.choice())
            if not self.take(","):
                self.need(close)
                break
        return tuple(items)

    def atom(self):
        if self.at >= len(self.tokens):
            raise TemplateError("an expression ends too early")
        kind, value = self.tokens[self.at]
        if kind == "num":
            self.at += 1
            return Const(float(value) if "." in value else int(value))
        if kind == "str":
            self.at += 1
            return Const(re.sub(r"\\(.)", lambda m: _STRING_ESCAPES.get(m[1], m[1]), value[1:-1], flags=re.DOTALL))
        if self.take("("):
            node = self.choice()
            self.need(")")
            return node
        if self.take("["):
            return ListOf(self.many("]"))
        name = self.name()
        words = {"true": True, "false": False, "none": None, "True": True, "False": False, "None": None}
        return Const(words[name]) if name in words else Name(name)


def _expression(source: str):
    e = _Expression(source)
    return e.done(e.choice())


def _pieces(source: str) -> Iterator[tuple[str, str]]:
    at, strip = 0, False
    for m in _TAGS.finditer(source):
        text = source[at : m.start()]
        text = text.lstrip() if strip else text
        yield "text", text.rstrip() if m[1].endswith("-") else text
        if m[1][:2] + m[3][-2:] not in ("{{}}", "{%%}", "{##}"):
            raise TemplateError(f"tag {m[0]!r} is not closed properly")
        if m[1] != "{#":
            yield ("put" if m[1].startswith("{{") else "do"), m[2].strip()
        at, strip = m.end(), m[3].startswith("-")
    yield "text", source[at:].lstrip() if strip else source[at:]


def parse(source: str) -> tuple:
    pieces = list(_pieces(source))
    at = 0

    def body(*ends: str) -> tuple[tuple, str]:
        nonlocal at
        nodes = []
        while at < len(pieces):
            kind, value = pieces[at]
            at += 1
            if kind == "text":
                if value:
                    nodes.append(Text(value))
            elif kind == "put":
                nodes.append(Put(_expression(value)))
            else:
                word, _, rest = value.partition(" ")
                if word in ends:
                    return tuple(nodes), value
                if word == "for":
                    m = re.fullmatch(r"([A-Za-z]\w*)\s+in\s+(.*)", rest.strip(), re.DOTALL)
                    if not m:
                        raise TemplateError(f"cannot read {value!r}")
                    inside, _ = body("endfor")
                    nodes.append(For(m[1], _expression(m[2]), inside))
                elif word == "if":
                    branches, condition = [], _expression(rest)
                    while True:
                        inside, end = body("elif", "else", "endif")
                        branches.append((condition, inside))
                        if end.startswith("elif"):
                            condition = _expression(end[4:])
                        elif end == "else":
                            condition = Const(True)
                        else:
                            break
                    nodes.append(If(tuple(branches)))
                elif word == "set":
                    name, equals, expression = rest.partition("=")
                    if not equals or not re.fullmatch(r"[A-Za-z]\w*", name.strip()):
                        raise TemplateError(f"cannot read {value!r}")
                    nodes.append(Set(name.strip(), _expression(expression)))
                elif word == "generation":
                    inside, _ = body("endgeneration")
                    nodes.append(Generation(inside))
                else:
                    raise TemplateError(f"no block {word!r}")
        if ends:
            raise TemplateError(f"{ends[-1]!r} is missing")
        return tuple(nodes), ""

    return body()[0]


# --- folding -----------------------------------------------------------------------------------------------


def _constant(*nodes) -> bool:
    return all(isinstance(n, Const) for n in nodes)


def fold(node):
    """The expression with constant parts worked out; errors are left for rendering."""
    if isinstance(node, (Const, Name)):
        return node
    if isinstance(node, Item):
        return Item(fold(node.of), fold(node.key))
    if isinstance(node, ListOf):
        items = tuple(map(fold, node.items))
        return Const([i.value for i in items]) if _constant(*items) else ListOf(items)
    if isinstance(node, Choose):
        condition = fold(node.condition)
        if _constant(condition):
            return fold(node.then if condition.value else node.other)
        return Choose(condition, fold(node.then), fold(node.other))
    if isinstance(node, Binary):
        new = Binary(node.op, fold(node.left), fold(node.right))
        inside = (new.left, new.right)
    elif isinstance(node, Logic):
        new = Logic(node.op, tuple(map(fold, node.parts)))
        inside = new.parts
    elif isinstance(node, Filter):
        new = Filter(node.name, fold(node.of), tuple(map(fold, node.args)))
        inside = (new.of, *new.args)
    else:
        new = Test(node.name, fold(node.of), node.negated)
        inside = (new.of,)
    if _constant(*inside):
        try:
            return Const(_evaluator(new)({}))
        except Exception:
            return new
    return new


def folded(body: Iterable) -> tuple:
    """Statements with folded expressions, decided branches and joined texts."""
    out: list = []

    def add(node) -> None:
        if isinstance(node, Text) and out and isinstance(out[-1], Text):
            out[-1] = Text(out[-1].text + node.text)
        else:
            out.append(node)

    for node in body:
        if isinstance(node, Put):
            value = fold(node.value)
            if _constant(value):
                if shown := _shown(value.value):
                    add(Text(shown))
            else:
                add(Put(value))
        elif isinstance(node, If):
            left = []
            for condition, inside in node.branches:
                condition = fold(condition)
                if _constant(condition) and not condition.value:
                    continue
                left.append((condition, folded(inside)))
                if _constant(condition):
                    break
            if left and _constant(left[0][0]):
                for inner in left[0][1]:
                    add(inner)
            elif left:
                add(If(tuple(left)))
        elif isinstance(node, For):
            add(For(node.name, fold(node.of), folded(node.body)))
        elif isinstance(node, Set):
            add(Set(node.name, fold(node.value)))
        elif isinstance(node, Generation):
            add(Generation(folded(node.body)))
        else:
            add(node)
    return tuple(out)


def _shown(value) -> str:
    return "" if value is None else value if isinstance(value, str) else str(value)


# --- closures -------------------------------------------------------------------------------------------------

BEGIN, END = object(), object()


def _evaluator(node) -> Callable[[dict], object]:
    if isinstance(node, Const):
        value = node.value
        return lambda scope: value
    if isinstance(node, Name):
        name = node.name
        return lambda scope: scope.get(name)
    if isinstance(node, Item):
        of, key = _evaluator(node.of), _evaluator(node.key)

        def item(scope):
            box, k = of(scope), key(scope)
            if isinstance(box, dict):
                return box.get(k)
            if isinstance(box, (list, tuple, str)) and isinstance(k, int):
                return box[k] if -len(box) <= k < len(box) else None
            return None

        return item
    if isinstance(node, ListOf):
        items = [_evaluator(i) for i in node.items]
        return lambda scope: [i(scope) for i in items]
    if isinstance(node, Choose):
        condition, then, other = _evaluator(node.condition), _evaluator(node.then), _evaluator(node.other)
        return lambda scope: then(scope) if condition(scope) else other(scope)
    if isinstance(node, Binary):
        op, left, right = _OPERATORS[node.op], _evaluator(node.left), _evaluator(node.right)
        return lambda scope: op(left(scope), right(scope))
    if isinstance(node, Logic):
        parts = [_evaluator(p) for p in node.parts]
        if node.op == "not":
            return lambda scope: not parts[0](scope)
        stop_at = node.op == "or"

        def logic(scope):
            value = None
            for p in parts:
                value = p(scope)
                if bool(value) is stop_at:
                    break
            return value

        return logic
    if isinstance(node, Filter):
        run, of, args = FILTERS[node.name], _evaluator(node.of), [_evaluator(a) for a in node.args]
        return (lambda scope: run(of(scope), *[a(scope) for a in args])) if args else (lambda scope: run(of(scope)))
    if isinstance(node, Test):
        run, of, negated = TESTS[node.name], _evaluator(node.of), node.negated
        return lambda scope: bool(run(of(scope))) is not negated
    raise TemplateError(f"not an expression: {node!r}")


def _statement(node) -> Callable[[dict], Iterator]:
    if isinstance(node, Text):
        text = node.text

        def write(scope):
            yield text

        return write
    if isinstance(node, Put):
        value = _evaluator(node.value)

        def put(scope):
            yield _shown(value(scope))

        return put
    if isinstance(node, Set):
        value, name = _evaluator(node.value), node.name

        def assign(scope):
            scope[name] = value(scope)
            return
            yield

        return assign
    if isinstance(node, If):
        branches = [(_evaluator(c), _body(b)) for c, b in node.branches]

        def decide(scope):
            for condition, inside in branches:
                if condition(scope):
                    yield from inside(scope)
                    return

        return decide
    if isinstance(node, For):
        of, name, inside = _evaluator(node.of), node.name, _body(node.body)

        def loop(scope):
            many = iter(of(scope) or ())
            now, nothing = next(many, BEGIN), BEGIN
            index = 0
            while now is not nothing:
                after = next(many, BEGIN)
                own = dict(scope)
                own[name], own["loop"] = now, {"index": index + 1, "index0": index, "first": index == 0, "last": after is nothing}
                yield from inside(own)
                now, index = after, index + 1

        return loop
    if isinstance(node, Generation):
        inside = _body(node.body)

        def generation(scope):
            yield BEGIN
            yield from inside(scope)
            yield END

        return generation
    raise TemplateError(f"not a statement: {node!r}")


def _body(nodes: tuple) -> Callable[[dict], Iterator]:
    parts = [_statement(n) for n in nodes]

    def run(scope):
        for p in parts:
            yield from p(scope)

    return run


def compiled(source: str) -> Callable[[dict], Iterator]:
    """A closure that renders a scope lazily: texts, BEGIN and END."""
    return _body(folded(parse(source)))


def segments(render: Iterator, most: int = SEGMENT_CHARS) -> Iterator[tuple[str, list[tuple[int, int]]]]:
    """Text and generation spans, let go at a piece's end once there are ``most`` characters."""
    parts, at, spans, open_at = [], 0, [], None
    for piece in render:
        if piece is BEGIN:
            open_at = at
        elif piece is END:
            if at > open_at:
                spans.append((open_at, at))
            open_at = None
        else:
            parts.append(piece)
            at += len(piece)
            if at >= most:
                if open_at is not None and at > open_at:
                    spans.append((open_at, at))
                yield "".join(parts), spans
                parts, at, spans, open_at = [], 0, [], None if open_at is None else 0
    if at:
        yield "".join(parts), spans


def render(source: str, scope: dict) -> tuple[str, list[tuple[int, int]]]:
    """The whole text and its generation spans."""
    return next(segments(compiled(source)(scope), most=1 << 62), ("", []))


# --- tables ------------------------------------------------------------------------------------------------------


def format_conversations(rows: DataFrame, template: str = TEMPLATE) -> DataFrame:
    """``conv_id, segment, text, loss_starts, loss_ends``: the formatted text in segments, in order in each partition.

    ``rows``: ``conv_id, turn, role, text``. A conversation's segments are its output, one after another;
    the loss spans count code points within the segment.
    """
    parse(template)
    lined = rows.select(F.col("conv_id").cast("long"), "turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        program = compiled(template)
        flat = (r for batch in batches for r in zip(*[c.to_pylist() for c in batch.columns], strict=True))
        held, size = [], 0
        for conv_id, own in itertools.groupby(flat, key=operator.itemgetter(0)):
            messages = ({"turn": t, "role": r, "text": x} for _, t, r, x in own)
            for k, (text, spans) in enumerate(segments(program({"messages": messages}))):
                held.append((conv_id, k, text, [a for a, _ in spans], [b for _, b in spans]))
                size += len(text)
                if size >= 1 << 22:
                    yield _batch(held)
                    held, size = [], 0
        if held:
            yield _batch(held)

    def _batch(held: list[tuple]) -> pa.RecordBatch:
        kinds = (pa.int64(), pa.int64(), pa.string(), pa.list_(pa.int64()), pa.list_(pa.int64()))
        return pa.RecordBatch.from_arrays([pa.array(x, type=t) for x, t in zip(zip(*held, strict=True), kinds, strict=True)], ["conv_id", "segment", "text", "loss_starts", "loss_ends"])

    return lined.mapInArrow(run, "conv_id long, segment long, text string, loss_starts array<long>, loss_ends array<long>")


def turns(texts: Iterable[str]) -> Iterator[tuple[str, str]]:
    """Role and text of each turn, read back from formatted text in segments (the standard template)."""
    rest = ""
    for text in texts:
        rest, at = rest + text, 0
        while m := _TURN.match(rest, at):
            yield unescaped(m[1]), unescaped(m[2])
            at = m.end()
        rest = rest[at:]
    if rest:
        raise ValueError("formatted text does not end with a whole turn")


def read_back(formatted: DataFrame) -> DataFrame:
    """Digests of each conversation from its segments alone; needs the partitions of ``format_conversations``.

    Segments out of order, or apart from their conversation's others, are an error: stored output is first to be
    repartitioned by conv_id and sorted within partitions by conv_id and segment.
    """
    names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        flat = (r for batch in batches for r in zip(*[c.to_pylist() for c in batch.columns], strict=True))
        held = []
        for conv_id, own in itertools.groupby(flat, key=operator.itemgetter(0)):
            count = {"n": 0, "loss": 0, "chars": 0}
            said, learnt = hashlib.sha256(), hashlib.sha256()

            def seen(rows=own, count=count, learnt=learnt):
                for place, (conv, k, text, starts, ends) in enumerate(rows):
                    if k != place:
                        raise ValueError(f"conversation {conv}: segment {k} comes at place {place}")
                    count["chars"] += len(text)
                    for a, b in zip(starts, ends, strict=True):
                        piece = unescaped(text[a:b])
                        count["loss"] += len(piece)
                        learnt.update(piece.encode("utf-8", "surrogatepass"))
                    yield text

            for role, text in turns(seen()):
                count["n"] += 1
                said.update(f"{role}\n{text}\n".encode("utf-8", "surrogatepass"))
            held.append((conv_id, count["n"], said.hexdigest(), count["loss"], learnt.hexdigest(), count["chars"]))
            if len(held) >= 10_000:
                yield _batch(held)
                held = []
        if held:
            yield _batch(held)

    def _batch(held: list[tuple]) -> pa.RecordBatch:
        kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
        return pa.RecordBatch.from_arrays([pa.array(x, type=t) for x, t in zip(zip(*held, strict=True), kinds, strict=True)], names)

    return formatted.mapInArrow(run, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")
