"""Chat formatting by a template compiler.

A template is cut into tokens, parsed to a syntax tree, folded where it is constant, and turned into Python
closures. The language is a sandbox: values are strings, numbers, booleans, null, lists and mappings; names reach
what the caller passes and nothing else; there are no calls, no attributes of Python objects and no imports.

    {{ expression }}                          the value's text
    {% for x in xs %} .. {% endfor %}         with loop.index, loop.index0, loop.first, loop.last
    {% if a %} .. {% elif b %} .. {% else %} .. {% endif %}
    {% set x = expression %}
    {% generation %} .. {% endgeneration %}   marks what the model is trained to write
    {# comment #}                             and - inside a tag's end strips white space

Expressions: literals, names, a.b and a['b'] of mappings, a[0] of lists, | filters, ~ + - * / % (of numbers),
== != < <= > >= in, not, and, or, a if c else b.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterable, Iterator

from pyspark.sql import DataFrame

TAG = re.compile(r"\{\{-?(.*?)-?\}\}|\{%-?(.*?)-?%\}|\{#.*?#\}", re.S)
LEX = re.compile(r"""\s*(?:(?P<num>\d+(?:\.\d+)?)|(?P<name>[A-Za-z_]\w*)|(?P<str>'(?:[^'\\]|\\.)*'|"(?:[^"\\]|\\.)*")|(?P<op>==|!=|<=|>=|[-+*/%~<>()\[\],.|=]))""", re.S)
ESCAPES = {"n": "\n", "t": "\t", "r": "\r"}
WORDS = {"true": True, "false": False, "none": None, "True": True, "False": False, "None": None}


class TemplateError(ValueError):
    """The template is wrong, or asks for what the sandbox does not give."""


# Control strings of the default template. Fixed values.
CONTROL = ("###", "</turn>")
ROLES = {"user": "User", "assistant": "Assistant", "system": "System", "tool": "Tool"}
_ESCAPED = re.compile(r"\\|#(?=##)|<(?=/turn>)")


def escape(text: str) -> str:
    """A backslash before each backslash and before the start of each control string."""
    return _ESCAPED.sub(lambda m: "\\" + m[0], text)


def unescape(text: str) -> str:
    return re.sub(r"\\(.)", r"\1", text, flags=re.S)


def role_label(role: str) -> str:
    """A known role's label, or = and the role with colons, line ends and control strings escaped."""
    return ROLES.get(role) or "=" + re.sub(r"[:\n]", lambda m: "\\" + m[0], escape(role))


FILTERS: dict[str, Callable] = {
    "escape": escape, "label": role_label, "trim": lambda s: str(s).strip(), "upper": lambda s: str(s).upper(),
    "lower": lambda s: str(s).lower(), "length": len, "string": str, "default": lambda v, d="": d if v is None else v,
    "replace": lambda s, a, b: str(s).replace(a, b), "join": lambda xs, sep="": sep.join(map(str, xs)), "first": lambda xs: xs[0], "last": lambda xs: xs[-1],
}
BINARY: dict[str, Callable] = {
    "~": lambda a, b: _text(a) + _text(b), "==": lambda a, b: a == b, "!=": lambda a, b: a != b, "in": lambda a, b: a in b,
    "<": lambda a, b: a < b, "<=": lambda a, b: a <= b, ">": lambda a, b: a > b, ">=": lambda a, b: a >= b,
    "+": lambda a, b: _number(a) + _number(b), "-": lambda a, b: _number(a) - _number(b), "*": lambda a, b: _number(a) * _number(b),
    "/": lambda a, b: _number(a) / _number(b), "%": lambda a, b: _number(a) % _number(b),
}
LEVELS = (("==", "!=", "<", "<=", ">", ">=", "in"), ("~",), ("+", "-"), ("*", "/", "%"))
DEFAULT = (
    "{% for m in messages %}### {{ m.role | label }}: "
    "{% if m.role == 'assistant' %}{% generation %}{{ m.text | escape }}{% endgeneration %}"
    "{% else %}{{ m.text | escape }}{% endif %}</turn>\n{% endfor %}"
)


def _text(value) -> str:
    return "" if value is None else value if isinstance(value, str) else str(value)


def _number(value):
    if isinstance(value, bool) or not isinstance(value, int | float):
        raise TemplateError("arithmetic is of numbers; ~ joins texts")
    return value


def _get(value, key):
    """A mapping's entry (null if it has none) or a list's element; nothing of any other object."""
    if isinstance(value, dict):
        return value.get(key)
    if isinstance(value, list | tuple | str) and isinstance(key, int) and not isinstance(key, bool):
        return value[key] if -len(value) <= key < len(value) else None
    return None


class _Expression:
    """Recursive descent over one expression's tokens; nodes are tuples, ("const", v) once folded."""

    def __init__(self, source: str):
        self.tokens, at = [], 0
        source = source.strip()
        while at < len(source):
            m = LEX.match(source, at)
            if not m:
                raise TemplateError(f"can't read {source[at:]!r}")
            kind = m.lastgroup
            self.tokens.append((kind, m[kind]))
            at = m.end()
        self.at = 0

    def peek(self, *values):
        return self.at < len(self.tokens) and self.tokens[self.at][0] != "str" and self.tokens[self.at][1] in values

    def take(self, *values):
        if self.peek(*values):
            self.at += 1
            return self.tokens[self.at - 1][1]
        return None

    def need(self, value):
        if not self.take(value):
            raise TemplateError(f"{value!r} is missing")

    def name(self):
        if self.at < len(self.tokens) and self.tokens[self.at][0] == "name":
            self.at += 1
            return self.tokens[self.at - 1][1]
        raise TemplateError("a name is missing")

    def whole(self):
        node = self.choice()
        if self.at < len(self.tokens):
            raise TemplateError(f"{self.tokens[self.at][1]!r} is left over")
        return node

    def choice(self):
        node = self.disjunction()
        if self.take("if"):
            test = self.disjunction()
            other = self.choice() if self.take("else") else ("const", None)
            return _folded(("choose", test, node, other))
        return node

    def disjunction(self):
        node = self.conjunction()
        while self.take("or"):
            node = _folded(("or", node, self.conjunction()))
        return node

    def conjunction(self):
        node = self.negation()
        while self.take("and"):
            node = _folded(("and", node, self.negation()))
        return node

    def negation(self):
        return _folded(("not", self.negation())) if self.take("not") else self.binary(0)

    def binary(self, level):
        if level == len(LEVELS):
            return self.postfix()
        node = self.binary(level + 1)
        while (op := self.take(*LEVELS[level])) or (level == 0 and self.peek("not") and self.at + 1 < len(self.tokens) and self.tokens[self.at + 1][1] == "in"):
            if op:
                node = _folded(("binary", op, node, self.binary(level + 1)))
            else:
                self.at += 2
                node = _folded(("not", ("binary", "in", node, self.binary(level + 1))))
        return node

    def postfix(self):
        node = self.atom()
        while True:
            if self.take("."):
                node = _folded(("get", node, ("const", self.name())))
            elif self.take("["):
                key = self.choice()
                self.need("]")
                node = _folded(("get", node, key))
            elif self.take("|"):
                name, args = self.name(), []
                if name not in FILTERS:
                    raise TemplateError(f"there is no filter {name}")
                if self.take("("):
                    while not self.take(")"):
                        args.append(self.choice())
                        if not self.peek(")"):
                            self.need(",")
                node = _folded(("filter", name, node, *args))
            else:
                return node

    def atom(self):
        if self.take("("):
            node = self.choice()
            self.need(")")
            return node
        if self.take("-"):
            return _folded(("binary", "-", ("const", 0), self.postfix()))
        if self.at >= len(self.tokens):
            raise TemplateError("an expression is missing")
        kind, value = self.tokens[self.at]
        self.at += 1
        if kind == "num":
            return ("const", float(value) if "." in value else int(value))
        if kind == "str":
            return ("const", re.sub(r"\\(.)", lambda m: ESCAPES.get(m[1], m[1]), value[1:-1], flags=re.S))
        if kind == "name":
            return ("const", WORDS[value]) if value in WORDS else ("name", value)
        raise TemplateError(f"{value!r} is not expected")


def _folded(node):
    """The node, or its value as a constant where all its operands are constants."""
    operands = [x for x in node[1:] if isinstance(x, tuple)]
    if operands and all(x[0] == "const" for x in operands):
        try:
            return ("const", _value(node)({}))
        except Exception:
            return node  # it fails when the template runs, if it runs there
    if node[0] == "choose" and node[1][0] == "const":
        return node[2] if node[1][1] else node[3]
    return node


def _value(node) -> Callable[[dict], object]:
    """A closure from the names' values to the node's value."""
    kind, parts = node[0], node[1:]
    if kind == "const":
        return lambda env, v=parts[0]: v
    if kind == "name":
        return lambda env, n=parts[0]: env.get(n)
    if kind == "get":
        a, b = map(_value, parts)
        return lambda env: _get(a(env), b(env))
    if kind == "not":
        a = _value(parts[0])
        return lambda env: not a(env)
    if kind == "and":
        a, b = map(_value, parts)
        return lambda env: a(env) and b(env)
    if kind == "or":
        a, b = map(_value, parts)
        return lambda env: a(env) or b(env)
    if kind == "choose":
        t, a, b = map(_value, parts)
        return lambda env: a(env) if t(env) else b(env)
    if kind == "binary":
        f, a, b = BINARY[parts[0]], _value(parts[1]), _value(parts[2])
        return lambda env: f(a(env), b(env))
    f, a, args = FILTERS[parts[0]], _value(parts[1]), [_value(x) for x in parts[2:]]
    return lambda env: f(a(env), *(x(env) for x in args))


def parse(source: str) -> list[tuple]:
    """The syntax tree: nodes text, print, for, if, set, generation. Constant prints are text, constant ifs are gone."""
    stack: list[tuple[str, list, list]] = [("template", [], [])]
    at, strip = 0, False

    def put(node):
        body = stack[-1][1]
        if node[0] == "text" and body and body[-1][0] == "text":
            body[-1] = ("text", body[-1][1] + node[1])
        elif node[0] != "text" or node[1]:
            body.append(node)

    for m in TAG.finditer(source):
        text = source[at : m.start()]
        text = text.lstrip() if strip else text
        put(("text", text.rstrip() if m[0][2:3] == "-" else text))
        at, strip = m.end(), m[0][-3:-2] == "-"
        if m[1] is not None:
            node = _Expression(m[1]).whole()
            put(("text", _text(node[1])) if node[0] == "const" else ("print", node))
        elif m[2] is not None:
            word, _, rest = m[2].strip().partition(" ")
            if word == "for":
                e = _Expression(rest)
                name = e.name()
                e.need("in")
                stack.append(("for", [], [name, e.whole()]))
            elif word == "if":
                stack.append(("if", [], [[], _Expression(rest).whole()]))
            elif word in ("elif", "else") and stack[-1][0] == "if":
                _, body, (done, test) = stack.pop()
                stack.append(("if", [], [[*done, (test, body)], _Expression(rest).whole() if word == "elif" else ("const", True)]))
            elif word == "generation":
                if any(kind == "generation" for kind, _, _ in stack):
                    raise TemplateError("generation blocks don't nest")
                stack.append(("generation", [], []))
            elif word == "set":
                e = _Expression(rest)
                name = e.name()
                e.need("=")
                put(("set", name, e.whole()))
            elif word.startswith("end") and word[3:] == stack[-1][0]:
                kind, body, extra = stack.pop()
                if kind == "for":
                    put(("for", *extra, body))
                elif kind == "generation":
                    put(("generation", body))
                else:
                    branches = []
                    for test, inner in [*extra[0], (extra[1], body)]:
                        if test[0] != "const" or test[1]:
                            branches.append((test, inner))
                        if test[0] == "const" and test[1]:
                            break
                    if branches and branches[0][0][0] == "const":
                        for node in branches[0][1]:
                            put(node)
                    elif branches:
                        put(("if", branches))
            else:
                raise TemplateError(f"{m[2].strip()!r} is not expected")
    text = source[at:]
    put(("text", text.lstrip() if strip else text))
    if len(stack) > 1:
        raise TemplateError(f"{stack[-1][0]} has no end")
    return stack[0][1]


def _looped(items: Iterable) -> Iterator[tuple[object, dict]]:
    """Each item with its loop variables; one item ahead is read for loop.last."""
    if not isinstance(items, list | tuple) and not hasattr(items, "__next__"):
        raise TemplateError("for goes over lists")
    items = iter(items)
    end = object()
    item, i = next(items, end), 0
    while item is not end:
        following = next(items, end)
        yield item, {"index": i + 1, "index0": i, "first": i == 0, "last": following is end}
        item, i = following, i + 1


def _block(nodes: list[tuple]) -> Callable[[dict, bool], Iterator[tuple[str, bool]]]:
    steps = [_step(node) for node in nodes]

    def run(env, marked):
        for step in steps:
            yield from step(env, marked)

    return run


def _step(node):
    kind = node[0]
    if kind == "text":
        return lambda env, marked, t=node[1]: iter(((t, marked),))
    if kind == "print":
        value = _value(node[1])
        return lambda env, marked: iter(((_text(value(env)), marked),))
    if kind == "generation":
        body = _block(node[1])
        return lambda env, marked: body(env, True)
    if kind == "set":
        name, value = node[1], _value(node[2])

        def assign(env, marked):
            env[name] = value(env)
            return iter(())

        return assign
    if kind == "if":
        branches = [(_value(test), _block(body)) for test, body in node[1]]

        def choose(env, marked):
            for test, body in branches:
                if test(env):
                    return body(env, marked)
            return iter(())

        return choose
    name, value, body = node[1], _value(node[2]), _block(node[3])

    def loop(env, marked):
        for item, about in _looped(value(env) or []):
            yield from body({**env, name: item, "loop": about}, marked)

    return loop


def compile_template(source: str) -> Callable[[dict], Iterator[tuple[str, bool]]]:
    """render(names) yields (text, whether the model is trained on it). Lists may be iterators: they are read as needed."""
    body = _block(parse(source))
    return lambda names: body(dict(names), False)


def _conversations(batches) -> Iterator[tuple[object, Iterator[dict]]]:
    """The conversations of sorted batches; each must be read to its end before the next."""
    from itertools import groupby

    def rows():
        for batch in batches:
            yield from zip(*(batch.column(c).to_pylist() for c in ("conv_id", "role", "text")), strict=True)

    for conv_id, turns in groupby(rows(), key=lambda r: r[0]):
        yield conv_id, ({"role": role or "", "text": text or ""} for _, role, text in turns)


def format_conversations(conversations: DataFrame, template: str = DEFAULT, part_chars: int = 1_000_000) -> DataFrame:
    """conv_id, part, text, loss (array of start, end in the part's code points) for every conversation.

    Rows of a conversation go in the order of turn, then role, then text (nulls first). Null roles and texts count as
    empty; a null conv_id is a conversation. A conversation is one part unless it is longer than part_chars, so that a
    task holds one part and one turn at a time, however long a conversation is. Parts lie in order within a partition.
    An empty table gives no rows; other columns are ignored.
    """

    def render(batches):
        import pyarrow as pa

        run = compile_template(template)
        schema = pa.schema([("conv_id", pa.int64()), ("part", pa.int32()), ("text", pa.string()), ("loss", pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())])))])
        out, waiting = [], 0

        def flush():
            nonlocal out, waiting
            batch = pa.RecordBatch.from_pylist(out, schema)
            out, waiting = [], 0
            return batch

        for conv_id, turns in _conversations(batches):
            number, texts, length, loss = 0, [], 0, []
            for text, marked in run({"messages": turns}):
                if marked and text:
                    if loss and loss[-1]["end"] == length and loss[-1]["open"]:
                        loss[-1]["end"] += len(text)
                    else:
                        loss.append({"start": length, "end": length + len(text), "open": True})
                elif loss:
                    loss[-1]["open"] = False
                texts.append(text)
                length += len(text)
                if length >= part_chars:
                    out.append({"conv_id": conv_id, "part": number, "text": "".join(texts), "loss": loss})
                    yield flush()
                    number, texts, length, loss = number + 1, [], 0, []
            if texts or not number:
                out.append({"conv_id": conv_id, "part": number, "text": "".join(texts), "loss": loss})
                waiting += length
            if len(out) >= 2000 or waiting >= part_chars:
                yield flush()
        if out:
            yield flush()

    rows = conversations.select("conv_id", "turn", "role", "text")
    dealt = rows.repartition("conv_id").sortWithinPartitions("conv_id", "turn", "role", "text")
    return dealt.select("conv_id", "role", "text").mapInArrow(
        render, "conv_id long, part int, text string, loss array<struct<start:long,end:long>>"
    )


_MARK = re.compile(r"\\.|### |</turn>\n", re.S)
_ROLE_END = re.compile(r"\\.|: ", re.S)


class TurnReader:
    """Reads the default template's output back, in pieces of any size; turns() yields (role, text) of whole turns."""

    def __init__(self):
        self.rest = ""

    def turns(self, more: str) -> Iterator[tuple[str, str]]:
        data = self.rest + more
        at = 0
        while True:
            end = next((m for m in _MARK.finditer(data, at) if m[0] == "</turn>\n"), None)
            if end is None:
                break
            if not data.startswith("### ", at):
                raise ValueError("a turn must begin with its mark")
            colon = next(m for m in _ROLE_END.finditer(data, at + 4) if m[0] == ": ")
            label = data[at + 4 : colon.start()]
            role = unescape(label[1:]) if label.startswith("=") else {v: k for k, v in ROLES.items()}[label]
            yield role, unescape(data[colon.end() : end.start()])
            at = end.end()
        self.rest = data[at:]


def read_back(formatted: DataFrame) -> DataFrame:
    """conv_id, n_turns, turns_sha256, loss_chars, loss_sha256, formatted_chars, read from format_conversations' output.

    turns_sha256 is of role, line end, text, line end of each turn; loss_sha256 of all text under the loss mask, unescaped.
    The partitions and their order must be as format_conversations left them.
    """

    def read(batches):
        import pyarrow as pa
        from itertools import groupby

        names = ["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"]
        schema = pa.schema([(n, pa.string() if n.endswith("sha256") else pa.int64()) for n in names])

        def rows():
            for batch in batches:
                yield from zip(*(batch.column(c).to_pylist() for c in ("conv_id", "text", "loss")), strict=True)

        out = []
        for conv_id, parts in groupby(rows(), key=lambda r: r[0]):
            reader, turns, loss, n, loss_chars, chars = TurnReader(), hashlib.sha256(), hashlib.sha256(), 0, 0, 0
            for _, text, spans in parts:
                chars += len(text)
                for role, said in reader.turns(text):
                    n += 1
                    turns.update(f"{role}\n{said}\n".encode("utf-8", "surrogatepass"))
                for span in spans:
                    said = unescape(text[span["start"] : span["end"]])
                    loss_chars += len(said)
                    loss.update(said.encode("utf-8", "surrogatepass"))
            if reader.rest:
                raise ValueError("a turn has no end")
            out.append((conv_id, n, turns.hexdigest(), loss_chars, loss.hexdigest(), chars))
            if len(out) >= 5000:
                yield pa.RecordBatch.from_pylist([dict(zip(names, r, strict=True)) for r in out], schema)
                out = []
        yield pa.RecordBatch.from_pylist([dict(zip(names, r, strict=True)) for r in out], schema)

    return formatted.mapInArrow(
        read, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long"
    )
