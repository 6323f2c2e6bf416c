"""A sandboxed template language for conversations, compiled to Python closures.

Text stands for itself. `{{ expr }}` writes a value, `{% for m in messages %}` ..
`{% endfor %}`, `{% if expr %}` .. `{% elif expr %}` .. `{% else %}` ..
`{% endif %}` control, and `{% generation %}` .. `{% endgeneration %}` marks what
a model is trained on. A line break right after a `%}` is dropped.

Expressions have strings, integers, true and false, names, `m.field` or
`m['field']` on messages and `loop` only, `+`, `==`, `!=`, `not`, `and`, `or`,
parentheses, and filters after `|`. There are no calls, no other attributes and
no loops but over `messages`, so a template can't reach Python or run on.

Source is parsed into a tree, constant parts are folded (constant expressions,
pure filters of constants, branches with a constant condition, neighbouring
text), and the tree becomes nested closures.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterable
from dataclasses import dataclass, field
from typing import Any

FIELDS = ("role", "text")
LOOP_FIELDS = ("index0", "index", "first")


class TemplateError(ValueError):
    """The template's source is not in the language."""


# -- escaping ----------------------------------------------------------------

def escape(text: str) -> str:
    """Make control strings (those that begin with `<|`) impossible in ``text``; reversible."""
    return text.replace("\\", "\\\\").replace("<|", "<\\|")


def escape_line(text: str) -> str:
    """The same for a text on one line: line breaks become `\\n`."""
    return escape(text).replace("\n", "\\n")


_ESCAPED = re.compile(r"\\(.)", re.S)


def unescape(text: str) -> str:
    return _ESCAPED.sub(lambda m: "\n" if m[1] == "n" else m[1], text)


FILTERS: dict[str, Callable[[str], str]] = {
    "escape": escape, "escape_line": escape_line, "trim": str.strip, "upper": str.upper, "lower": str.lower,
}


# -- tree --------------------------------------------------------------------

@dataclass(frozen=True)
class Const:
    value: Any


@dataclass(frozen=True)
class Name:
    name: str


@dataclass(frozen=True)
class Get:
    of: str
    field: str


@dataclass(frozen=True)
class Op:
    op: str
    args: tuple


@dataclass(frozen=True)
class Filter:
    name: str
    arg: Any


@dataclass
class Text:
    text: str


@dataclass
class Write:
    expr: Any


@dataclass
class If:
    branches: list[tuple[Any, list]]
    other: list = field(default_factory=list)


@dataclass
class For:
    name: str
    body: list


@dataclass
class Generation:
    body: list


# -- parsing -----------------------------------------------------------------

_TAGS = re.compile(r"(\{\{.*?\}\}|\{%.*?%\}\n?)", re.S)
_TOKENS = re.compile(r"\s*(?:('(?:[^'\\]|\\.)*'|\"(?:[^\"\\]|\\.)*\")|(\d+)|([A-Za-z_]\w*)|(==|!=|[-+|.()\[\]]))")


def _tokens(source: str) -> list[str]:
    out, at = [], 0
    source = source.strip()
    while at < len(source):
        m = _TOKENS.match(source, at)
        if not m:
            raise TemplateError(f"unexpected text in an expression: {source[at:at + 20]!r}")
        out.append(m[0].strip())
        at = m.end()
    return out


class _Expression:
    """A recursive-descent parser of one expression."""

    def __init__(self, source: str, names: frozenset[str]):
        self.tokens, self.at, self.names = _tokens(source), 0, names

    def peek(self) -> str | None:
        return self.tokens[self.at] if self.at < len(self.tokens) else None

    def take(self, want: str | None = None) -> str:
        token = self.peek()
        if token is None or want is not None and token != want:
            raise TemplateError(f"expected {want or 'more'}, found {token}")
        self.at += 1
        return token

    def whole(self) -> Any:
        out = self.either()
        if self.peek() is not None:
            raise TemplateError(f"unexpected {self.peek()}")
        return out

    def _left(self, ops: tuple[str, ...], below: Callable[[], Any]) -> Any:
        out = below()
        while self.peek() in ops:
            out = Op(self.take(), (out, below()))
        return out

    def either(self) -> Any:
        return self._left(("or",), self.both)

    def both(self) -> Any:
        return self._left(("and",), self.negation)

    def negation(self) -> Any:
        if self.peek() == "not":
            self.take()
            return Op("not", (self.negation(),))
        return self._left(("==", "!="), self.total)

    def total(self) -> Any:
        return self._left(("+",), self.filtered)

    def filtered(self) -> Any:
        out = self.atom()
        while self.peek() == "|":
            self.take()
            name = self.take()
            if name not in FILTERS:
                raise TemplateError(f"unknown filter {name}")
            out = Filter(name, out)
        return out

    def atom(self) -> Any:
        token = self.take()
        if token == "(":
            out = self.either()
            self.take(")")
            return out
        if token[0] in "'\"":
            return Const(re.sub(r"\\(.)", lambda m: {"n": "\n", "t": "\t"}.get(m[1], m[1]), token[1:-1], flags=re.S))
        if token.isdigit():
            return Const(int(token))
        if token in ("true", "false"):
            return Const(token == "true")
        if not re.fullmatch(r"[A-Za-z]\w*", token):
            raise TemplateError(f"unexpected {token}")
        if token not in self.names:
            raise TemplateError(f"unknown name {token}")
        if self.peek() in (".", "["):
            if self.take() == ".":
                key = self.take()
            else:
                key = self.take()
                if key[0] not in "'\"":
                    raise TemplateError("a field's name is a string")
                key = key[1:-1]
                self.take("]")
            allowed = LOOP_FIELDS if token == "loop" else FIELDS
            if key not in allowed or token == "add_generation_prompt":
                raise TemplateError(f"{token} has no field {key}")
            return Get(token, key)
        if token != "add_generation_prompt":
            raise TemplateError(f"{token} needs a field")
        return Name(token)


def parse(source: str) -> list:
    """The tree of a template."""
    parts = _TAGS.split(source)
    at = 0

    def block(ends: tuple[str, ...], names: frozenset[str], loop: bool, marked: bool) -> tuple[list, str]:
        nonlocal at
        out: list = []
        while at < len(parts):
            part = parts[at]
            at += 1
            if part.startswith("{{") and part.endswith("}}"):
                out.append(Write(_Expression(part[2:-2], names).whole()))
            elif part.startswith("{%") and part.rstrip("\n").endswith("%}"):
                code = part.rstrip("\n")[2:-2].strip()
                word, _, rest = code.partition(" ")
                if word in ends:
                    return out, code
                if word == "if":
                    branches = []
                    cond = _Expression(rest, names).whole()
                    while True:
                        body, end = block(("elif", "else", "endif"), names, loop, marked)
                        branches.append((cond, body))
                        if not end.startswith("elif"):
                            break
                        cond = _Expression(end[4:], names).whole()
                    other = block(("endif",), names, loop, marked)[0] if end == "else" else []
                    out.append(If(branches, other))
                elif word == "for":
                    m = re.fullmatch(r"([A-Za-z]\w*) +in +messages", rest.strip())
                    if not m or loop or marked or m[1] in names or m[1] == "loop":
                        raise TemplateError(f"unsupported loop: {code}")
                    body, _ = block(("endfor",), names | {m[1], "loop"}, True, marked)
                    out.append(For(m[1], body))
                elif word == "generation" and not rest and not marked:
                    out.append(Generation(block(("endgeneration",), names, loop, True)[0]))
                else:
                    raise TemplateError(f"unexpected tag {code}")
            elif part:
                out.append(Text(part))
        if ends:
            raise TemplateError(f"missing {ends[-1]}")
        return out, ""

    return block((), frozenset({"add_generation_prompt"}), False, False)[0]


# -- folding -----------------------------------------------------------------

_PURE: dict[str, Callable[..., Any]] = {
    "+": lambda a, b: a + b if isinstance(a, int) and isinstance(b, int) and not isinstance(a, bool) else _show(a) + _show(b),
    "==": lambda a, b: a == b, "!=": lambda a, b: a != b, "not": lambda a: not a, "and": lambda a, b: a and b, "or": lambda a, b: a or b,
}


def _show(value: Any) -> str:
    return value if isinstance(value, str) else str(value).lower() if isinstance(value, bool) else str(value)


def fold_expr(e: Any) -> Any:
    if isinstance(e, Op):
        args = tuple(map(fold_expr, e.args))
        return Const(_PURE[e.op](*(a.value for a in args))) if all(isinstance(a, Const) for a in args) else Op(e.op, args)
    if isinstance(e, Filter):
        arg = fold_expr(e.arg)
        return Const(FILTERS[e.name](_show(arg.value))) if isinstance(arg, Const) else Filter(e.name, arg)
    return e


def fold(body: list) -> list:
    """The same tree with constant parts worked out."""
    out: list = []

    def put(node: Any) -> None:
        if isinstance(node, Text):
            if not node.text:
                return
            if out and isinstance(out[-1], Text):
                out[-1] = Text(out[-1].text + node.text)
                return
        out.append(node)

    for node in body:
        if isinstance(node, Write):
            e = fold_expr(node.expr)
            put(Text(_show(e.value)) if isinstance(e, Const) else Write(e))
        elif isinstance(node, If):
            branches, other = [], fold(node.other)
            for cond, inner in node.branches:
                cond = fold_expr(cond)
                if isinstance(cond, Const):
                    if cond.value:
                        other = fold(inner)
                        break
                    continue
                branches.append((cond, fold(inner)))
            if branches:
                put(If(branches, other))
            else:
                for x in other:
                    put(x)
        elif isinstance(node, For):
            put(For(node.name, fold(node.body)))
        elif isinstance(node, Generation):
            put(Generation(fold(node.body)))
        else:
            put(node)
    return out


# -- closures ----------------------------------------------------------------

Env = dict[str, Any]
#: Pieces of output, each with whether it is under the loss mask.
Out = list[tuple[str, bool]]


def _value(e: Any) -> Callable[[Env], Any]:
    if isinstance(e, Const):
        return lambda env, v=e.value: v
    if isinstance(e, Name):
        return lambda env, n=e.name: env[n]
    if isinstance(e, Get):
        return lambda env, n=e.of, f=e.field: env[n][f]
    if isinstance(e, Filter):
        return lambda env, f=FILTERS[e.name], a=_value(e.arg): f(_show(a(env)))
    args = [_value(a) for a in e.args]
    if e.op == "and":
        return lambda env: args[0](env) and args[1](env)
    if e.op == "or":
        return lambda env: args[0](env) or args[1](env)
    if len(args) == 1:
        return lambda env, f=_PURE[e.op]: f(args[0](env))
    return lambda env, f=_PURE[e.op]: f(args[0](env), args[1](env))


def _block(body: list, mask: bool) -> Callable[[Env, Out], None]:
    steps: list[Callable[[Env, Out], None]] = []
    for node in body:
        if isinstance(node, Text):
            steps.append(lambda env, out, t=(node.text, mask): out.append(t))
        elif isinstance(node, Write):
            steps.append(lambda env, out, v=_value(node.expr): out.append((_show(v(env)), mask)))
        elif isinstance(node, Generation):
            steps.append(_block(node.body, True))
        elif isinstance(node, If):
            ways = [(_value(c), _block(b, mask)) for c, b in node.branches]

            def choose(env: Env, out: Out, ways=ways, other=_block(node.other, mask)) -> None:
                for cond, run in ways:
                    if cond(env):
                        return run(env, out)
                return other(env, out)

            steps.append(choose)
        else:
            def loop(env: Env, out: Out, name=node.name, run=_block(node.body, mask)) -> None:
                for i, message in enumerate(env["messages"]):
                    run({**env, name: message, "loop": {"index0": i, "index": i + 1, "first": i == 0}}, out)

            steps.append(loop)

    def run_all(env: Env, out: Out) -> None:
        for step in steps:
            step(env, out)

    return run_all


def _uses_loop(node: Any) -> bool:
    if isinstance(node, Get):
        return node.of == "loop"
    if isinstance(node, (list, tuple)):
        return any(map(_uses_loop, node))
    return hasattr(node, "__dataclass_fields__") and any(_uses_loop(getattr(node, f)) for f in node.__dataclass_fields__)


class Template:
    """A compiled template."""

    def __init__(self, source: str):
        self.source = source
        self.tree = fold(parse(source))
        self._whole = _block(self.tree, False)
        loops = [i for i, n in enumerate(self.tree) if isinstance(n, For)]
        #: Turns render by themselves if one loop stands alone on the top level and doesn't look at its counter.
        self.by_turn = len(loops) == 1 and not _uses_loop(self.tree) and not any(isinstance(n, (If, Generation)) and _has_loop(n) for n in self.tree)
        if self.by_turn:
            at = loops[0]
            self._head, self._tail = _block(self.tree[:at], False), _block(self.tree[at + 1 :], False)
            self._turn, self._name = _block(self.tree[at].body, False), self.tree[at].name

    def render(self, messages: Iterable[dict[str, str]], add_generation_prompt: bool = False) -> Out:
        out: Out = []
        self._whole({"messages": messages, "add_generation_prompt": add_generation_prompt}, out)
        return out

    def render_turn(self, message: dict[str, str], add_generation_prompt: bool = False) -> Out:
        out: Out = []
        self._turn({self._name: message, "add_generation_prompt": add_generation_prompt}, out)
        return out

    def ends(self, add_generation_prompt: bool = False) -> tuple[str, str]:
        """What stands before and after the turns."""
        head: Out = []
        tail: Out = []
        self._head({"add_generation_prompt": add_generation_prompt}, head)
        self._tail({"add_generation_prompt": add_generation_prompt}, tail)
        return "".join(t for t, _ in head), "".join(t for t, _ in tail)


def _has_loop(node: Any) -> bool:
    if isinstance(node, For):
        return True
    if isinstance(node, (list, tuple)):
        return any(map(_has_loop, node))
    return hasattr(node, "__dataclass_fields__") and any(_has_loop(getattr(node, f)) for f in node.__dataclass_fields__)
