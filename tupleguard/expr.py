"""Constraint expressions: a small SQL expression tree with a precedence-climbing parser.

The tree is rendered back to SQL, with names substituted, whenever a Spark column is built, so
every scalar function that Spark knows can appear in a constraint."""

from __future__ import annotations

import re
from dataclasses import dataclass, field, replace as _replace
from typing import Callable, Iterator

from .errors import PolicySyntaxError


@dataclass(frozen=True)
class Node:
    pass


@dataclass(frozen=True)
class Lit(Node):
    sql: str


@dataclass(frozen=True)
class Attr(Node):
    """A possibly qualified name."""

    parts: tuple[str, ...]

    @property
    def qualifier(self) -> str | None:
        return ".".join(self.parts[:-1]) or None

    @property
    def name(self) -> str:
        return self.parts[-1]


@dataclass(frozen=True)
class Call(Node):
    name: str
    args: tuple[Node, ...]
    distinct: bool = False
    where: Node | None = None
    star: bool = False


@dataclass(frozen=True)
class Op(Node):
    """An operator: NOT and unary minus have one operand; IN, BETWEEN, LIKE and IS forms keep
    their word as ``op``."""

    op: str
    args: tuple[Node, ...]


@dataclass(frozen=True)
class Case(Node):
    whens: tuple[tuple[Node, Node], ...]
    otherwise: Node | None = None


@dataclass(frozen=True)
class Slot(Node):
    """An aggregate that the rewritten query computes."""

    key: str


AGGREGATES = {
    "count", "sum", "avg", "mean", "min", "max", "stddev", "stddev_samp", "stddev_pop", "variance", "var_samp", "var_pop", "covar_samp", "covar_pop", "corr", "regr_slope",
    "bool_and", "every", "bool_or", "some", "any", "unique", "approx_count_distinct", "approx_distinct", "percentile", "median", "collect_list", "collect_set", "mode",
}
_COMPARE = {"=", "==", "<>", "!=", "<", "<=", ">", ">=", "<=>"}
_TOKEN = re.compile(
    r"\s*(?:(?P<num>\d+(?:\.\d*)?(?:[eE][-+]?\d+)?|\.\d+)|(?P<str>'(?:[^']|'')*')|(?P<name>[A-Za-z_][A-Za-z_0-9]*|`[^`]+`)|(?P<op><=>|<>|!=|==|<=|>=|\|\||[-+*/%<>=(),.])|(?P<bad>\S))"
)
_WORDS = {"and", "or", "not", "in", "between", "like", "rlike", "is", "null", "true", "false", "case", "when", "then", "else", "end", "distinct", "filter", "where", "unique"}


class _Parser:
    def __init__(self, text: str):
        self.text, self.toks, self.i = text, [], 0
        at = 0
        while at < len(text):
            m = _TOKEN.match(text, at)
            if not m or m.end() == at:
                break
            if m.group("bad"):
                raise PolicySyntaxError(f"unexpected {m.group('bad')!r}", m.start("bad"))
            kind = m.lastgroup
            if kind is None:
                break
            self.toks.append((kind, m.group(kind), m.start(kind)))
            at = m.end()
            if not text[at:].strip():
                break

    def peek(self, k: int = 0) -> tuple:
        return self.toks[self.i + k] if self.i + k < len(self.toks) else ("end", "", len(self.text))

    def word(self, *words: str) -> bool:
        kind, v, _ = self.peek()
        return kind == "name" and v.lower() in words

    def take(self, *ops: str) -> str | None:
        kind, v, _ = self.peek()
        if (kind == "op" and v in ops) or (kind == "name" and v.lower() in ops):
            self.i += 1
            return v.lower()
        return None

    def need(self, *ops: str) -> str:
        got = self.take(*ops)
        if got is None:
            raise PolicySyntaxError(f"expected {' or '.join(ops)}, found {self.peek()[1] or 'end'!r}", self.peek()[2])
        return got

    def whole(self) -> Node:
        out = self.disjunction()
        if self.peek()[0] != "end":
            raise PolicySyntaxError(f"unexpected {self.peek()[1]!r}", self.peek()[2])
        return out

    def disjunction(self) -> Node:
        parts = [self.conjunction()]
        while self.take("or"):
            parts.append(self.conjunction())
        return parts[0] if len(parts) == 1 else Op("or", tuple(parts))

    def conjunction(self) -> Node:
        parts = [self.negation()]
        while self.take("and"):
            parts.append(self.negation())
        return parts[0] if len(parts) == 1 else Op("and", tuple(parts))

    def negation(self) -> Node:
        if self.take("not"):
            return Op("not", (self.negation(),))
        return self.predicate()

    def predicate(self) -> Node:
        if self.word("unique") and self.peek(1)[1] != "(":
            self.i += 1
            return Call("unique", (self.sum(),))
        left = self.sum()
        kind, v, _ = self.peek()
        if kind == "op" and v in _COMPARE:
            self.i += 1
            return Op({"==": "=", "<>": "!="}.get(v, v), (left, self.sum()))
        negated = False
        if self.word("not") and self.peek(1)[1].lower() in ("in", "between", "like", "rlike"):
            self.i += 1
            negated = True
        out: Node | None = None
        if self.take("in"):
            self.need("(")
            items = [self.disjunction()]
            while self.take(","):
                items.append(self.disjunction())
            self.need(")")
            out = Op("in", (left, *items))
        elif self.take("between"):
            low = self.sum()
            self.need("and")
            out = Op("between", (left, low, self.sum()))
        elif (w := self.take("like", "rlike")) is not None:
            out = Op(w, (left, self.sum()))
        elif self.take("is"):
            no = self.take("not")
            what = self.need("null", "true", "false")
            out = Op(f"is{' not' if no else ''} {what}", (left,))
        if out is None:
            return left
        return Op("not", (out,)) if negated else out

    def sum(self) -> Node:
        out = self.product()
        while (op := self.take("+", "-", "||")) is not None:
            out = Op(op, (out, self.product()))
        return out

    def product(self) -> Node:
        out = self.unary()
        while (op := self.take("*", "/", "%")) is not None:
            out = Op(op, (out, self.unary()))
        return out

    def unary(self) -> Node:
        if self.take("-"):
            return Op("neg", (self.unary(),))
        return self.atom()

    def atom(self) -> Node:
        kind, v, pos = self.peek()
        if kind == "num" or kind == "str":
            self.i += 1
            return Lit(v)
        if self.take("("):
            out = self.disjunction()
            self.need(")")
            return out
        if kind != "name":
            raise PolicySyntaxError(f"unexpected {v or 'end'!r}", pos)
        low = v.lower()
        if low in ("true", "false", "null"):
            self.i += 1
            return Lit(low)
        if low in ("date", "timestamp", "interval") and self.peek(1)[0] == "str":
            self.i += 2
            return Lit(f"{low} {self.toks[self.i - 1][1]}")
        if low == "case":
            return self.case()
        if low in _WORDS and not (low == "unique" and self.peek(1)[1] == "("):
            raise PolicySyntaxError(f"unexpected {v!r}", pos)
        self.i += 1
        if self.take("("):
            return self.call(low)
        parts = [v.strip("`")]
        while self.peek()[1] == "." and self.peek(1)[0] == "name":
            parts.append(self.peek(1)[1].strip("`"))
            self.i += 2
        return Attr(tuple(parts))

    def call(self, name: str) -> Node:
        distinct = star = False
        args: list[Node] = []
        if self.take("*"):
            star = True
        elif self.peek()[1] != ")":
            distinct = self.take("distinct") is not None
            args.append(self.disjunction())
            while self.take(","):
                args.append(self.disjunction())
        self.need(")")
        where = None
        if self.word("filter"):
            self.i += 1
            self.need("(")
            self.need("where")
            where = self.disjunction()
            self.need(")")
        return Call(name, tuple(args), distinct, where, star)

    def case(self) -> Node:
        self.need("case")
        subject = None if self.word("when") else self.disjunction()
        whens = []
        while self.take("when"):
            cond = self.disjunction()
            self.need("then")
            whens.append((cond if subject is None else Op("=", (subject, cond)), self.disjunction()))
        other = self.disjunction() if self.take("else") else None
        self.need("end")
        return Case(tuple(whens), other)


def parse(text: str) -> Node:
    return _Parser(text).whole()


def children(n: Node) -> tuple[Node, ...]:
    if isinstance(n, Call):
        return n.args + ((n.where,) if n.where is not None else ())
    if isinstance(n, Op):
        return n.args
    if isinstance(n, Case):
        return tuple(x for w in n.whens for x in w) + ((n.otherwise,) if n.otherwise is not None else ())
    return ()


def rebuild(n: Node, f: Callable[[Node], Node]) -> Node:
    """The node with ``f`` applied to its children."""
    if isinstance(n, Call):
        return _replace(n, args=tuple(f(a) for a in n.args), where=None if n.where is None else f(n.where))
    if isinstance(n, Op):
        return Op(n.op, tuple(f(a) for a in n.args))
    if isinstance(n, Case):
        return Case(tuple((f(a), f(b)) for a, b in n.whens), None if n.otherwise is None else f(n.otherwise))
    return n


def walk(n: Node) -> Iterator[Node]:
    yield n
    for c in children(n):
        yield from walk(c)


def attrs(n: Node) -> list[Attr]:
    return list(dict.fromkeys(x for x in walk(n) if isinstance(x, Attr)))


def is_aggregate(n: Node) -> bool:
    return isinstance(n, Call) and n.name in AGGREGATES


def has_aggregate(n: Node) -> bool:
    return any(is_aggregate(x) for x in walk(n))


def conjuncts(n: Node) -> list[Node]:
    return [x for a in n.args for x in conjuncts(a)] if isinstance(n, Op) and n.op == "and" else [n]


def quote(name: str) -> str:
    return name if re.fullmatch(r"[A-Za-z_][A-Za-z_0-9]*", name) and name.lower() not in _WORDS else f"`{name}`"


def render(n: Node, name: Callable[[Node], str | None] = lambda _: None) -> str:
    """SQL text; ``name`` may give the text of attributes and slots."""
    go = lambda x: render(x, name)
    if isinstance(n, (Attr, Slot)):
        own = name(n)
        if own is not None:
            return own
        return ".".join(quote(p) for p in n.parts) if isinstance(n, Attr) else f"`{n.key}`"
    if isinstance(n, Lit):
        return n.sql
    if isinstance(n, Call):
        inner = "*" if n.star else ("DISTINCT " if n.distinct else "") + ", ".join(map(go, n.args))
        return f"{n.name}({inner})" + (f" FILTER (WHERE {go(n.where)})" if n.where is not None else "")
    if isinstance(n, Case):
        return "CASE " + " ".join(f"WHEN {go(a)} THEN {go(b)}" for a, b in n.whens) + (f" ELSE {go(n.otherwise)}" if n.otherwise is not None else "") + " END"
    assert isinstance(n, Op)
    a = n.args
    if n.op in ("and", "or"):
        return "(" + f" {n.op.upper()} ".join(map(go, a)) + ")"
    if n.op == "not":
        return f"(NOT {go(a[0])})"
    if n.op == "neg":
        return f"(- {go(a[0])})"
    if n.op == "in":
        return f"({go(a[0])} IN ({', '.join(map(go, a[1:]))}))"
    if n.op == "between":
        return f"({go(a[0])} BETWEEN {go(a[1])} AND {go(a[2])})"
    if n.op.startswith("is"):
        return f"({go(a[0])} {n.op.upper()})"
    return f"({go(a[0])} {n.op.upper()} {go(a[1])})"


def number(n: Node) -> float | None:
    """The value of a numeric literal, signed ones included."""
    if isinstance(n, Op) and n.op == "neg":
        v = number(n.args[0])
        return None if v is None else -v
    if isinstance(n, Lit):
        try:
            return float(n.sql)
        except ValueError:
            return None
    return None


@dataclass
class Linear:
    """``scale * term + shift``."""

    scale: float
    term: Node
    shift: float = 0.0
    notes: dict = field(default_factory=dict)


def linear(n: Node) -> Linear:
    """Constant scale and shift pulled out of a scalar expression."""
    if isinstance(n, Op) and n.op == "neg":
        x = linear(n.args[0])
        return Linear(-x.scale, x.term, -x.shift)
    if isinstance(n, Op) and n.op in ("+", "-"):
        a, b = n.args
        sign = 1.0 if n.op == "+" else -1.0
        if (k := number(b)) is not None:
            x = linear(a)
            return Linear(x.scale, x.term, x.shift + sign * k)
        if (k := number(a)) is not None:
            x = linear(b)
            return Linear(sign * x.scale, x.term, k + sign * x.shift)
    if isinstance(n, Op) and n.op == "*":
        a, b = n.args
        if (k := number(b)) is None and (k := number(a)) is not None:
            a = b
        if k is not None:
            x = linear(a)
            return Linear(x.scale * k, x.term, x.shift * k)
    if isinstance(n, Op) and n.op == "/" and (k := number(n.args[1])):
        x = linear(n.args[0])
        return Linear(x.scale / k, x.term, x.shift / k)
    return Linear(1.0, n, 0.0)
