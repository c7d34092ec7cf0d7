"""A policy's constraint split into the aggregates that a query must carry and the predicate
that is left over them, the output tuple, dimensions and session values."""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import Callable

from . import expr as E
from .algebra import ALIASES, Agg, bounded_distinct
from .errors import UnknownAttribute
from .policy import OUTPUT, FlowPolicy

SESSION = {"current_user": "current_user()", "current_date": "current_date()", "current_timestamp": "current_timestamp()", "current_database": "current_database()"}


@dataclass
class ConstraintForm:
    """``residual`` has slots: keys of ``aggs``, ``out:<column>`` for the output tuple and
    ``exists:<n>`` for dimension sub-formulas."""

    residual: E.Node
    aggs: dict[str, Agg] = field(default_factory=dict)
    outputs: list[str] = field(default_factory=list)
    exists: dict[str, E.Node] = field(default_factory=dict)
    #: Source aliases that the aggregates read.
    reads: dict[str, frozenset] = field(default_factory=dict)


def alias_of(node: E.Node) -> frozenset:
    """The source aliases of a resolved scalar tree."""
    return frozenset(a.parts[0] for a in E.attrs(node))


class _Analysis:
    def __init__(self, p: FlowPolicy, schema_of: Callable[[str], list[str]]):
        self.p = p
        self.columns: dict[str, list[str]] = {}
        self.kind: dict[str, str] = {}
        self.owner: dict[str, str] = {}
        for s in p.sources:
            self._add(s.name, "source", schema_of(s.table))
            if s.alias is None and "." in s.table:
                self._add(s.table.rsplit(".", 1)[1], "source", schema_of(s.table))
        for d in p.dimensions:
            if d.table.upper() == OUTPUT:
                self._add(d.name, "output", [])
                continue
            self._add(d.name, "keyed" if d.on else "free", schema_of(d.table))
            if d.on:
                keys = [a for a in E.attrs(E.parse(d.on)) if a.qualifier and a.qualifier.lower() != d.name.lower()]
                self.owner[d.name.lower()] = (keys[0].qualifier if keys else p.sources[0].name).lower()
        self._add(OUTPUT, "output", [])
        if p.sink is not None:
            for n in {p.sink.name, p.sink.table}:
                self._add(n, "output", [])
        self.form = ConstraintForm(E.Lit("true"))

    def _add(self, name: str, kind: str, cols: list[str]) -> None:
        self.columns.setdefault(name.lower(), cols)
        self.kind.setdefault(name.lower(), kind)

    def resolve(self, a: E.Attr) -> tuple[str, E.Node]:
        """(kind, resolved node) of a name."""
        if a.qualifier is None:
            if a.name.lower() in SESSION:
                return "session", E.Attr(("session", a.name.lower()))
            hits = [q for q, cols in self.columns.items() if a.name.lower() in (c.lower() for c in cols)]
            hits = list(dict.fromkeys(hits))
            if len(hits) == 1:
                return self.kind[hits[0]], E.Attr((hits[0], a.name))
            if not hits and (self.p.sink is not None or OUTPUT in (d.table.upper() for d in self.p.dimensions)):
                return "output", E.Attr((OUTPUT, a.name))
            raise UnknownAttribute(f"{a.name}: {'ambiguous among ' + ', '.join(hits) if hits else 'no such attribute'}")
        q = a.qualifier.lower()
        if q not in self.kind:
            raise UnknownAttribute(f"{a.qualifier}.{a.name}")
        kind = self.kind[q]
        if kind == "output":
            return kind, E.Attr((OUTPUT, a.name))
        if a.name.lower() not in (c.lower() for c in self.columns[q]):
            raise UnknownAttribute(f"{a.qualifier}.{a.name}")
        return kind, E.Attr((q, a.name))

    def kinds(self, n: E.Node) -> set[str]:
        return {self.resolve(a)[0] for a in E.attrs(n)}

    def resolved(self, n: E.Node) -> E.Node:
        return self.resolve(n)[1] if isinstance(n, E.Attr) else E.rebuild(n, self.resolved)

    def slot(self, agg: Agg) -> E.Slot:
        self.form.aggs[agg.key] = agg
        self.form.reads[agg.key] = frozenset(self.owner.get(x, x) for a in agg.args for x in alias_of(a))
        return E.Slot(agg.key)

    def unique(self, arg: E.Node) -> E.Node:
        low, high = self.slot(Agg("min", (arg,))), self.slot(Agg("max", (arg,)))
        return E.Call("coalesce", (E.Op("=", (low, high)), E.Lit("false")))

    def aggregate(self, c: E.Call) -> E.Node:
        args = tuple(self.resolved(a) for a in c.args)
        for a in args:
            for x in E.attrs(a):
                if x.parts[0] == OUTPUT or self.kind.get(x.parts[0]) == "free":
                    raise UnknownAttribute(f"{E.render(x)} cannot be aggregated")
        name = ALIASES.get(c.name, c.name)
        if c.where is not None:
            cond = self.resolved(c.where)
            args = tuple(E.Case(((cond, a),)) for a in (args or (E.Lit("1"),)))
        if name == "unique":
            return self.unique(args[0])
        if name == "count" and c.distinct:
            return self.slot(Agg("distinct", args))
        return self.slot(Agg(name, args))

    def value(self, n: E.Node, bare: list[E.Node]) -> E.Node:
        """A scalar part of an atom; bare source attributes are noted and stand for their one value."""
        if E.is_aggregate(n):
            return self.aggregate(n)
        if isinstance(n, E.Attr):
            kind, node = self.resolve(n)
            if kind in ("source", "keyed"):
                if node not in bare:
                    bare.append(node)
                return self.slot(Agg("min", (node,)))
            if kind == "output":
                if n.name not in self.form.outputs:
                    self.form.outputs.append(n.name)
                return E.Slot(f"out:{n.name}")
            if kind == "free":
                raise UnknownAttribute(f"{E.render(n)}: a dimension without a key may only stand beside dimensions and session values")
            return node
        return E.rebuild(n, lambda x: self.value(x, bare))

    def atom(self, n: E.Node) -> E.Node:
        if isinstance(n, E.Op) and n.op in ("=", "!=", "<", "<=", ">", ">="):
            flip = {"<": ">", "<=": ">=", ">": "<", ">=": "<="}
            for a, b, op in ((n.args[0], n.args[1], n.op), (n.args[1], n.args[0], flip.get(n.op, n.op))):
                if isinstance(a, E.Call) and a.name == "count" and a.distinct and (k := E.number(b)) is not None and (form := bounded_distinct(op, k)):
                    args = self.aggregate(a)
                    arg = self.form.aggs.pop(args.key).args[0]
                    self.form.reads.pop(args.key)
                    low, high = self.slot(Agg("min", (arg,))), self.slot(Agg("max", (arg,)))
                    return _template(form, low, high)
        bare: list[E.Node] = []
        out = self.value(n, bare)
        return E.Op("and", (*(self.unique(b) for b in bare), out)) if bare else out

    def only_free(self, n: E.Node) -> bool:
        """Whether dimension rows alone decide the part; a negation is of the existence below it."""
        if E.has_aggregate(n) or any(isinstance(x, E.Op) and x.op == "not" for x in E.walk(n)):
            return False
        kinds = self.kinds(n)
        return "free" in kinds and kinds <= {"free", "session"}

    def exists(self, n: E.Node) -> E.Node:
        key = f"exists:{len(self.form.exists)}"
        self.form.exists[key] = self.resolved(n)
        return E.Slot(key)

    def boolean(self, n: E.Node) -> E.Node:
        if self.only_free(n):
            return self.exists(n)
        if isinstance(n, E.Op) and n.op == "and":
            free = tuple(a for a in n.args if self.only_free(a))
            rest = [self.boolean(a) for a in n.args if a not in free]
            if free:
                rest.append(self.exists(free[0] if len(free) == 1 else E.Op("and", free)))
            return rest[0] if len(rest) == 1 else E.Op("and", tuple(rest))
        if isinstance(n, E.Op) and n.op in ("or", "not"):
            return E.Op(n.op, tuple(self.boolean(a) for a in n.args))
        if isinstance(n, E.Case):
            return E.Case(tuple((self.boolean(a), self.boolean(b)) for a, b in n.whens), None if n.otherwise is None else self.boolean(n.otherwise))
        return self.atom(n)


def _template(text: str, low: E.Slot, high: E.Slot) -> E.Node:
    swap = {"min_": low, "max_": high}

    def put(n: E.Node) -> E.Node:
        return swap[n.name] if isinstance(n, E.Attr) and n.name in swap else E.rebuild(n, put)

    return put(E.parse(text.replace("{min}", "min_").replace("{max}", "max_")))


def analyze(p: FlowPolicy, schema_of: Callable[[str], list[str]]) -> ConstraintForm:
    a = _Analysis(p, schema_of)
    a.form.residual = a.boolean(p.tree)
    used = {s.key for s in E.walk(a.form.residual) if isinstance(s, E.Slot)}
    a.form.aggs = {k: v for k, v in a.form.aggs.items() if k in used}
    a.form.reads = {k: v for k, v in a.form.reads.items() if k in used}
    return a.form


def split_linear(agg: Agg, non_null: set[str] = frozenset()) -> list[tuple[int, Agg]] | None:
    """``sum(a + b)`` over different sources as signed single-source sums, or None. It holds only
    if no operand is null where another isn't, so every attribute must be known non-null."""
    if agg.kind != "sum" or len(alias_of(agg.args[0])) < 2:
        return None
    terms: list[tuple[int, E.Node]] = []

    def collect(n: E.Node, sign: int) -> None:
        if isinstance(n, E.Op) and n.op in ("+", "-"):
            collect(n.args[0], sign)
            collect(n.args[1], sign if n.op == "+" else -sign)
        elif isinstance(n, E.Op) and n.op == "neg":
            collect(n.args[0], -sign)
        else:
            terms.append((sign, n))

    collect(agg.args[0], 1)
    if any(len(alias_of(t)) > 1 for _, t in terms):
        return None
    if not all(E.render(a) in non_null for a in E.attrs(agg.args[0])):
        return None
    return [(s, Agg("sum", (t,))) for s, t in terms]
