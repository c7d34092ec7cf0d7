"""Templated threshold policies: millions of bindings collapse to a handful of clauses.

A template is ``agg(expr) op ?``. Of bindings with one canonical aggregate, only the dominating
bound matters: the largest for > and >=, the smallest for < and <= (a strict bound wins a tie),
one value for = (two values cannot hold), all distinct values at once for !=. Linear forms are
brought to one canonical aggregate first: shifts and scales move into the bound."""

from __future__ import annotations

import heapq
from collections import Counter
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, functions as F

from . import expr as E
from .policy import FlowPolicy, Resolution, REMOVE, SourceRef

_FLIP = {"<": ">", "<=": ">=", ">": "<", ">=": "<=", "=": "=", "!=": "!="}


@dataclass(frozen=True)
class PolicyTemplate:
    agg: str
    expr: str
    op: str

    def bind(self, k: float, owner: str | None = None) -> "Binding":
        return Binding(self, float(k), owner)


@dataclass(frozen=True)
class Binding:
    template: PolicyTemplate
    k: float
    owner: str | None = None


def canonical_term(agg: str, expr: str, op: str, k: float) -> tuple[str, str, str, float]:
    """The canonical ``(aggregate SQL, '', op, bound)`` of one binding."""
    name = agg.lower()
    if name not in ("min", "max", "avg", "sum"):
        return f"{name}({E.render(E.parse(expr)) if expr != '*' else '*'})", name, op, k
    lin = E.linear(E.parse(expr))
    if name == "sum" and lin.shift:
        # sum(a x + b) = a sum(x) + b count(x): the bound depends on the count, so the sum of the
        # scaled term and the count stay together, in one canonical spelling
        text = E.render(lin.term)
        ratio = lin.shift / lin.scale
        if lin.scale < 0:
            op = _FLIP[op]
        return f"(sum({text}) + {ratio!r} * count({text}))", "sum", op, k / lin.scale
    if lin.scale < 0:
        op = _FLIP[op]
        name = {"min": "max", "max": "min"}.get(name, name)
    return f"{name}({E.render(lin.term)})", name, op, (k - lin.shift * (name != "sum")) / lin.scale


class _Bounds:
    """A multiset of bounds with its extreme at hand: lazy deletion from a heap."""

    def __init__(self, sign: int):
        self.sign, self.heap, self.live = sign, [], Counter()

    def add(self, item: tuple) -> None:
        self.live[item] += 1
        heapq.heappush(self.heap, item)

    def remove(self, item: tuple) -> None:
        self.live[item] -= 1

    def best(self) -> tuple | None:
        while self.heap and self.live[self.heap[0]] <= 0:
            heapq.heappop(self.heap)
        return self.heap[0] if self.heap else None


@dataclass
class _Class:
    lower: _Bounds = field(default_factory=lambda: _Bounds(-1))
    upper: _Bounds = field(default_factory=lambda: _Bounds(1))
    equal: Counter = field(default_factory=Counter)
    other: Counter = field(default_factory=Counter)


class TemplateIndex:
    """The bindings' dominating clauses; adding is O(log n), reading them O(classes)."""

    def __init__(self):
        self.classes: dict[str, _Class] = {}

    @staticmethod
    def _item(op: str, k: float) -> tuple:
        # heaps pop the smallest: lower bounds are negated; strict sorts before loose
        return (-k if op in (">", ">=") else k, 0 if op in ("<", ">") else 1)

    def add(self, b: Binding) -> None:
        text, _, op, k = canonical_term(b.template.agg, b.template.expr, b.template.op, b.k)
        c = self.classes.setdefault(text, _Class())
        if op in (">", ">="):
            c.lower.add(self._item(op, k))
        elif op in ("<", "<="):
            c.upper.add(self._item(op, k))
        elif op == "=":
            c.equal[k] += 1
        else:
            c.other[k] += 1

    def remove(self, b: Binding) -> None:
        text, _, op, k = canonical_term(b.template.agg, b.template.expr, b.template.op, b.k)
        c = self.classes[text]
        if op in (">", ">="):
            c.lower.remove(self._item(op, k))
        elif op in ("<", "<="):
            c.upper.remove(self._item(op, k))
        else:
            (c.equal if op == "=" else c.other)[k] -= 1

    def clauses(self, simplify: bool = True) -> list[str]:
        out = []
        for text, c in self.classes.items():
            lo, hi = c.lower.best(), c.upper.best()
            equal = sorted(k for k, n in c.equal.items() if n > 0)
            other = sorted(k for k, n in c.other.items() if n > 0)
            if simplify and self._contradiction(lo, hi, equal, other):
                return ["false"]
            if equal:
                out.append(f"({text} = {equal[0]!r})" if len(equal) == 1 else "false")
                if simplify and len(equal) == 1:
                    continue
            if lo is not None:
                out.append(f"({text} {'>' if lo[1] == 0 else '>='} {-lo[0]!r})")
            if hi is not None:
                out.append(f"({text} {'<' if hi[1] == 0 else '<='} {hi[0]!r})")
            if other:
                out.append(f"(NOT ({text} IN ({', '.join(repr(k) for k in other)})))")
        return out

    @staticmethod
    def _contradiction(lo, hi, equal, other) -> bool:
        low = None if lo is None else -lo[0]
        if len(equal) > 1:
            return True
        if lo is not None and hi is not None and (low > hi[0] or (low == hi[0] and 0 in (lo[1], hi[1]))):
            return True
        if equal:
            e = equal[0]
            return bool((lo is not None and (e < low or (e == low and lo[1] == 0))) or (hi is not None and (e > hi[0] or (e == hi[0] and hi[1] == 0))) or e in other)
        return False

    def policy(self, name: str, table: str, on_fail: Resolution = REMOVE) -> FlowPolicy:
        return FlowPolicy(name, " AND ".join(self.clauses()) or "true", (SourceRef(table),), on_fail=on_fail)

    @classmethod
    def from_dataframe(cls, df: DataFrame) -> "TemplateIndex":
        """From rows ``(agg, expr, op, k)``: bindings are reduced in Spark to their dominating
        bounds per template before the driver sees them."""
        out = cls()
        one = df.where("op in ('<','<=','>','>=')").groupBy("agg", "expr", "op").agg(F.min("k").alias("low"), F.max("k").alias("high"))
        for r in one.toLocalIterator():
            out.add(PolicyTemplate(r["agg"], r["expr"], r["op"]).bind(r["high"] if r["op"] in (">", ">=") else r["low"]))
        # two values of an equality decide; exclusions are kept whole, as distinct values
        eq = df.where("op = '='").groupBy("agg", "expr", "op").agg(F.min("k").alias("low"), F.max("k").alias("high"))
        for r in eq.toLocalIterator():
            for k in {r["low"], r["high"]}:
                out.add(PolicyTemplate(r["agg"], r["expr"], "=").bind(k))
        # exclusions that the bounds decide already stay in Spark
        edge = df.where("op in ('<','<=','>','>=')").groupBy("agg", "expr").agg(F.max(F.when(F.col("op").isin(">", ">="), F.col("k"))).alias("above"), F.min(F.when(F.col("op").isin("<", "<="), F.col("k"))).alias("below"))
        other = df.where("op = '!='").select("agg", "expr", "k").distinct().join(edge, ["agg", "expr"], "left").where("(above is null or k >= above) and (below is null or k <= below)")
        for r in other.select("agg", "expr", "k").toLocalIterator():
            out.add(PolicyTemplate(r["agg"], r["expr"], "!=").bind(r["k"]))
        return out


def naive_conjunction(bindings) -> str:
    """One clause a binding, uncollapsed: the baseline."""
    return " AND ".join(f"({b.template.agg}({b.template.expr}) {b.template.op} {b.k!r})" for b in bindings) or "true"
