"""Self-joins: all assignments of policy aliases to instances, and their linear form.

A constraint holds for all assignments if each of its conjuncts holds for all instances (one
alias), for all pairs (two), and so on. A symmetric pair needs fewer comparisons where it is
transitive: equality takes one with a representative for each further instance, inequality one
distinctness test, a bounded difference one spread test. Other symmetric pairs keep all
unordered pairs, and conjuncts over more aliases all assignments of theirs."""

from __future__ import annotations

import itertools
import math
from dataclasses import replace
from typing import Callable, Sequence

from . import expr as E
from .constraint import analyze
from .plan import Bound, Instance, alias_assignments, bind
from .policy import FlowPolicy, SourceRef


def _swap(n: E.Node, m: dict[str, str]) -> E.Node:
    if isinstance(n, E.Attr) and n.qualifier and n.qualifier.lower() in m:
        return E.Attr((m[n.qualifier.lower()], n.name))
    if isinstance(n, E.Attr):
        return E.Attr(tuple(p.lower() if i == 0 and len(n.parts) > 1 else p for i, p in enumerate(n.parts)))
    return E.rebuild(n, lambda x: _swap(x, m))


def _canonical(n: E.Node) -> str:
    if isinstance(n, E.Op) and n.op in ("and", "or", "=", "!=", "<=>", "+", "*"):
        return f"{n.op}({', '.join(sorted(_canonical(a) for a in n.args))})"
    if isinstance(n, E.Op) and n.op in (">", ">="):
        return _canonical(E.Op({">": "<", ">=": "<="}[n.op], (n.args[1], n.args[0])))
    if isinstance(n, E.Call) and n.name in ("greatest", "least"):
        return f"{n.name}({', '.join(sorted(_canonical(a) for a in n.args))})"
    if isinstance(n, E.Call) and n.name == "abs" and isinstance(n.args[0], E.Op) and n.args[0].op == "-":
        return f"absdiff({', '.join(sorted(_canonical(a) for a in n.args[0].args))})"
    if isinstance(n, (E.Attr, E.Lit, E.Slot)):
        return E.render(n).lower()
    if isinstance(n, E.Call):
        return f"{n.name}[{n.distinct}]({', '.join(_canonical(a) for a in n.args)})"
    return E.render(E.rebuild(n, lambda x: E.Lit(_canonical(x))))


def is_symmetric(p: FlowPolicy) -> bool:
    """Whether swapping any two aliases of one table leaves the constraint as it is."""
    groups: dict[str, list[str]] = {}
    for s in p.sources:
        groups.setdefault(s.table.lower(), []).append(s.name.lower())
    tree = p.tree
    base = _canonical(_swap(tree, {}))
    for names in groups.values():
        for a, b in zip(names, names[1:]):
            if _canonical(_swap(tree, {a: b, b: a})) != base:
                return False
    return any(len(v) > 1 for v in groups.values())


def permutation_count(n: int, m: int) -> int:
    return math.perm(n, m)


def _term(c: E.Node, alias: str) -> E.Node | None:
    """The side of an equality that reads the alias alone."""
    if isinstance(c, E.Op) and c.op in ("=", "!="):
        for x in c.args:
            if {y.qualifier for y in E.attrs(x)} == {alias}:
                return x
    return None


def linear_clauses(p: FlowPolicy, n: int) -> list[str]:
    """Clauses of a policy over one table with the instances ``t0 .. t(n-1)``."""
    return clauses_over(p, {s.table.lower(): [f"t{i}" for i in range(n)] for s in p.sources})


def clauses_over(p: FlowPolicy, names: dict[str, list[str]]) -> list[str]:
    """Clauses over the instances of each table that together say what all assignments of the
    policy's aliases say."""
    table = {s.name.lower(): s.table.lower() for s in p.sources}
    out: dict[str, None] = {}

    def put(c: E.Node, places: dict[str, str]) -> str:
        return E.render(_swap(c, places))

    for c in E.conjuncts(_swap(p.tree, {})):
        used = list(dict.fromkeys(x.qualifier for x in E.attrs(c) if x.qualifier in table))
        made: list[str] = []
        if len(used) == 2 and len({table[u] for u in used}) == 1 and _canonical(_swap(c, dict(zip(used, reversed(used))))) == _canonical(c):
            made = _symmetric(c, used, names[table[used[0]]], put)
        else:
            by: dict[str, list[str]] = {}
            for u in used:
                by.setdefault(table[u], []).append(u)
            ways = [[dict(zip(mine, w)) for w in itertools.permutations(names[t], len(mine))] for t, mine in by.items()]
            made = [put(c, {k: v for part in way for k, v in part.items()}) for way in itertools.product(*ways)]
        out |= dict.fromkeys(made)
    return list(out)


def _symmetric(c: E.Node, used: list[str], at: list[str], put) -> list[str]:
    a, b = used
    term = _term(c, a)
    if isinstance(c, E.Op) and c.op == "=" and term is not None:
        return [put(c, {a: at[0], b: t}) for t in at[1:]]
    if isinstance(c, E.Op) and c.op == "!=" and term is not None:
        every = [put(term, {a: t}) for t in at]
        nulls = " AND ".join(f"({x} IS NOT NULL)" for x in every)
        return [f"(size(array_distinct(array({', '.join(every)}))) = {len(at)} AND {nulls})"]
    if (spread := _spread(c)) is not None:
        term, op, k = spread
        every = [put(_swap(term, {b: a}), {a: t}) for t in at]
        nulls = " AND ".join(f"({x} IS NOT NULL)" for x in every)
        return [f"((greatest({', '.join(every)}) - least({', '.join(every)})) {op} {k} AND {nulls})"] if len(at) > 1 else []
    return [put(c, {a: x, b: y}) for x, y in itertools.combinations(at, 2)]


def _spread(c: E.Node):
    if isinstance(c, E.Op) and c.op in ("<", "<=") and isinstance(c.args[0], E.Call) and c.args[0].name == "abs":
        d = c.args[0].args[0]
        if isinstance(d, E.Op) and d.op == "-" and E.number(c.args[1]) is not None:
            return d.args[0], c.op, E.render(c.args[1])
    return None


def permutation_clauses(p: FlowPolicy, n: int) -> list[str]:
    """One clause for each assignment of the aliases to instances."""
    names = [s.name.lower() for s in p.sources]
    return [E.render(_swap(p.tree, dict(zip(names, (f"t{i}" for i in combo))))) for combo in itertools.permutations(range(n), len(names))]


def linear_bound(p: FlowPolicy, instances: Sequence[Instance], schema_of: Callable[[str], list[str]]) -> Bound | None:
    """One bound policy that stands for all assignments, or None where a part of the policy ties
    an alias to more than its conjuncts (keyed dimensions, required sources, unqualified names)."""
    if p.required or any(d.on for d in p.dimensions) or any(x.qualifier is None for x in E.attrs(p.tree)):
        return None
    here: dict[str, list[Instance]] = {}
    for s in p.sources:
        table = s.table.lower()
        here[table] = [i for i in instances if i.table == table.rsplit(".", 1)[-1]]
    clauses = clauses_over(p, {t: [f"t{i.id}" for i in own] for t, own in here.items()})
    sources = tuple(SourceRef(t, f"t{i.id}") for t, own in here.items() for i in own)
    spread = replace(p, sources=sources, constraint=" AND ".join(clauses))
    form = analyze(spread, schema_of)
    kept = {E.render(c): c for c in E.conjuncts(form.residual)}
    form.residual = E.Op("and", tuple(kept.values())) if len(kept) > 1 else form.residual
    return bind(spread, form, {f"t{i.id}": i.id for own in here.values() for i in own})


__all__ = ["alias_assignments", "clauses_over", "is_symmetric", "linear_bound", "linear_clauses", "permutation_clauses", "permutation_count"]
