"""Portable SQL of guarded queries, for engines other than Spark: annotations are extra columns of
every block, the guard is a filter above and a closing projection."""

from __future__ import annotations

import re
from dataclasses import dataclass, field
from typing import Callable

from . import expr as E
from .algebra import components, direct_sql, finalize_sql
from .constraint import ConstraintForm, analyze
from .errors import UnsupportedPlan
from .plan import Bound, Instance, alias_assignments, all_components, bind
from .policy import FlowPolicy


def to_sql(select: list[str], body: str, group_by: list[str], policies: list[FlowPolicy], schema_of) -> str:
    """``SELECT select FROM/WHERE body GROUP BY group_by`` guarded by policies whose sources are
    named in ``body`` by the policies' source names."""
    forms = [analyze(p, schema_of) for p in policies]
    slots: dict[str, str] = {}
    for f in forms:
        for key, agg in f.aggs.items():
            if key not in slots:
                slots[key] = direct_sql(agg, [E.render(a) for a in agg.args])
    names = {key: f"tg_{i}" for i, key in enumerate(slots)}

    def name(n):
        if isinstance(n, E.Slot):
            return n.key[4:] if n.key.startswith("out:") else names[n.key]
        return None

    inner = ", ".join([*select, *(f"{text} AS {names[k]}" for k, text in slots.items())])
    cols = ", ".join(s.rsplit(" AS ", 1)[-1].rsplit(" as ", 1)[-1].rsplit(".", 1)[-1].strip() for s in select)
    where = " AND ".join(f"coalesce({E.render(f.residual, name)}, false)" for f in forms) or "true"
    group = f" GROUP BY {', '.join(group_by)}" if group_by else ""
    return f"SELECT {cols} FROM (SELECT {inner} {body}{group}) AS guarded WHERE {where}"


@dataclass(frozen=True)
class From:
    """One relation of a block: a table's name, or another query. ``how``: inner, left or semi;
    a semi join keeps rows whose ``on`` (an expression) equals the side's column ``key``."""

    what: object
    alias: str
    how: str = "inner"
    on: str | None = None
    key: str | None = None


@dataclass(frozen=True)
class Block:
    """``SELECT items FROM sources WHERE where GROUP BY group_by HAVING having tail``. Items are
    (expression, name); ``group_by`` None: no aggregation, (): one row for all. DISTINCT is a
    grouping by all items. ``tail`` holds ORDER BY and LIMIT."""

    items: tuple[tuple[str, str], ...]
    sources: tuple[From, ...]
    where: str | None = None
    group_by: tuple[str, ...] | None = None
    having: str | None = None
    tail: str = ""


@dataclass(frozen=True)
class UnionAll:
    parts: tuple


@dataclass
class _Text:
    """SQL of a query and the columns that its annotations stand in."""

    sql: str
    names: list[str]
    cols: dict[str, str] = field(default_factory=dict)
    mult: str | None = None
    here: dict[int, str] = field(default_factory=dict)


def _portable(text: str) -> str:
    """Number literals without Spark's suffixes; the text holds only columns and numbers."""
    return re.sub(r"\b(\d+)L\b", r"\1", re.sub(r"\b(\d+(?:e-?\d+)?)D\b", lambda m: m[1] if "e" in m[1] else m[1] + "e0", text))


class _Writer:
    """Inline enforcement as text: the same leaves, scaling and merging as in Spark plans."""

    def __init__(self, query, policies, schema_of: Callable[[str], list[str]]):
        self.instances: list[Instance] = []
        self.schema_of = schema_of
        self.wanted = {s.table.lower() for p in policies for s in p.sources}
        self.optional = False
        self._find(query)
        self.bound: list[Bound] = []
        read = {i.table for i in self.instances}
        for p in policies:
            if p.sink is not None or any(d.table.upper() != "_OUTPUT_" for d in p.dimensions):
                raise UnsupportedPlan("SQL text", f"policy {p.name}, which has a sink or dimensions")
            if any(s.table.lower() not in read and not s.required for s in p.sources):
                continue
            if any(s.table.lower() not in read for s in p.sources):
                b = Bound(p, ConstraintForm(E.Lit("false")), {})
                b.missing_required = True
                self.bound.append(b)
                continue
            form = analyze(p, schema_of)
            self.bound += [bind(p, form, w) for w in alias_assignments(p, self.instances)]
        self.comps, holistic = all_components(self.bound)
        for key, (c, _) in self.comps.items():
            if c.plus in ("set", "hll"):
                raise UnsupportedPlan("SQL text", f"aggregate {key}")
        if holistic:
            raise UnsupportedPlan("SQL text", f"aggregate {next(iter(holistic))}")
        self.next = 0
        self.made = 0

    def _find(self, q) -> None:
        if isinstance(q, UnionAll):
            self.optional = True
            for p in q.parts:
                self._find(p)
            return
        self.optional |= q.group_by == ()
        for s in q.sources:
            self.optional |= s.how == "left"
            if not isinstance(s.what, str):
                self._find(s.what)
            elif s.what.lower() in self.wanted:
                self.instances.append(Instance(len(self.instances), s.what.lower(), s.alias.lower(), tuple(self.schema_of(s.what))))

    def fresh(self) -> str:
        self.made += 1
        return f"tg_{self.made}"

    def leaf(self, tree: E.Node, alias: dict[int, str], here: dict[int, str]) -> str:
        """A component's value of one row, over the tables of this block."""

        def put(n: E.Node) -> E.Node:
            if isinstance(n, E.Call) and n.name == "tg_one":
                tests = [here[int(x.sql)] for x in n.args if here[int(x.sql)] != "1"]
                return E.Lit(f"case when {' and '.join(f'{t} = 1' for t in tests)} then 1 end") if tests else E.Lit("1")
            if isinstance(n, E.Attr):
                return E.Attr((alias[int(n.parts[0][1:])], n.name))
            if isinstance(n, E.Lit):
                return E.Lit(n.sql[:-1]) if re.fullmatch(r"\d+L", n.sql) else n
            if isinstance(n, E.Call) and n.name == "if":
                return E.Case(((put(n.args[0]), put(n.args[1])),), put(n.args[2]))
            if isinstance(n, E.Call) and n.name == "double":
                return E.Op("*", (put(n.args[0]), E.Lit("1e0")))
            return E.rebuild(n, put)

        # double quotes name columns outside Spark; plain names need none
        return E.render(put(tree), lambda n: ".".join(n.parts) if isinstance(n, E.Attr) else None)

    def write(self, q) -> _Text:
        return self.union(q) if isinstance(q, UnionAll) else self.block(q)

    def union(self, q: UnionAll) -> _Text:
        parts = [self.write(p) for p in q.parts]
        out = _Text("", parts[0].names)
        out.cols = {k: self.fresh() for k in dict.fromkeys(k for p in parts for k in p.cols)}
        out.mult = self.fresh() if self.comps else None
        out.here = {i: self.fresh() for i in sorted({i for p in parts for i in p.here})}
        texts = []
        for p in parts:
            more = [f"{p.cols.get(k, 'NULL')} AS {c}" for k, c in out.cols.items()]
            more += [f"{p.mult} AS {out.mult}"] if out.mult else []
            more += [f"{p.here.get(i, '0')} AS {c}" for i, c in out.here.items()]
            texts.append(f"SELECT {', '.join([*p.names, *more])} FROM ({p.sql}) AS part")
        out.sql = " UNION ALL ".join(texts)
        return out

    def block(self, b: Block) -> _Text:
        text, alias, here, sides = "", {}, {}, []
        for n, s in enumerate(b.sources):
            cols: dict[str, str] = {}
            mult, of = None, frozenset()
            what = s.what
            if s.how == "semi":
                # one row a key, so that no row of the other side repeats
                what = Block(((f"{s.alias}.{s.key}", s.key),), (From(s.what, s.alias),), None, (f"{s.alias}.{s.key}",))
            if isinstance(what, str):
                body = what
                if what.lower() in self.wanted:
                    i, self.next = self.next, self.next + 1
                    alias[i], of = s.alias, frozenset({i})
                    here[i] = "1"
                    if s.how == "left":
                        body, here[i] = f"(SELECT *, 1 AS tg_here FROM {what})", f"coalesce({s.alias}.tg_here, 0)"
            else:
                inner = self.write(what)
                body, of = f"({inner.sql})", frozenset(inner.here)
                cols = {k: f"{s.alias}.{c}" for k, c in inner.cols.items()}
                mult = inner.mult and f"{s.alias}.{inner.mult}"
                if mult and s.how == "left":
                    mult = f"coalesce({mult}, 1)"
                here |= {i: f"coalesce({s.alias}.{c}, 0)" if s.how == "left" else f"{s.alias}.{c}" for i, c in inner.here.items()}
            sides.append((cols, mult, of))
            on = f"{s.on} = {s.alias}.{s.key}" if s.how == "semi" else s.on
            if n:
                text += f" {'LEFT JOIN' if s.how == 'left' else 'JOIN' if on else 'CROSS JOIN'} "
            text += f"{body} AS {s.alias}" + (f" ON {on}" if n and on else "")
        values: dict[str, str] = {}
        for key, (c, where) in self.comps.items():
            held = [n for n, (cols, _, _) in enumerate(sides) if key in cols]
            if held:
                value, own = sides[held[0]][0][key], {held[0]}
            elif where and where <= alias.keys():
                value, own = self.leaf(c.leaf, alias, here), {n for n, (_, _, of) in enumerate(sides) if of & where}
            elif where and where <= here.keys():
                raise UnsupportedPlan("SQL text", f"aggregate {key} over relations of which one is aggregated below")
            else:
                continue
            scale = [m for n, (_, m, _) in enumerate(sides) if m and n not in own] if c.sumlike else []
            values[key] = " * ".join([f"({value})", *scale]) if scale else value
        mult = " * ".join(m for _, m, _ in sides if m) or "1"
        out = _Text("", [n for _, n in b.items])
        more = []
        if self.bound:
            merged = b.group_by is not None
            for key, value in values.items():
                out.cols[key] = self.fresh()
                more.append(f"{self.comps[key][0].plus}({value}) AS {out.cols[key]}" if merged else f"{value} AS {out.cols[key]}")
            out.mult = self.fresh()
            more.append(f"sum({mult}) AS {out.mult}" if merged else f"{mult} AS {out.mult}")
            for i, h in here.items():
                out.here[i] = self.fresh()
                more.append(f"max({h}) AS {out.here[i]}" if merged else f"{h} AS {out.here[i]}")
        out.sql = f"SELECT {', '.join([*(f'{e} AS {n}' for e, n in b.items), *more])} FROM {text}"
        for word, part in (("WHERE", b.where), ("GROUP BY", ", ".join(b.group_by or ())), ("HAVING", b.having)):
            out.sql += f" {word} {part}" if part else ""
        out.sql += f" {b.tail}" if b.tail else ""
        return out

    def guarded(self, q) -> str:
        t = self.write(q)
        if not self.bound:
            return t.sql
        tests = []
        for b in self.bound:
            values = {k: _portable(finalize_sql(a, [t.cols[c.key] for c in components(a)])) for k, a in b.aggs.items()}

            def name(n):
                if isinstance(n, E.Slot):
                    return n.key[4:] if n.key.startswith("out:") else f"({values[n.key]})"
                return None

            ok = "false" if b.missing_required else f"coalesce({E.render(b.form.residual, name)}, false)"
            all_here = lambda ids: " AND ".join(f"coalesce({t.here[i]}, 0) = 1" for i in sorted(ids))
            if self.optional and b.required:
                ok = f"({all_here(b.required)} AND {ok})"
            if self.optional and b.cover:
                ok = f"(NOT ({all_here(b.cover)}) OR {ok})"
            tests.append(ok)
        return f"SELECT {', '.join(t.names)} FROM ({t.sql}) AS guarded WHERE {' AND '.join(tests)}"


def write_sql(query: "Block | UnionAll", policies: list[FlowPolicy], schema_of: Callable[[str], list[str]]) -> str:
    """Portable text of a query of nested blocks, left and semi joins and unions under policies
    whose violating rows are removed. Without policies: the query's own text."""
    return _Writer(query, policies, schema_of).guarded(query)
