"""Provenance baseline, row-replicating: every output row is repeated once per derivation with
its source rows' attributes, the policies are tested over these groups, and the groups are
collapsed again. Exact for every aggregate, at the cost of materialising all derivations."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from typing import Sequence

from .. import expr as E
from ..algebra import direct_sql
from ..errors import NonMonotonePlan, UnsupportedPlan
from ..plan import Bound, QueryPlan, instances_of
from .common import Annotated, dimension_column, join_dimensions, keyed_dimensions, strip_one


@dataclass
class Wide:
    plan: object
    #: (instance, attribute) to column.
    raw: dict[tuple, str] = field(default_factory=dict)
    #: Instance to the column of its row id (null where the row is padding).
    rid: dict[int, str] = field(default_factory=dict)
    #: Columns that identify the output row.
    gid: list[str] = field(default_factory=list)

    @property
    def extra(self) -> list[str]:
        return list(dict.fromkeys([*self.raw.values(), *self.rid.values(), *self.gid]))


class Widener:
    name = "replay_rows"

    def __init__(self, query: QueryPlan, bound: Sequence[Bound], prune: bool = True):
        self.q, self.b, self.bound, self.prune = query, query.bridge, bound, prune
        self.dims = keyed_dimensions(bound)
        self.count = 0
        self.needs: dict[int, set] = {}
        for bd in bound:
            for agg in bd.aggs.values():
                for a in agg.args:
                    for x in E.attrs(a):
                        if x.parts[0].startswith("d:"):
                            self.needs.setdefault(self.dims[x.parts[0][2:]][0], set()).add(x.parts[0] + "." + x.name)
                        else:
                            self.needs.setdefault(int(x.parts[0][1:]), set()).add(x.name)

    def carry(self, w: Wide) -> list:
        return [self.b.attr(w.plan, n) for n in w.extra]

    def base(self, w: Wide) -> list:
        own = set(w.extra)
        return [a for a in self.b.output(w.plan) if a.name() not in own]

    def visit(self, node) -> Wide:
        if self.q.instance_table(node):
            return self.leaf(node)
        kind = self.b.kind(node)
        rule = getattr(self, f"on_{kind}", None)
        if rule is not None:
            return rule(node)
        kids = self.b.children(node)
        if not kids:
            return self.plain(node)
        if kind in ("GlobalLimit", "LocalLimit", "Offset", "Tail", "Sample"):
            raise UnsupportedPlan(self.name, "LIMIT below the guard" if "Limit" in kind else kind)
        if kind == "Sort":
            return self.visit(kids[0])
        if kind in ("Filter", "ResolvedHint", "Repartition", "RepartitionByExpression", "Generate"):
            w = self.visit(kids[0])
            out = replace(w, plan=self.b.with_children(node, [w.plan]))
            if kind == "Generate":
                rid = self.b.fresh("r")
                out.plan = self.b.project(out.plan, [self.b.named("monotonically_increasing_id()", rid)])
                out.gid = out.gid + [rid]
            return out
        raise NonMonotonePlan(kind)

    def plain(self, node) -> Wide:
        """A relation that no policy names: only its row identity matters."""
        rid = self.b.fresh("r")
        return Wide(self.b.project(node, [self.b.named("monotonically_increasing_id()", rid)]), {}, {}, [rid])

    def leaf(self, node) -> Wide:
        i = self.count
        self.count += 1
        base = self.b.output(node)
        plan = join_dimensions(self.q, node, i, self.dims)
        rid = self.b.fresh("r")
        more, raw = [self.b.named("monotonically_increasing_id()", rid)], {}
        wanted = set(self.needs.get(i, ()))
        if not self.prune:
            wanted |= set(self.q.instances[i].columns)
        for attr in sorted(wanted):
            raw[i, attr] = self.b.fresh("v")
            more.append(self.b.named(dimension_column(attr) if attr.startswith("d:") else E.quote(attr), raw[i, attr]))
        return Wide(self.b.project(plan, more, base), raw, {i: rid}, [rid])

    def on_SubqueryAlias(self, node):
        return self.visit(self.b.children(node)[0])

    on_View = on_SubqueryAlias

    def on_Project(self, node):
        w = self.visit(self.b.children(node)[0])
        return replace(w, plan=self.b.project(w.plan, self.carry(w), self.b.items(node.projectList())))

    def on_Join(self, node):
        how = self.b.kind(node.joinType())
        l, r = (self.visit(c) for c in self.b.children(node))
        if how == "LeftSemi":
            cond = node.condition().get() if node.condition().isDefined() else None
            plan = self.b.join(l.plan, r.plan, "inner", cond)
            drop = {a.exprId().id() for a in self.base(r)}
            keep = [a for a in self.b.output(plan) if a.exprId().id() not in drop]
            return Wide(self.b.project(plan, [], keep), l.raw | r.raw, l.rid | r.rid, l.gid)
        if how not in ("Inner", "Cross", "LeftOuter", "RightOuter", "FullOuter"):
            raise NonMonotonePlan(how)
        return Wide(self.b.with_children(node, [l.plan, r.plan]), l.raw | r.raw, l.rid | r.rid, l.gid + r.gid)

    def regrouped(self, node, keys: list, outputs: list) -> Wide:
        """The base aggregate joined back with its own widened input."""
        child = self.b.children(node)[0]
        w = self.visit(child)
        names, other = [self.b.fresh("k") for _ in keys], [self.b.fresh("q") for _ in keys]
        base = self.b.aggregate(keys, outputs + [self.b.rename(k, n) for k, n in zip(keys, names)], child)
        inner = Wide(w.plan, w.raw, w.rid, [])
        own = [self.b.attr(w.plan, n) for n in inner.extra]
        wide = self.b.project(w.plan, own, [self.b.rename(k, n) for k, n in zip(keys, other)])
        cond = " and ".join(f"{x} <=> {y}" for x, y in zip(names, other))
        plan = self.b.join(base, wide, "left", self.b.sql(cond) if keys else self.b.sql("true"))
        drop = set(other)
        plan = self.b.project(plan, [], [a for a in self.b.output(plan) if a.name() not in drop])
        return Wide(plan, w.raw, w.rid, names)

    def on_Aggregate(self, node):
        return self.regrouped(node, self.b.items(node.groupingExpressions()), self.b.items(node.aggregateExpressions()))

    def on_Distinct(self, node):
        keys = self.b.output(self.b.children(node)[0])
        return self.regrouped(node, keys, list(keys))

    on_Deduplicate = on_Distinct

    def on_Union(self, node):
        kids = [self.visit(c) for c in self.b.children(node)]
        types = {}
        for k in kids:
            for at, col in [*k.raw.items(), *k.rid.items()]:
                types[at] = self.b.attr(k.plan, col).dataType().sql()
        names = {at: self.b.fresh("v") for at in types}
        gid = self.b.fresh("g")
        plans = []
        for n, k in enumerate(kids):
            have = {**k.raw, **k.rid}
            more = [self.b.named(f"cast({have.get(at, 'null')} as {types[at]})", names[at]) for at in types]
            ids = ", ".join(f"coalesce(cast({g} as string), '~')" for g in k.gid)
            more.append(self.b.named(f"concat_ws('|', '{n}'{', ' + ids if ids else ''})", gid))
            plans.append(self.b.project(k.plan, more, self.base(k)))
        return Wide(self.b.with_children(node, plans), {at: n for at, n in names.items() if isinstance(at, tuple)}, {at: n for at, n in names.items() if isinstance(at, int)}, [gid])

    def on_Expand(self, node):
        w = self.visit(self.b.children(node)[0])
        own = self.carry(w)
        rows = [self.b.seq(self.b.items(r) + own) for r in self.b.items(node.projections())]
        plan = self.b.resolve(self.b.logical.Expand(self.b.seq(rows), self.b.seq(self.b.items(node.output()) + own), w.plan))
        return replace(w, plan=plan)


def bag_values(query: QueryPlan, bound: Sequence[Bound], w, dims) -> tuple[list, list[dict[str, str]], list]:
    """Aggregations over the rows of each output's bag: named expressions, and each policy's
    values and presence tests in their terms."""
    b = query.bridge
    more, values, present = [], [], []
    by_key: dict[str, str] = {}
    where = {k: v[0] for k, v in dims.items()}

    def name(n):
        if isinstance(n, E.Attr):
            at = (where[n.parts[0][2:]], n.parts[0] + "." + n.name) if n.parts[0].startswith("d:") else (int(n.parts[0][1:]), n.name)
            return w.raw[at]
        return None

    def agg(text: str) -> str:
        if text not in by_key:
            by_key[text] = b.fresh("b")
            more.append(b.named(text, by_key[text]))
        return by_key[text]

    for bd in bound:
        own = {}
        for key, a in bd.aggs.items():
            ids = instances_of(a, where)
            args = [E.render(strip_one(x), name) for x in a.args]
            cover = " and ".join(f"{w.rid[i]} is not null" for i in sorted(ids))
            if ids:
                # constants (a percentage, say) stay as they are
                args = [f"case when {cover} then {text} end" if E.attrs(x) or strip_one(x) != x else text for x, text in zip(a.args, args)]
            own[key] = agg(direct_sql(a, args))
        values.append(own)

        agg_now = {i: agg(f"coalesce(bool_or({w.rid[i]} is not null), false)") for i in sorted(bd.needs)}
        present.append(lambda ids, m=agg_now: " and ".join(m[i] for i in sorted(ids)) or "true")
    return more, values, present


def collapse(query: QueryPlan, w: Wide, base: list, bound, dims) -> Annotated:
    """Groups the derivations of each output row, tests them, and keeps one row."""
    b = query.bridge
    more, values, present = bag_values(query, bound, w, dims)
    names = [b.fresh("o") for _ in base]
    firsts = [b.expression_first(x, n) for x, n in zip(base, names)]
    keys = [b.attr(w.plan, g) for g in dict.fromkeys(w.gid)]
    plan = b.aggregate(keys, firsts + more, w.plan)
    output = [b.rename(b.attr(plan, n), x.name()) for n, x in zip(names, base)]
    hidden = [a for a in b.output(plan) if a.name() not in set(names)]
    plan = b.project(plan, hidden, output)
    return Annotated(query, plan, b.output(plan)[: len(base)], values, None, present)


def replay_rows(query: QueryPlan, bound: Sequence[Bound], prune: bool = True) -> Annotated:
    query.check_monotone()
    query.check_deterministic()
    limits, plan = [], query.plan
    b = query.bridge
    while b.kind(plan) in ("GlobalLimit", "LocalLimit", "Offset", "Sort"):
        limits.append(plan)
        plan = b.children(plan)[0]
    wide = Widener(query, bound, prune)
    w = wide.visit(plan)
    if any(b.kind(x) != "Sort" for x in limits):
        # the limited base rows keep only their own derivations: rejoined on the output id
        w = _limited(wide, w, limits)
    return collapse(query, w, wide.base(w), bound, wide.dims)


def _limited(wide: Widener, w: Wide, limits: list) -> Wide:
    b = wide.b
    base = wide.base(w)
    keys = [b.attr(w.plan, g) for g in dict.fromkeys(w.gid)]
    names = [b.fresh("l") for _ in keys]
    # one row for each output id, sorted and limited as the query says
    one = b.aggregate([*base, *keys], [*base, *[b.rename(k, n) for k, n in zip(keys, names)]], w.plan)
    for node in reversed(limits):
        one = b.with_children(node, [one])
    one = b.project(one, [], [b.attr(one, n) for n in names])
    cond = " and ".join(f"{k.name()} <=> {n}" for k, n in zip(keys, names)) or "true"
    return replace(w, plan=b.join(w.plan, one, "leftsemi", b.sql(cond)))
