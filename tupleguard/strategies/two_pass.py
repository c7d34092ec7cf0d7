"""Two-pass enforcement: the base query runs untouched; a second scan computes the policies'
aggregates per output key, partially aggregated below the final join, and is joined on the key.

Push-down reaches the final join only: nested aggregates below it are annotated as they stand.
Without an aggregate in the query the bag of a row is the row itself and the guard a filter."""

from __future__ import annotations

from dataclasses import replace
from typing import Sequence

from .. import expr as E
from ..algebra import direct_sql, finalize_sql, components, merge_sql
from ..errors import UnsupportedPlan
from ..plan import Bound, QueryPlan
from .common import Annotated, mask_present, policy_values, strip_one
from .inline import Annotator, inline

_THROUGH = {"Project", "Filter", "Sort", "GlobalLimit", "LocalLimit", "Offset", "SubqueryAlias", "View", "ResolvedHint"}


def final_aggregate(query: QueryPlan):
    """The topmost aggregate and the unary operators above it, outermost first."""
    b, node, path = query.bridge, query.plan, []
    while b.kind(node) in _THROUGH and not query.instance_table(node):
        path.append(node)
        node = b.children(node)[0]
    if b.kind(node) in ("Aggregate", "Distinct"):
        return node, path
    return None, path


def expose_keys(query: QueryPlan, node, path, keys: list, names: list[str]):
    """The base plan with the grouping keys as extra output columns."""
    b = query.bridge
    child = b.children(node)[0]
    named = [b.rename(k, n) for k, n in zip(keys, names)]
    outputs = b.items(node.aggregateExpressions()) if b.kind(node) == "Aggregate" else b.output(child)
    plan = b.aggregate(keys, outputs + named, child)
    for p in reversed(path):
        if b.kind(p) == "Project":
            plan = b.project(plan, [b.attr(plan, n) for n in names], b.items(p.projectList()))
        elif b.kind(p) not in ("SubqueryAlias", "View"):
            plan = b.with_children(p, [plan])
    return plan


def _needed_above(query: QueryPlan, child, keys: list):
    """The join right below the final aggregate, and the ids that are read above its sides."""
    b, need, node = query.bridge, set(), child
    for k in keys:
        need |= b.ids(k)
    while b.kind(node) in ("Project", "Filter", "SubqueryAlias", "View"):
        if query.instance_table(node):
            return None
        if b.kind(node) == "Filter":
            need |= b.ids(node.condition())
        if b.kind(node) == "Project":
            for e in b.items(node.projectList()):
                if b.kind(e) == "Alias":
                    need |= b.ids(e)
        node = b.children(node)[0]
    if b.kind(node) != "Join" or b.kind(node.joinType()) not in ("Inner", "Cross"):
        return None
    if node.condition().isDefined():
        need |= b.ids(node.condition().get())
    return node, need


class _SecondScan(Annotator):
    """Computes policy aggregates only: projections keep just what is read above."""

    def on_Project(self, node, up):
        st = self.visit(self.b.children(node)[0], up)
        if self.push is None or not self.pushed:
            return replace(st, plan=self.b.project(st.plan, self.carry(st), self.b.items(node.projectList())))
        have = {a.exprId().id() for a in self.b.output(st.plan)}
        kept = [e for e in self.b.items(node.projectList()) if self.b.ids(e) <= have]
        return replace(st, plan=self.b.project(st.plan, self.carry(st), kept))


def two_pass(query: QueryPlan, bound: Sequence[Bound], push: bool = True, left_only: bool = False) -> Annotated:
    query.check_monotone(left_only)
    node, path = final_aggregate(query)
    b = query.bridge
    if node is None:
        return inline(query, bound, left_only)
    query.check_deterministic()
    child = b.children(node)[0]
    keys = b.items(node.groupingExpressions()) if b.kind(node) == "Aggregate" else b.output(child)
    names = [b.fresh("k") for _ in keys]
    base = expose_keys(query, node, path, keys, names)
    an = _SecondScan(query, bound, left_only=left_only)
    if push and not an.holistic and not an.raw_needs:
        an.push = _needed_above(query, child, keys)
    st = an.visit(child, 1)
    other = [b.fresh("q") for _ in keys]
    more, cols, whole = [], {}, {}
    counted = set(st.counted)
    for key, col in st.cols.items():
        plus = an.comps[key][0].plus
        cols[key] = b.fresh("a")
        text = merge_sql(plus, col, key in st.single)
        if plus == "set" and key in st.single:
            text = f"count(distinct get({col}, 0))"
            counted.add(key)
        more.append(b.named(text, cols[key]))
    for key, (agg, where) in an.holistic.items():
        def name(n):
            if isinstance(n, E.Attr):
                at = (an.dims[n.parts[0][2:]][0], n.parts[0] + "." + n.name) if n.parts[0].startswith("d:") else (int(n.parts[0][1:]), n.name)
                if at not in st.raw:
                    raise UnsupportedPlan("two_pass", f"{agg.kind} over a nested aggregate")
                return st.raw[at]
            return None

        whole[key] = b.fresh("a")
        more.append(b.named(direct_sql(agg, [E.render(strip_one(a), name) for a in agg.args]), whole[key]))
    missing = [k for k in an.comps if k not in cols]
    if missing:
        raise UnsupportedPlan("two_pass", f"aggregate {missing[0]}")
    mask = None
    if st.mask:
        mask = tuple(b.fresh("m") for _ in st.mask)
        more += [b.named(f"bit_or({old})", new) for old, new in zip(st.mask, mask)]
    second = b.aggregate(keys, [b.rename(k, n) for k, n in zip(keys, other)] + more, st.plan)
    cond = " and ".join(f"{x} <=> {y}" for x, y in zip(names, other))
    plan = b.join(base, second, "left" if keys else "cross", b.sql(cond) if keys else None)
    hidden = set(names)
    output = [a for a in b.output(base) if a.name() not in hidden]
    values = policy_values(query, bound, cols, counted, whole)
    return Annotated(query, plan, output, values, mask, [mask_present(mask)] * len(bound))


__all__ = ["components", "final_aggregate", "finalize_sql", "two_pass"]
