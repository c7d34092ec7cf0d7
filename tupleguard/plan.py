"""Queries as analyzed Catalyst plans: relation instances, monotonicity, binding of policies."""

from __future__ import annotations

import itertools
import os
from dataclasses import dataclass, field
from typing import Iterable, Sequence

from py4j.protocol import Py4JError
from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession

from . import constraint as C
from . import expr as E
from .algebra import Agg, components
from .catalyst import Bridge
from .errors import NonDeterministicPlan, NonMonotonePlan, ReservedName, UnsupportedPlan
from .policy import RESERVED, FlowPolicy

_REJECT = {"Except": "EXCEPT", "UnionLoop": "recursion", "Window": "window functions", "Pivot": "pivot"}
_OPAQUE = {"LogicalRDD", "MapInPandas", "MapInArrow", "FlatMapGroupsInPandas", "FlatMapGroupsInArrow", "ExternalRDD", "MapPartitions", "FlatMapCoGroupsInPandas"}


@dataclass(frozen=True)
class Instance:
    """One occurrence of a relation in a query."""

    id: int
    table: str
    alias: str
    columns: tuple[str, ...]


@dataclass
class Bound:
    """A policy with its aliases bound to instances, and its aggregates over ``i<id>`` names."""

    policy: FlowPolicy
    form: C.ConstraintForm
    assignment: dict[str, int]
    aggs: dict[str, Agg] = field(default_factory=dict)
    missing_required: bool = False

    @property
    def needs(self) -> frozenset:
        return frozenset(self.assignment.values())

    @property
    def cover(self) -> frozenset:
        """The instances whose presence makes it applicable (required sources apply always)."""
        req = {s.name.lower() for s in self.policy.required}
        return frozenset(i for a, i in self.assignment.items() if a not in req)

    @property
    def required(self) -> frozenset:
        req = {s.name.lower() for s in self.policy.required}
        return frozenset(i for a, i in self.assignment.items() if a in req)


class QueryPlan:
    def __init__(self, df: DataFrame, tables: Iterable[str] = ()):
        self.df = df
        self.spark: SparkSession = df.sparkSession
        self.bridge = Bridge(self.spark)
        for c in df.columns:
            if c.lower().startswith(RESERVED):
                raise ReservedName(c)
        self.plan = self._semi_joins_down(self.bridge.analyzed(df))
        self.wanted = {t.lower().rsplit(".", 1)[-1] for t in tables}
        self._places = self._locations()
        self.instances: list[Instance] = []
        self._names: dict[str, tuple] = {}
        self._tables: dict[str, tuple | None] = {}
        self._find(self.plan)
        #: Policy tables that only subquery expressions read.
        self.hidden: set[str] = set()
        if self.wanted:
            for sub in self.bridge.items(self.plan.subqueriesAll()):
                self._look_inside(sub)

    def _semi_joins_down(self, plan):
        """Semi joins at the lowest place that shows their left columns, as the optimizer would
        put them: there an annotated subquery still reduces what stands above."""
        b = self.bridge
        if "LeftSemi" not in plan.toString():
            return plan

        def sink(node, right, semi, refs: set):
            kids = b.children(node)
            if b.kind(node) == "Filter" and node.condition().deterministic():
                return node.withNewChildren(b.seq([sink(kids[0], right, semi, refs)]))
            if b.kind(node) == "Join" and b.kind(node.joinType()) in ("Inner", "Cross"):
                for i, k in enumerate(kids):
                    if refs and refs <= {a.exprId().id() for a in b.output(k)}:
                        return node.withNewChildren(b.seq([sink(x, right, semi, refs) if i == j else x for j, x in enumerate(kids)]))
            return semi.withNewChildren(b.seq([node, right]))

        def walk(node):
            kids = b.children(node)
            new = [walk(k) for k in kids]
            if any(x is not y for x, y in zip(kids, new)):
                node = node.withNewChildren(b.seq(new))
            if b.kind(node) == "Project":
                # what decorrelation leaves behind: all columns, as they are
                listed = b.items(node.projectList())
                if all(b.kind(e) == "AttributeReference" for e in listed) and [e.exprId().id() for e in listed] == [a.exprId().id() for a in b.output(new[0])]:
                    return new[0]
            if b.kind(node) == "Join" and b.kind(node.joinType()) == "LeftSemi" and node.condition().isDefined():
                left, right = b.children(node)
                if b.kind(left) in ("Filter", "Join"):
                    own = {a.exprId().id() for a in b.output(left)}
                    return sink(left, right, node, b.ids(node.condition().get()) & own)
            return node

        return walk(plan)

    # -- instances
    def _locations(self) -> dict[str, str]:
        """Places of the files under the policies' tables: other names of them are found too."""
        out = {}
        catalog = self.bridge.session.sessionState().catalog()
        for t in self.wanted:
            try:
                view = catalog.getTempView(t)
                plan = view.get().child() if view.isDefined() else self.spark.table(t)._jdf.queryExecution().analyzed()
            except AnalysisException:
                continue
            place = self._place(self._read_names(plan)[2])
            if place:
                out[place] = t
        return out

    def _place(self, node) -> str | None:
        if self.bridge.kind(node) != "LogicalRelation":
            return None
        try:
            return node.relation().location().rootPaths().mkString("|")
        except Py4JError:  # relations without files have no place
            return None

    def names(self, node) -> tuple[str | None, list[str], object]:
        """The outermost alias, the catalog's names (a query cannot choose these), and the node
        below all names."""
        at = node._target_id
        if at not in self._names:
            self._names[at] = self._read_names(node)
        return self._names[at]

    def _read_names(self, node) -> tuple[str | None, list[str], object]:
        b, alias, out = self.bridge, None, []
        while b.kind(node) in ("SubqueryAlias", "View"):
            if b.kind(node) == "View":
                out.append(node.desc().identifier().table().lower())
            elif alias is None:
                alias = node.alias().lower()
            node = b.children(node)[0]
        if b.kind(node) == "LogicalRelation":
            if node.catalogTable().isDefined():
                out.append(node.catalogTable().get().identifier().table().lower())
            else:
                place = self._place(node)
                if place:
                    out.append(os.path.basename(place.split("|")[0].rstrip("/")).split(".")[0].lower())
        return alias or (out[0] if out else None), out, node

    def instance_table(self, node) -> tuple[str, str] | None:
        """``(table, alias)`` if the node is an occurrence of a policy's table: a relation that
        the catalog (or the files' place) names so. Aliases of the query's text never count."""
        at = node._target_id
        if at not in self._tables:
            alias, names, inner = self.names(node)
            found = list(dict.fromkeys(n for n in names if n in self.wanted))
            place = self._place(inner) if self._places else None
            if place in self._places and self._places[place] not in found:
                found.append(self._places[place])
            if len(found) > 1:
                raise UnsupportedPlan("binding", f"{' and '.join(found)}, which are one relation")
            self._tables[at] = (found[0], alias or found[0]) if found else None
        return self._tables[at]

    def _find(self, node) -> None:
        got = self.instance_table(node)
        if got:
            below = self.names(node)[2]
            if self._first_below(below, got[0]):
                raise UnsupportedPlan("binding", f"{got[0]}, a view over a policy's table")
            cols = tuple(a.name() for a in self.bridge.output(node))
            self.instances.append(Instance(len(self.instances), got[0], got[1], cols))
            return
        for c in self.bridge.children(node):
            self._find(c)

    def _first_below(self, node, own: str) -> str | None:
        """Another policy's table below the node of a view."""
        if len(self.wanted) < 2:
            return None
        got = self.instance_table(node)
        if got and got[0] != own:
            return got[0]
        return next((x for c in self.bridge.children(node) if (x := self._first_below(c, own))), None)

    def _look_inside(self, node) -> None:
        got = self.instance_table(node)
        if got:
            self.hidden.add(got[0])
        for c in self.bridge.children(node):
            self._look_inside(c)

    def read_ids(self) -> set:
        """Ids of the columns that some operator reads, or that the output shows."""
        b = self.bridge
        if not hasattr(self, "_read_ids"):
            self._read_ids = {a.exprId().id() for a in b.output(self.plan)}

            def look(node):
                self._read_ids.update(b.ids(node))
                if b.kind(node) in ("Union", "Distinct", "Deduplicate", "Intersect", "Except", "Expand"):
                    self._read_ids.update(a.exprId().id() for c in b.children(node) for a in b.output(c))
                if not self.instance_table(node):
                    for c in b.children(node):
                        look(c)

            look(self.plan)
        return self._read_ids

    def tables_read(self) -> set[str]:
        return {i.table for i in self.instances}

    # -- checks
    def check_monotone(self, left_only: bool = False, windows: bool = False) -> None:
        def look(node):
            if self.instance_table(node):
                return
            _, names, inner = self.names(node)
            if names and self.bridge.kind(inner) in ("LogicalRDD", "ExternalRDD"):
                return  # a named in-memory relation is a scan
            k = self.bridge.kind(node)
            if k in _REJECT and not (windows and k == "Window"):
                raise NonMonotonePlan(_REJECT[k])
            if k == "Join":
                how = self.bridge.kind(node.joinType())
                if how == "LeftAnti" and not left_only:
                    raise NonMonotonePlan("NOT EXISTS / NOT IN / anti join")
                if how == "ExistenceJoin":
                    raise NonMonotonePlan("EXISTS inside a disjunction")
            if k in _OPAQUE and self.wanted:
                raise NonMonotonePlan(f"{k} (its derivation is unknown)")
            if k == "Deduplicate" and node.keys().size() < len(self.bridge.output(node)):
                raise NonMonotonePlan("dropDuplicates on some columns")
            for c in self.bridge.children(node):
                look(c)

        look(self.plan)
        if self.bridge.scalar_subqueries(self.plan):
            raise NonMonotonePlan("scalar subqueries")

    def check_deterministic(self) -> None:
        def look(node) -> bool:
            return self.bridge.kind(node) == "Sample" or any(not e.deterministic() for e in self.bridge.items(node.expressions())) or any(look(c) for c in self.bridge.children(node))

        if look(self.plan):
            raise NonDeterministicPlan("the base query would run twice with unlike results")

    def has(self, *kinds: str) -> bool:
        return self.bridge._has(self.plan, kinds)

    def has_alternatives(self) -> bool:
        """Whether some output tuples derive from fewer relations than others: unions, outer joins,
        and aggregates without keys below joins and aggregates."""

        def look(node, below=False):
            k = self.bridge.kind(node)
            if k == "Union" or (k == "Join" and self.bridge.kind(node.joinType()) in ("LeftOuter", "RightOuter", "FullOuter")):
                return True
            if below and k == "Aggregate" and node.groupingExpressions().size() == 0:
                return True
            return any(look(c, below or k in ("Join", "Aggregate")) for c in self.bridge.children(node))

        return look(self.plan)

    def needs_mask(self) -> bool:
        """Whether applicability differs between output tuples: there are alternatives, or an
        aggregate without keys, whose one row may have no derivation at all."""

        def keyless(node):
            if self.bridge.kind(node) == "Aggregate" and node.groupingExpressions().size() == 0:
                return True
            return any(keyless(c) for c in self.bridge.children(node))

        return self.has_alternatives() or keyless(self.plan)


def alias_assignments(policy: FlowPolicy, instances: Sequence[Instance]) -> list[dict[str, int]]:
    """All ways to bind the policy's aliases to distinct instances of their tables."""
    by_table: dict[str, list[str]] = {}
    for s in policy.sources:
        by_table.setdefault(s.table.lower().rsplit(".", 1)[-1], []).append(s.name.lower())
    choices = []
    for table, aliases in by_table.items():
        here = [i.id for i in instances if i.table == table]
        choices.append([dict(zip(aliases, p)) for p in itertools.permutations(here, len(aliases))])
    return [dict(kv for part in combo for kv in part.items()) for combo in itertools.product(*choices)]


def bind(policy: FlowPolicy, form: C.ConstraintForm, assignment: dict[str, int]) -> Bound:
    def put(n: E.Node) -> E.Node:
        if isinstance(n, E.Attr) and len(n.parts) == 2:
            alias = n.parts[0]
            if alias in assignment:
                return E.Attr((f"i{assignment[alias]}", n.name))
            return E.Attr((f"d:{alias}", n.name))
        return E.rebuild(n, put)

    out = Bound(policy, form, assignment)
    cover = ",".join(map(str, sorted(assignment.values())))
    for key, agg in form.aggs.items():
        args = tuple(put(a) for a in agg.args)
        if not any(E.attrs(a) for a in args):
            # count(*) and the like: one for each monomial that covers all sources
            args = (E.Call("tg_one", tuple(E.Lit(x) for x in cover.split(",") if x)),)
        out.aggs[key] = Agg(agg.kind, args)
    return out


def instances_of(agg: Agg, dims: dict[str, int]) -> frozenset:
    """The instances that an aggregate's argument reads."""
    found = set()
    for a in agg.args:
        for n in E.walk(a):
            if isinstance(n, E.Attr):
                found.add(dims[n.parts[0][2:]] if n.parts[0].startswith("d:") else int(n.parts[0][1:]))
            elif isinstance(n, E.Call) and n.name == "tg_one":
                found.update(int(x.sql) for x in n.args)
    return frozenset(found)


def keyed_dimensions(bound: Sequence[Bound]) -> dict[str, tuple[int, object]]:
    """Dimension alias to the instance that its key equality names, and the dimension."""
    out = {}
    for b in bound:
        for d in b.policy.dimensions:
            if d.on:
                own = [a for a in E.attrs(E.parse(d.on)) if a.qualifier and a.qualifier.lower() in b.assignment]
                alias = own[0].qualifier.lower() if own else next(iter(b.assignment))
                out[d.name.lower()] = (b.assignment[alias], d)
    return out


def all_components(bound: Sequence[Bound]):
    """Distinct components of all policies with their instances; kinds without one are returned
    apart."""
    dims = {k: v[0] for k, v in keyed_dimensions(bound).items()}
    comps, holistic = {}, {}
    for b in bound:
        for agg in b.aggs.values():
            own = components(agg)
            where = instances_of(agg, dims)
            if not own:
                holistic[agg.key] = (agg, where)
            for c in own:
                comps[c.key] = (c, where)
    return comps, holistic
