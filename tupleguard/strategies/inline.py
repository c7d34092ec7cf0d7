"""Inline enforcement: constant-size annotations ride through the base query's own operators.

Leaves compute the components of the policies' aggregates; joins scale sum-like components by
the other side's multiplicity; aggregates merge components in the same node as the base
aggregates. No scan and no join is added, but where a semi join's subquery holds a policy
source: it becomes an aggregated inner join."""

from __future__ import annotations

from dataclasses import dataclass, field, replace
from typing import Sequence

from .. import expr as E
from ..algebra import components, merge_sql, set_caps
from ..errors import NonMonotonePlan, UnsupportedPlan
from ..plan import Bound, QueryPlan
from .common import Annotated, all_components, dimension_column, join_dimensions, keyed_dimensions, leaf_name, mask_bits, mask_present, mask_words, policy_values, strip_one


@dataclass
class State:
    plan: object
    #: Component key to column.
    cols: dict[str, str] = field(default_factory=dict)
    #: (instance, attribute) to column, carried for arguments that span instances.
    raw: dict[tuple, str] = field(default_factory=dict)
    mult: str | None = None
    #: The words of the lineage mask.
    mask: tuple[str, ...] | None = None
    present: frozenset = frozenset()
    #: Set components that are still single values, and those that are already counts.
    single: frozenset = frozenset()
    counted: frozenset = frozenset()

    @property
    def extra(self) -> list[str]:
        return [*self.cols.values(), *self.raw.values(), *([self.mult] if self.mult else []), *(self.mask or ())]


class _Lost(UnsupportedPlan):
    """A value that an argument over several relations reads does not reach the operator where
    the relations meet."""

    def __init__(self, op: str):
        super().__init__("inline", op)


class Annotator:
    def __init__(self, query: QueryPlan, bound: Sequence[Bound], mask: bool | None = None, left_only: bool = False):
        self.q, self.b, self.bound = query, query.bridge, bound
        self.comps, self.holistic = all_components(bound)
        self.dims = keyed_dimensions(bound)
        self.mask = query.needs_mask() if mask is None else mask
        self.words = mask_words(query)
        self.left_only = left_only
        #: Elements that a set needs at most, over all policies that read it.
        self.caps: dict[str, int | None] = {}
        for bd in bound:
            sets = {key: components(agg)[0].key for key, agg in bd.aggs.items() if agg.kind == "distinct"}
            for key, cap in set_caps(bd.form.residual, sets).items():
                old = self.caps.get(key, 0)
                self.caps[key] = None if cap is None or old is None else max(old, cap)
        self.sumlike = any(c.sumlike for c, _ in self.comps.values())
        self.count = 0
        self.raw_needs: dict[int, set] = {}
        for c, where in self.comps.values():
            if len(where) > 1:
                self._need_raw(c.leaf)
        for agg, _ in self.holistic.values():
            for a in agg.args:
                self._need_raw(a)
        #: A join below which a side is pre-aggregated: (node, expression ids needed above).
        self.push: tuple | None = None
        self.pushed = False

    def _need_raw(self, tree: E.Node) -> None:
        for a in E.attrs(tree):
            if not a.parts[0].startswith("d:"):
                self.raw_needs.setdefault(int(a.parts[0][1:]), set()).add(a.name)
            else:
                self.raw_needs.setdefault(self.dims[a.parts[0][2:]][0], set()).add(a.parts[0] + "." + a.name)

    # -- helpers
    def carry(self, st: State) -> list:
        return [self.b.attr(st.plan, n) for n in st.extra]

    def add(self, st: State, sqls: dict[str, str]) -> State:
        """Projects more columns on top: name to SQL."""
        if not sqls:
            return st
        return replace(st, plan=self.b.project(st.plan, [self.b.named(s, n) for n, s in sqls.items()]))

    def base(self, st: State) -> list:
        own = set(st.extra)
        return [a for a in self.b.output(st.plan) if a.name() not in own]

    def fresh_mask(self) -> tuple[str, ...]:
        return tuple(self.b.fresh("m") for _ in range(self.words))

    # -- dispatch
    def visit(self, node, aggregates_above: int = 0) -> State:
        if self.q.instance_table(node):
            return self.leaf(node)
        kind = self.b.kind(node)
        rule = getattr(self, f"on_{kind}", None)
        if rule is None:
            kids = self.b.children(node)
            if not kids:
                return State(node)
            if kind in ("Sort", "GlobalLimit", "LocalLimit", "Offset", "Filter", "Generate", "Sample", "Repartition", "RepartitionByExpression", "RebalancePartitions", "ResolvedHint", "Tail", "CollectMetrics", "EventTimeWatermark", "UnresolvedHint"):
                st = self.visit(kids[0], aggregates_above)
                return replace(st, plan=self.b.with_children(node, [st.plan]))
            st = self.visit(kids[0], aggregates_above) if len(kids) == 1 else None
            if st is not None and not st.present:
                return replace(st, plan=self.b.with_children(node, [st.plan]))
            raise NonMonotonePlan(kind)
        return rule(node, aggregates_above)

    def leaf(self, node) -> State:
        i = self.count
        self.count += 1
        base = self.b.output(node)
        plan = join_dimensions(self.q, node, i, self.dims)
        name = leaf_name(self.q, self.dims)
        cols, raw, more, single = {}, {}, [], set()
        for key, (c, where) in self.comps.items():
            if where == {i}:
                cols[key] = self.b.fresh("a")
                more.append(self.b.named(E.render(strip_one(c.leaf), name), cols[key]))
                if c.plus in ("set", "hll"):
                    single.add(key)
        for attr in sorted(self.raw_needs.get(i, ())):
            raw[i, attr] = self.b.fresh("v")
            text = dimension_column(attr) if attr.startswith("d:") else E.quote(attr)
            more.append(self.b.named(text, raw[i, attr]))
        mask = None
        if self.mask:
            mask = self.fresh_mask()
            more += [self.b.named(bits, m) for bits, m in zip(mask_bits(i, self.words), mask)]
        plan = self.b.project(plan, more, base) if more or plan is not node else node
        return State(plan, cols, raw, None, mask, frozenset({i}), frozenset(single))

    def on_SubqueryAlias(self, node, up):
        return self.visit(self.b.children(node)[0], up)

    on_View = on_SubqueryAlias

    def on_Project(self, node, up):
        st = self.visit(self.b.children(node)[0], up)
        return replace(st, plan=self.b.project(st.plan, self.carry(st), self.b.items(node.projectList())))

    def on_Expand(self, node, up):
        st = self.visit(self.b.children(node)[0], up)
        own = self.carry(st)
        rows = [self.b.seq(self.b.items(r) + own) for r in self.b.items(node.projections())]
        plan = self.b.logical.Expand(self.b.seq(rows), self.b.seq(self.b.items(node.output()) + own), st.plan)
        return replace(st, plan=self.b.resolve(plan))

    def on_Join(self, node, up):
        how = self.b.kind(node.joinType())
        left, right = self.b.children(node)
        if how in ("LeftSemi", "LeftAnti"):
            return self.semi(node, left, right, up, how)
        if how not in ("Inner", "Cross", "LeftOuter", "RightOuter", "FullOuter"):
            raise NonMonotonePlan(how)
        before = self.count
        a, b = self.visit(left, up), self.visit(right, up)
        if self.push is not None and node.equals(self.push[0]) and how in ("Inner", "Cross"):
            a, b = self.push_side(a), self.push_side(b)
        try:
            return self.joined(self.b.with_children(node, [a.plan, b.plan]), a, b, how)
        except _Lost:
            return self.replayed(node, before)

    def replayed(self, node, first: int) -> State:
        """The subplan as one source: its derivations are replayed and merged to one row each,
        with all components over its relations. What stands above goes on inline."""
        from .replay_rows import Widener

        self.q.check_deterministic()
        b = self.b
        wide = Widener(self.q, self.bound)
        wide.count = first
        w = wide.visit(node)
        self.count = wide.count
        present = frozenset(range(first, self.count))

        def name(n):
            if isinstance(n, E.Attr):
                return w.raw[(self.dims[n.parts[0][2:]][0], n.parts[0] + "." + n.name) if n.parts[0].startswith("d:") else (int(n.parts[0][1:]), n.name)]
            return None

        cols, more = {}, []
        for key, (c, where) in self.comps.items():
            if where and where <= present:
                cover = " and ".join(f"{w.rid[i]} is not null" for i in sorted(where))
                cols[key] = b.fresh("a")
                more.append(b.named(merge_sql(c.plus, f"case when {cover} then {E.render(strip_one(c.leaf), name)} end", True, self.caps.get(key)), cols[key]))
        mult = mask = None
        if self.sumlike:
            mult = b.fresh("x")
            more.append(b.named("count(1)", mult))
        if self.mask:
            mask = self.fresh_mask()
            for word, m in enumerate(mask):
                own = [f"max(case when {w.rid[i]} is not null then {mask_bits(i, self.words)[word]} else 0L end)" for i in sorted(present)]
                more.append(b.named(" + ".join(own), m))
        keys = [b.attr(w.plan, g) for g in dict.fromkeys(w.gid)]
        return State(self.once(w.plan, keys, wide.base(w), more), cols, {}, mult, mask, present)

    def once(self, plan, keys: list, base: list, more: list):
        """One row for each group of rows that repeat ``base``, whose columns keep their identities."""
        names = [self.b.fresh("o") for _ in base]
        made = self.b.aggregate(keys, [self.b.expression_first(x, n) for x, n in zip(base, names)] + more, plan)
        own = {a.name(): a for a in self.b.output(made)}
        kept = [a for a in self.b.output(made)[len(names) :]]
        return self.b.project(made, kept, [self.b.same(own[n], x) for n, x in zip(names, base)])

    def joined(self, plan, a: State, b: State, how: str) -> State:
        st = State(plan, a.cols | b.cols, a.raw | b.raw, None, None, a.present | b.present, a.single | b.single, a.counted | b.counted)
        outer_left, outer_right = how in ("RightOuter", "FullOuter"), how in ("LeftOuter", "FullOuter")
        ma = a.mult and (f"coalesce({a.mult}, 1L)" if outer_left else a.mult)
        mb = b.mult and (f"coalesce({b.mult}, 1L)" if outer_right else b.mult)
        new, cols = {}, dict(st.cols)
        for side, factor in ((a, mb), (b, ma)):
            if factor is None:
                continue
            for key, col in side.cols.items():
                if self.comps[key][0].sumlike:
                    cols[key] = self.b.fresh("a")
                    new[cols[key]] = f"{col} * {factor}"
        mult = None
        if ma or mb:
            mult = self.b.fresh("x")
            new[mult] = " * ".join(x for x in (ma, mb) if x)
        mask = None
        if a.mask or b.mask:
            mask = self.fresh_mask()
            for w, m in enumerate(mask):
                new[m] = " | ".join(f"coalesce({side[w]}, 0L)" for side in (a.mask, b.mask) if side)
        st = self.add(st, new)
        st.cols, st.mult, st.mask = cols, mult, mask
        return self.spanning(self.drop_stale(st) if new else st)

    def drop_stale(self, st: State) -> State:
        """Forgets columns that were replaced."""
        keep = set(st.extra)
        base = [a for a in self.b.output(st.plan) if not a.name().startswith("__tg_a") and not a.name().startswith("__tg_x") and not a.name().startswith("__tg_m") or a.name() in keep]
        if len(base) == len(self.b.output(st.plan)):
            return st
        return replace(st, plan=self.b.project(st.plan, [], base))

    def spanning(self, st: State) -> State:
        """Components over several instances, computed where all of them first meet."""
        new, cols = {}, {}
        for key, (c, where) in self.comps.items():
            if len(where) < 2 or key in st.cols or not where <= st.present:
                continue

            def name(n):
                if isinstance(n, E.Attr):
                    at = (self.dims[n.parts[0][2:]][0], n.parts[0] + "." + n.name) if n.parts[0].startswith("d:") else (int(n.parts[0][1:]), n.name)
                    if at not in st.raw:
                        raise _Lost(f"an argument over {E.render(n)}, which was aggregated away below")
                    return st.raw[at]
                return None

            text = E.render(strip_one(c.leaf), name)
            if st.mask:
                text = f"case when {mask_present(st.mask)(where)} then {text} end"
            if c.sumlike and st.mult:
                text = f"({text}) * {st.mult}"
            cols[key] = self.b.fresh("a")
            new[cols[key]] = text
            if c.plus in ("set", "hll"):
                st.single = st.single | {key}
        st = self.add(st, new)
        st.cols = st.cols | cols
        return st

    def push_side(self, st: State) -> State:
        """The partial aggregation of a join's side by what is needed above it."""
        if not st.cols or st.raw:
            return st
        needed = self.push[1]
        keys = [a for a in self.base(st) if a.exprId().id() in needed]
        self.pushed = True
        return self.grouped(st, keys, list(keys), 1)

    def grouped(self, st: State, keys: list, outputs: list, up: int) -> State:
        """Merges components under the given grouping; raw values end here."""
        cols, more, counted = {}, [], set(st.counted)
        for key, col in st.cols.items():
            plus = self.comps[key][0].plus
            cols[key] = self.b.fresh("a")
            text = merge_sql(plus, col, key in st.single, self.caps.get(key))
            if plus == "set" and up == 0 and key in st.single:
                text = f"count(distinct get({col}, 0))"
                counted.add(key)
            more.append(self.b.named(text, cols[key]))
        mult = mask = None
        if self.sumlike and up >= 0:
            mult = self.b.fresh("x")
            more.append(self.b.named(f"sum({st.mult})" if st.mult else "count(1)", mult))
        if st.mask:
            mask = self.fresh_mask()
            more += [self.b.named(f"bit_or({old})", m) for old, m in zip(st.mask, mask)]
        plan = self.b.aggregate(keys, outputs + more, st.plan)
        return State(plan, cols, {}, mult, mask, st.present, frozenset(), frozenset(counted))

    def on_Aggregate(self, node, up):
        st = self.visit(self.b.children(node)[0], up + 1)
        if not st.present and not self.sumlike:
            return State(self.b.with_children(node, [st.plan]))
        if self.holistic and any(w & st.present for _, w in self.holistic.values()):
            raise UnsupportedPlan("inline", "an aggregate without constant-size annotation")
        return self.grouped(st, self.b.items(node.groupingExpressions()), self.b.items(node.aggregateExpressions()), up)

    def on_Window(self, node, up):
        """Allowed on demand only (``windows=True``): a row derives from itself and the rows of its
        frame, where all functions share a frame that starts with the partition and reaches the
        row; else from its whole partition, which holds every frame. Functions over unlike
        partitions are refused."""
        # functions of unlike orders stand in nodes on top of each other
        chain = [node]
        while self.b.kind(self.b.children(chain[-1])[0]) == "Window":
            chain.append(self.b.children(chain[-1])[0])
        st = self.visit(self.b.children(chain[-1])[0], up + 1)
        if st.raw:
            raise UnsupportedPlan("inline", "an argument over several relations across a window")
        if self.holistic and any(w & st.present for _, w in self.holistic.values()):
            raise UnsupportedPlan("inline", "an aggregate without constant-size annotation over a window")
        plan, cols, more = st.plan, {}, []
        mult = mask = None
        if st.present or st.mult:
            spec = self.window_spec(chain)
            make, none = self.b.jvm.org.apache.spark.sql.catalyst.expressions, self.b.jvm.scala.Option.apply(None)

            own = set(st.extra)

            def over(text: str, name: str) -> str:
                more.append(make.Alias(make.WindowExpression(self.b.sql(text), spec), name, make.NamedExpression.newExprId(), self.b.seq([]), none, self.b.seq([])))
                return name

            sets = []
            for key, col in st.cols.items():
                plus = self.comps[key][0].plus
                cols[key] = self.b.fresh("a")
                if plus == "set":
                    # only a bare aggregate stands over a window
                    gathered = over(f"collect_set({col})", self.b.fresh("s"))
                    own.add(gathered)
                    sets.append(self.b.named(f"array_distinct(flatten({gathered}))", cols[key]))
                else:
                    over(merge_sql(plus, col, key in st.single), cols[key])
            mult = over(f"sum({st.mult})" if st.mult else "count(1)", self.b.fresh("x")) if self.sumlike else None
            mask = tuple(over(f"bit_or({m})", self.b.fresh("m")) for m in st.mask) if st.mask else None
            plan = self.b.project(plan, more)
            plan = self.b.project(plan, sets, [a for a in self.b.output(plan) if a.name() not in own])
        # the query's own functions stay as they are, above
        for n in reversed(chain):
            plan = self.b.with_children(n, [plan])
        return State(plan, cols, {}, mult, mask, st.present)

    def window_spec(self, chain: list):
        """The partition, order and frame by which the annotations are merged."""
        b, make = self.b, self.b.jvm.org.apache.spark.sql.catalyst.expressions
        specs = {}

        def look(e):
            if b.kind(e) == "WindowExpression":
                specs[e.windowSpec().toString()] = e.windowSpec()
            for c in b.items(e.children()):
                look(c)

        for n in chain:
            for e in b.items(n.windowExpressions()):
                look(e)
        if len({n.partitionSpec().toString() for n in chain}) > 1:
            raise UnsupportedPlan("inline", "window functions over unlike partitions")
        if len(specs) == 1:
            (spec,) = specs.values()
            frame = spec.frameSpecification()
            if b.kind(frame) == "SpecifiedWindowFrame" and b.kind(frame.lower()) == "UnboundedPreceding" and b.kind(frame.upper()) in ("CurrentRow", "UnboundedFollowing"):
                return spec
        whole = make.__getattr__("UnspecifiedFrame$").__getattr__("MODULE$")
        return make.WindowSpecDefinition(chain[0].partitionSpec(), b.seq([]), whole)

    def on_Distinct(self, node, up):
        st = self.visit(self.b.children(node)[0], up + 1)
        keys = self.base(st)
        return self.grouped(st, keys, list(keys), up)

    def on_Deduplicate(self, node, up):
        return self.on_Distinct(node, up)

    def on_Union(self, node, up):
        kids = [self.visit(c, up + 1) for c in self.b.children(node)]
        if not any(k.present or k.mult for k in kids):
            return State(self.b.with_children(node, [k.plan for k in kids]))
        if any(k.raw for k in kids):
            raise UnsupportedPlan("inline", "an argument over several relations across a union")
        types, keys = {}, list(dict.fromkeys(key for k in kids for key in k.cols))
        for k in kids:
            for key, col in k.cols.items():
                if self.comps[key][0].plus == "hll" and (key in k.single) != all(key in o.single for o in kids if key in o.cols):
                    raise UnsupportedPlan("inline", "a sketch beside plain values in a union")
                types[key] = self.b.attr(k.plan, col).dataType().sql()
        names = {key: self.b.fresh("a") for key in keys}
        mult = self.b.fresh("x") if any(k.mult for k in kids) else None
        mask = self.fresh_mask()
        plans = []
        for k in kids:
            more = [self.b.named(f"cast({k.cols.get(key, 'null')} as {types[key]})", names[key]) for key in keys]
            if mult:
                more.append(self.b.named(k.mult or "1L", mult))
            more += [self.b.named(f"coalesce({k.mask[w] if k.mask else '0L'}, 0L)", m) for w, m in enumerate(mask)]
            plans.append(self.b.project(k.plan, more, self.base(k)))
        plan = self.b.with_children(node, plans)
        single = frozenset.intersection(*[k.single | (frozenset(keys) - k.cols.keys()) for k in kids])
        return State(plan, names, {}, mult, mask, frozenset().union(*(k.present for k in kids)), single)

    def on_Intersect(self, node, up):
        if node.isAll():
            raise NonMonotonePlan("INTERSECT ALL")
        sides = []
        for c in self.b.children(node):
            st = self.visit(c, up + 1)
            keys = self.base(st)
            sides.append(self.grouped(st, keys, list(keys), 1))
        a, b = sides
        la, lb = self.base(a), self.base(b)
        names = [self.b.fresh("i") for _ in lb]
        other = self.b.project(b.plan, self.carry(b), [self.b.rename(x, n) for x, n in zip(lb, names)])
        keys = [self.b.fresh("j") for _ in la]
        a = replace(a, plan=self.b.project(a.plan, [self.b.rename(x, n) for x, n in zip(la, keys)]))
        cond = " and ".join(f"{x} <=> {y}" for x, y in zip(keys, names)) or "true"
        plan = self.b.join(a.plan, other, "inner", self.b.sql(cond))
        st = self.joined(plan, a, replace(b, plan=other), "Inner")
        drop = set(names) | set(keys)
        return replace(st, plan=self.b.project(st.plan, [], [x for x in self.b.output(st.plan) if x.name() not in drop]))

    def semi(self, node, left, right, up, how) -> State:
        """A semi join whose subquery holds policy sources becomes an aggregated inner join."""
        before = self.count
        a = self.visit(left, up)
        b = self.visit(right, up + 1)
        if how == "LeftAnti" or not b.present:
            if how == "LeftAnti" and not self.left_only:
                raise NonMonotonePlan("anti join")
            plain = b.plan if b.present else self.b.children(node)[1]
            if self.count == before:
                return State(self.b.with_children(node, [a.plan, plain]))
            if b.present:
                plain = self.b.project(b.plan, [], self.base(b))
            return replace(a, plan=self.b.with_children(node, [a.plan, plain]))
        cond = node.condition().get() if node.condition().isDefined() else None
        base_b = self.base(b)
        right_ids = {x.exprId().id() for x in base_b}
        left_ids = {x.exprId().id() for x in self.b.output(a.plan)}
        parts = self.b.conjuncts(cond) if cond is not None else []
        used, tied, led = set(), set(), set()
        for p in parts:
            ids = self.b.ids(p)
            used |= ids & right_ids
            if self.b.kind(p) in ("EqualTo", "EqualNullSafe"):
                l, r = self.b.ids(p.left()), self.b.ids(p.right())
                for x, y, own, side in ((l, r, p.left(), p.right()), (r, l, p.right(), p.left())):
                    if x <= left_ids and y <= right_ids and self.b.kind(side) == "AttributeReference":
                        tied |= y
                        led |= x if self.b.kind(own) == "AttributeReference" else set()
        equal = used <= tied
        keys = [x for x in base_b if x.exprId().id() in used]
        if equal:
            if not self.unique_by(right, used):
                b = self.grouped(b, keys, list(keys), 1)
            plan = self.b.join(a.plan, b.plan, "inner", cond)
            st = self.joined(plan, a, b, "Inner")
            return replace(st, plan=self.b.project(st.plan, [], [x for x in self.b.output(st.plan) if x.exprId().id() not in right_ids]))
        # several rows may match one row: pairs with a row id are merged to the row again. The
        # join's own keys stand first in the grouping, so its partitioning serves both
        b = replace(b, plan=self.b.project(b.plan, self.carry(b), keys))
        rid = self.b.fresh("r")
        left_base = self.base(a)
        a = replace(a, plan=self.b.project(a.plan, [self.b.named("monotonically_increasing_id()", rid)]))
        st = self.joined(self.b.join(a.plan, b.plan, "inner", cond), a, b, "Inner")
        needed = [x for x in left_base if x.exprId().id() in self.q.read_ids()]
        lead = [x for x in left_base if x.exprId().id() in led]
        rest = [x for x in needed if x.exprId().id() not in led]
        return self.grouped(st, [*lead, self.b.attr(st.plan, rid), *rest], needed, 1)

    def unique_by(self, node, ids: set) -> bool:
        """Whether the node has one row at most for each value of the columns."""
        b = self.b
        while b.kind(node) in ("Project", "Filter", "SubqueryAlias") and not self.q.instance_table(node):
            node = b.children(node)[0]
        if b.kind(node) != "Aggregate":
            return False
        keys = b.items(node.groupingExpressions())
        return bool(keys) and all(b.kind(k) == "AttributeReference" and k.exprId().id() in ids for k in keys)


def inline(query: QueryPlan, bound: Sequence[Bound], left_only: bool = False, windows: bool = False) -> Annotated:
    query.check_monotone(left_only, windows)
    an = Annotator(query, bound, left_only=left_only)
    st = an.visit(query.plan)
    for key, (c, where) in an.comps.items():
        if key not in st.cols:
            raise UnsupportedPlan("inline", f"aggregate {key}")
    values = policy_values(query, bound, st.cols, st.counted, single=st.single)
    return Annotated(query, st.plan, an.base(st), values, st.mask, [mask_present(st.mask)] * len(bound))
