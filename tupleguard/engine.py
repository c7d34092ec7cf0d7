"""The facade: register policies, then query, insert and update through a guard."""

from __future__ import annotations

from typing import Sequence

from py4j.java_gateway import is_instance_of
from pyspark.sql import DataFrame, SparkSession

from . import aliases, constraint, resolve
from .catalyst import Bridge
from .errors import NonMonotonePlan, UnsupportedPlan
from .plan import Bound, QueryPlan, alias_assignments, bind
from .policy import OUTPUT, FlowPolicy
from .strategies.common import check_dimensions


def _strategies() -> dict:
    from .strategies.inline import inline
    from .strategies.replay_ids import replay_ids
    from .strategies.replay_rows import replay_rows
    from .strategies.two_pass import two_pass

    return {"inline": inline, "two_pass": two_pass, "replay_rows": replay_rows, "replay_ids": replay_ids}


class Guard:
    """Queries run through a guard satisfy its policies. The raw session stays unguarded."""

    def __init__(self, spark: SparkSession, policies: Sequence[FlowPolicy] = (), check_keys: bool = False, linear_self_joins: bool = True):
        self.spark = spark
        self.policies: list[FlowPolicy] = list(policies)
        self.check_keys = check_keys
        self.linear = linear_self_joins

    def add(self, *policies: FlowPolicy) -> "Guard":
        self.policies += policies
        return self

    def _frame(self, q) -> DataFrame:
        """The query as a frame. Text must be a query: a command would run, or redefine a
        relation that policies name, before anything could be checked."""
        if not isinstance(q, str):
            return q
        parsed = plan = self.spark._jsparkSession.sessionState().sqlParser().parsePlan(q)
        while plan.getClass().getSimpleName() == "UnresolvedWith":
            plan = plan.child()
        gateway = self.spark.sparkContext._gateway
        if any(is_instance_of(gateway, plan, f"org.apache.spark.sql.catalyst.plans.logical.{kind}") for kind in ("Command", "ParsedStatement", "CompoundBody")):
            raise UnsupportedPlan("guard", f"a statement that is no query ({plan.getClass().getSimpleName()})")
        return Bridge(self.spark).frame(parsed)

    def _columns(self, query: QueryPlan | None = None):
        def schema_of(table: str) -> list[str]:
            if table.upper() == OUTPUT:
                return []
            if query is not None:
                for i in query.instances:
                    if i.table == table.lower().rsplit(".", 1)[-1]:
                        return list(i.columns)
            return self.spark.table(table).columns

        return schema_of

    def plan(self, q, sink: str | None = None, policies: Sequence[FlowPolicy] | None = None) -> tuple[QueryPlan, list[Bound]]:
        """The query and the policies that may apply to it, bound to its relation instances."""
        todo = [p for p in (self.policies if policies is None else policies) if p.sink is None or (sink is not None and p.sink.table.lower() == sink.lower())]
        query = QueryPlan(self._frame(q), [s.table for p in todo for s in p.sources])
        if query.hidden:
            raise NonMonotonePlan(f"subquery expressions over {', '.join(sorted(query.hidden))}")
        read = query.tables_read()
        bound: list[Bound] = []
        for p in todo:
            tables = {s.table.lower().rsplit(".", 1)[-1]: s.required for s in p.sources}
            missing = [t for t in tables if t not in read]
            if any(not tables[t] for t in missing):
                continue
            if missing:
                # a required source that the query doesn't read: every row fails
                b = Bound(p, constraint.ConstraintForm(constraint.E.Lit("false")), {})
                b.missing_required = True
                bound.append(b)
                continue
            counts = {t: (sum(i.table == t for i in query.instances), sum(s.table.lower().rsplit(".", 1)[-1] == t for s in p.sources)) for t in tables}
            linear = self.linear and all(n >= m for n, m in counts.values()) and any(n > 1 for n, _ in counts.values()) and not query.has_alternatives()
            if linear and (merged := aliases.linear_bound(p, query.instances, self._columns(query))) is not None:
                bound.append(merged)
                continue
            ways = alias_assignments(p, query.instances)
            if not ways and p.sources:
                continue
            form = constraint.analyze(p, self._columns(query))
            bound += [bind(p, form, w) for w in (ways or [{}])]
        if self.check_keys:
            check_dimensions(query, bound)
        return query, bound

    def annotate(self, q, strategy: str = "inline", sink: str | None = None, policies=None, **options):
        query, bound = self.plan(q, sink, policies)
        if not bound:
            return None, query, bound
        if strategy == "auto":
            from .strategies.choose import choose_strategy

            strategy = choose_strategy(query, bound)
            order = dict.fromkeys([strategy, "inline", "two_pass", "replay_rows"])
            for i, s in enumerate(order):
                try:
                    return _strategies()[s](query, bound, **options), query, bound
                except UnsupportedPlan:
                    if i + 1 == len(order):
                        raise
        return _strategies()[strategy](query, bound, **options), query, bound

    def query(self, q, strategy: str = "auto", limit_mode: str = "after", two_branch: bool = False, **options) -> DataFrame:
        """The query's output without (or repaired for) tuples whose derivation breaks a policy.

        ``limit_mode='refill'`` puts the guard below a final limit instead of above it."""
        if limit_mode == "refill":
            df = self._frame(q)
            b = QueryPlan(df).bridge
            node, stack = b.analyzed(df), []
            while b.kind(node) in ("GlobalLimit", "LocalLimit", "Offset"):
                stack.append(node)
                node = b.children(node)[0]
            if stack:
                inner = self.query(b.frame(node), strategy, two_branch=two_branch, **options)._jdf.queryExecution().analyzed()
                for s in reversed(stack):
                    inner = b.with_children(s, [inner])
                return b.frame(inner)
        a, query, bound = self.annotate(q, strategy, **options)
        return query.df if a is None else resolve.apply(a, bound, two_branch=two_branch)

    def verdicts(self, q, strategy: str = "inline", **options) -> DataFrame:
        a, query, bound = self.annotate(q, strategy, **options)
        if a is None:
            return self.spark.createDataFrame([], "policy string, applicable boolean, violations bigint, total bigint")
        return resolve.count_violations(a, bound)

    def explain(self, q, strategy: str = "inline") -> str:
        """Each policy's applicability, bindings, annotations and clause."""
        from .plan import all_components
        from .strategies.choose import choose_strategy

        query, bound = self.plan(q)
        lines = [f"query over {', '.join(f'{i.table} as {i.alias}' for i in query.instances) or 'no policy source'}", f"strategy: {choose_strategy(query, bound) if strategy == 'auto' else strategy}", f"per-tuple applicability: {query.needs_mask()}"]
        applied = {b.policy.name for b in bound}
        for p in self.policies:
            lines.append(f"policy {p.name}: {'applies' if p.name in applied else 'does not apply'}")
        for b in bound:
            lines.append(f"  {b.policy.name} {b.assignment}: {constraint.E.render(b.form.residual)}")
        comps, holistic = all_components(bound)
        lines += [f"annotation {k}: merged by {c.plus}{', scaled by multiplicity' if c.sumlike else ''}" for k, (c, _) in comps.items()]
        lines += [f"whole bag: {k}" for k in holistic]
        return "\n".join(lines)

    def insert_into(self, table, df, mode: str = "append", strategy: str = "auto"):
        from .sinks import insert_into

        return insert_into(self, table, self._frame(df), mode, strategy)

    def merge(self, table, key: str, df, matched: str = "update", not_matched: str = "insert", strategy: str = "auto"):
        from .sinks import merge_into

        return merge_into(self, table, key, self._frame(df), matched, not_matched, strategy)

    def update(self, table, key: str, set_: dict | None = None, where=None, changes=None):
        from .sinks import update

        return update(self, table, key, set_, where, changes)

    def update_each(self, table, key: str, requests: DataFrame, column: str):
        from .sinks import update_each

        return update_each(self, table, key, requests, column)

    def stream(self, df: DataFrame, build) -> DataFrame:
        from .streaming import guard_stream

        return guard_stream(self, df, build)
