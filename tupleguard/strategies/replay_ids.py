"""Provenance baseline, id vectors: the base query also emits, for each output row, the ids of
the source rows of each derivation; the attributes are fetched by a join with the base tables
afterwards. An emulation: Spark has no operator hook that records lineage."""

from __future__ import annotations

from typing import Sequence

from .. import expr as E
from ..errors import UnsupportedPlan
from ..plan import Bound, QueryPlan
from .common import Annotated
from .replay_rows import Wide, Widener, collapse


class _Ids(Widener):
    """Widens by row ids only: file and row index, stable between scans."""

    name = "replay_ids"

    def __init__(self, query, bound, nested: bool):
        super().__init__(query, bound, True)
        self.nested, self.depth, self.leaves = nested, 0, {}

    def leaf(self, node) -> Wide:
        i = self.count
        self.count += 1
        inner = self.q.names(node)[2]
        if self.b.kind(inner) != "LogicalRelation":
            raise UnsupportedPlan(self.name, "a source without files")
        if not inner.relation().fileFormat().getClass().getSimpleName().startswith("Parquet"):
            raise UnsupportedPlan(self.name, "a file format without row indexes")
        rid = self.b.fresh("r")
        base = self.b.output(node)
        more = [self.b.named("struct(_metadata.file_path, _metadata.row_index)", rid)]
        self.leaves[i] = (inner, rid)
        return Wide(self.b.project(inner, more, base), {}, {i: rid}, [rid])

    def on_Aggregate(self, node):
        if self.depth and not self.nested:
            raise UnsupportedPlan(self.name, "nested aggregates")
        self.depth += 1
        w = self.visit(self.b.children(node)[0])
        self.depth -= 1
        keys = self.b.items(node.groupingExpressions())
        names = [self.b.fresh("k") for _ in keys]
        vec = self.b.fresh("w")
        ids = ", ".join(w.rid.values())
        if not ids:
            return Wide(self.b.aggregate(keys, self.b.items(node.aggregateExpressions()) + [self.b.rename(k, n) for k, n in zip(keys, names)], w.plan), {}, {}, names)
        outputs = self.b.items(node.aggregateExpressions()) + [self.b.rename(k, n) for k, n in zip(keys, names)] + [self.b.named(f"collect_list(struct({ids}))", vec)]
        plan = self.b.aggregate(keys, outputs, w.plan)
        # the vectors unfold to one row per derivation again
        one = self.b.fresh("w")
        base = [a for a in self.b.output(plan) if a.name() != vec]
        plan = self.b.project(plan, [self.b.named(f"explode_outer({vec})", one)], base)
        fresh = {i: self.b.fresh("r") for i in w.rid}
        plan = self.b.project(plan, [self.b.named(f"{one}.{w.rid[i]}", fresh[i]) for i in w.rid], [a for a in self.b.output(plan) if a.name() != one])
        return Wide(plan, {}, fresh, names)

    def on_Distinct(self, node):
        raise UnsupportedPlan(self.name, "DISTINCT")

    on_Deduplicate = on_Distinct

    def on_Join(self, node):
        if self.b.kind(node.joinType()) == "LeftSemi" and not self.nested:
            raise UnsupportedPlan(self.name, "semi join")
        return super().on_Join(node)


def replay_ids(query: QueryPlan, bound: Sequence[Bound], nested: bool = False) -> Annotated:
    query.check_monotone()
    query.check_deterministic()
    b, plan = query.bridge, query.plan
    limits = []
    while b.kind(plan) in ("GlobalLimit", "LocalLimit", "Offset", "Sort"):
        limits.append(plan)
        plan = b.children(plan)[0]
    if any(b.kind(x) != "Sort" for x in limits):
        raise UnsupportedPlan("replay_ids", "LIMIT")
    ids = _Ids(query, bound, nested)
    w = ids.visit(plan)
    base = ids.base(w)
    # attributes come by a join of the derivations with each base table
    for i, attrs in ids.needs.items():
        if any(a.startswith("d:") for a in attrs):
            raise UnsupportedPlan("replay_ids", "keyed dimensions")
        inner, _ = ids.leaves[i]
        look = b.fresh("r")
        cols = {a: b.fresh("v") for a in sorted(attrs)}
        # a second instance of the relation has ids of its own
        table = b.frame(inner)
        scan = table.selectExpr(f"struct(_metadata.file_path, _metadata.row_index) as {look}", *[f"{E.quote(a)} as {n}" for a, n in cols.items()])
        w.plan = b.join(w.plan, scan._jdf.queryExecution().analyzed(), "left", b.sql(f"{w.rid[i]} = {look}"))
        w.raw |= {(i, a): n for a, n in cols.items()}
    return collapse(query, w, base, bound, ids.dims)
