"""Verdicts turned into output: remove, kill, repair, or hand over to a relation function."""

from __future__ import annotations

from typing import Sequence

from pyspark.sql import DataFrame, Observation, functions as F

from .errors import PolicyViolation, SchemaMismatch
from .plan import Bound
from .policy import RANK, resolution_function
from .strategies.common import Annotated, verdicts


def groups_of(bound: Sequence[Bound]) -> dict[str, list[int]]:
    """Positions of each policy's bound copies (one for each alias assignment)."""
    out: dict[str, list[int]] = {}
    for i, b in enumerate(bound):
        out.setdefault(b.policy.name, []).append(i)
    return out


def annotated_frame(a: Annotated, bound: Sequence[Bound], sink_columns=None) -> tuple[DataFrame, list[str], dict[str, str], dict[str, str]]:
    """The output with one ``ok`` and one ``applicable`` column for each policy."""
    b = a.query.bridge
    plan, cols = verdicts(a, bound, sink_columns)
    ok, app, more = {}, {}, []
    for name, places in groups_of(bound).items():
        ok[name], app[name] = b.fresh("pass"), b.fresh("does")
        more.append(b.named(" and ".join(cols[i][0] for i in places), ok[name]))
        more.append(b.named(" or ".join(cols[i][1] for i in places), app[name]))
    plan = b.project(plan, more, a.output) if more else plan
    return b.frame(plan), [x.name() for x in a.output], ok, app


def apply(a: Annotated, bound: Sequence[Bound], sink_columns=None, two_branch: bool = False) -> DataFrame:
    if not bound:
        return a.query.bridge.frame(a.plan)
    by_policy = {b.policy.name: b.policy for b in bound}
    order = list(by_policy)
    kinds = {n: by_policy[n].on_fail for n in order}
    if all(k.kind == "remove" for k in kinds.values()):
        # one filter and one projection on the plan
        bridge = a.query.bridge
        plan, cols = verdicts(a, bound, sink_columns)
        plan = bridge.filter(plan, " and ".join(f"coalesce({fine}, false)" for fine, _ in cols))
        return bridge.frame(bridge.project(plan, [], a.output))
    df, names, ok, _ = annotated_frame(a, bound, sink_columns)
    schema = a.query.df.schema
    # positions, as names of an output may repeat
    width = len(names)
    flat = df.toDF(*[f"__tg_c{i}" for i in range(width)], *[x for i in range(len(ok)) for x in (f"__tg_p{i}", f"__tg_d{i}")])
    passed = {n: f"__tg_p{i}" for i, n in enumerate(ok)}
    out_cols = [f"__tg_c{i}" for i in range(width)]

    def named(frame: DataFrame) -> DataFrame:
        return frame.select(*[F.col(c) for c in out_cols]).toDF(*names)

    kill = [n for n in order if kinds[n].kind == "kill"]
    if kill:
        flat = barrier(flat, [passed[n] for n in kill], kill)
    remove = [n for n in order if kinds[n].kind == "remove"]
    if remove:
        flat = flat.where(" and ".join(f"coalesce({passed[n]}, false)" for n in remove))
    for n in [n for n in order if kinds[n].kind == "map"]:
        flat = _transform(flat, out_cols, names, passed[n], resolution_function(kinds[n].name)[1], two_branch)
    relation = [n for n in order if kinds[n].kind == "relation"]
    out = None
    for n in relation:
        fn = resolution_function(kinds[n].name)[1]
        given = flat.select(*[F.col(c).alias(x) for c, x in zip(out_cols, names)], (~F.coalesce(F.col(passed[n]), F.lit(False))).alias("is_violation"))
        out = fn(given)
        if "is_violation" in out.columns:
            out = out.drop("is_violation")
        if [(f.name, f.dataType) for f in out.schema] != [(f.name, f.dataType) for f in schema]:
            raise SchemaMismatch(f"{kinds[n].name} returned {out.schema.simpleString()}")
        if len(relation) > 1:
            raise SchemaMismatch("one relation-level resolution at a time")
    return named(flat) if out is None else out


def barrier(df: DataFrame, passed: list[str], names: list[str]) -> DataFrame:
    """Aborts when a row violates. The metrics node under the filter keeps Catalyst from moving
    the test to rows that never reach the output."""
    bad = " or ".join(f"not coalesce({p}, false)" for p in passed)
    seen = df.observe(Observation(), F.count_if(F.expr(bad)).alias("violations"))
    message = "policy violated: " + ", ".join(names)
    return seen.where(F.expr(f"if({bad}, cast(raise_error('{message}') as boolean), true)"))


def _transform(flat: DataFrame, out_cols, names, passed: str, fn, two_branch: bool) -> DataFrame:
    """Violating tuples become what ``fn`` makes of them, or go where it gives null."""
    rest = [c for c in flat.columns if c not in out_cols]
    whole = F.struct(*[F.col(c).alias(x) for c, x in zip(out_cols, names)])
    good = F.coalesce(F.col(passed), F.lit(False))
    if two_branch:
        kept = flat.where(good)
        made = flat.where(~good).select(fn(whole).alias("__tg_t"), *rest).where("__tg_t is not null")
        return kept.union(made.select(*[F.col(f"__tg_t.`{x}`").alias(c) for c, x in zip(out_cols, names)], *rest))
    made = flat.select(F.when(good, whole).otherwise(fn(whole)).alias("__tg_t"), *rest).where("__tg_t is not null")
    return made.select(*[F.col(f"__tg_t.`{x}`").alias(c) for c, x in zip(out_cols, names)], *rest)


def count_violations(a: Annotated, bound: Sequence[Bound], sink_columns=None) -> DataFrame:
    """``(policy, applicable, violations, total)``."""
    df, _, ok, app = annotated_frame(a, bound, sink_columns)
    flat = df.toDF(*[f"__tg_c{i}" for i in range(len(df.columns))])
    n = len(df.columns) - 2 * len(ok)
    aggs = []
    for i, name in enumerate(ok):
        p, d = f"__tg_c{n + 2 * i}", f"__tg_c{n + 2 * i + 1}"
        aggs.append(F.struct(F.lit(name).alias("policy"), F.coalesce(F.bool_or(F.col(d)), F.lit(False)).alias("applicable"), F.count_if(~F.col(p)).alias("violations"), F.count(F.lit(1)).alias("total")))
    return flat.agg(F.array(*aggs).alias("v")).select(F.inline("v"))


__all__ = ["PolicyViolation", "RANK", "annotated_frame", "apply", "barrier", "count_violations"]
