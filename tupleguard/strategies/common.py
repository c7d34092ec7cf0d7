"""What every strategy hands to the resolution step, and how verdicts are written."""

from __future__ import annotations

from dataclasses import dataclass
from typing import Sequence

from pyspark.sql import functions as F

from .. import expr as E
from ..algebra import components, finalize_sql
from ..constraint import SESSION
from ..errors import UnsupportedPlan
from ..plan import Bound, QueryPlan, all_components, keyed_dimensions


@dataclass
class Annotated:
    """A plan whose rows carry policy values. ``values`` gives, for each bound policy, the SQL of
    each of its aggregates; ``mask`` holds the lineage mask's columns, if any."""

    query: QueryPlan
    plan: object
    output: list
    values: list[dict[str, str]]
    mask: tuple[str, ...] | None = None
    #: Per policy: SQL that says whether all of the given instances are present.
    present: list | None = None


def check_dimensions(query: QueryPlan, bound: Sequence[Bound]) -> None:
    """Asserts that keyed dimensions are unique on their keys."""
    from ..errors import DimensionNotUnique

    for alias, (_, d) in keyed_dimensions(bound).items():
        keys = [a.name for a in E.attrs(E.parse(d.on)) if a.qualifier and a.qualifier.lower() == alias]
        if query.spark.table(d.table).groupBy(*keys).count().where("count > 1").limit(1).count():
            raise DimensionNotUnique(f"{d.table}({', '.join(keys)})")


def leaf_name(query: QueryPlan, dims: dict):
    """How names of a bound argument read at their leaf."""

    def name(n):
        if isinstance(n, E.Attr):
            return dimension_column(n.parts[0] + "." + n.name) if n.parts[0].startswith("d:") else E.quote(n.name)
        return None

    return name


def dimension_column(attr: str) -> str:
    """The hidden name of ``d:<alias>.<column>`` beside its leaf's columns."""
    alias, _, column = attr[2:].partition(".")
    return E.quote(f"__tg_d_{alias}_{column}".lower())


def join_dimensions(query: QueryPlan, plan, instance: int, dims: dict):
    """The leaf joined with the keyed dimensions that hang on it."""
    b = query.bridge
    for alias, (at, d) in dims.items():
        if at != instance:
            continue
        table = query.spark.table(d.table)
        dim = table.toDF(*[f"__tg_d_{alias}_{c}".lower() for c in table.columns])
        # its own instances of relations, which the query may read too
        dim = b.children(b.join(dim._jdf.queryExecution().analyzed(), dim._jdf.queryExecution().analyzed(), "cross"))[1]
        cond = E.parse(d.on)
        text = E.render(cond, lambda n, a=alias: (dimension_column(f"d:{a}.{n.name}") if n.qualifier and n.qualifier.lower() == a else E.quote(n.name)) if isinstance(n, E.Attr) else None)
        plan = b.join(plan, dim, "left", b.sql(text))
    return plan


def strip_one(n: E.Node) -> E.Node:
    """The marker of one monomial as the number 1."""
    if isinstance(n, E.Call) and n.name == "tg_one":
        return E.Lit("1")
    return E.rebuild(n, strip_one)


def policy_values(query: QueryPlan, bound: Sequence[Bound], columns: dict[str, str], final: set[str] = frozenset(), more: dict[str, str] | None = None, single: frozenset = frozenset()) -> list[dict[str, str]]:
    """SQL of each policy's aggregates from component columns."""
    out = []
    for b in bound:
        own = {}
        for key, agg in b.aggs.items():
            comps = components(agg)
            if not comps:
                if more is None or agg.key not in more:
                    raise UnsupportedPlan("inline", agg.kind)
                own[key] = more[agg.key]
            elif agg.kind == "distinct" and comps[0].key in final:
                own[key] = f"coalesce({columns[comps[0].key]}, 0L)"
            else:
                own[key] = finalize_sql(agg, [columns[c.key] for c in comps], comps[0].key in single)
        out.append(own)
    return out


def verdicts(a: Annotated, bound: Sequence[Bound], sink_columns: dict[str, str] | None = None):
    """Adds, for each policy, ``ok`` (true also where it doesn't apply) and ``applicable``
    columns: returns the plan and the columns' names."""
    query, b = a.query, a.query.bridge
    names = {x.name().lower(): x for x in a.output}
    extra, outs = [], {}
    for bd in bound:
        for col in bd.form.outputs:
            if col in outs:
                continue
            real = (sink_columns or {}).get(col.lower(), col).lower()
            if real not in names:
                from ..errors import UnknownAttribute

                raise UnknownAttribute(f"output has no column {col}")
            outs[col] = b.fresh("o")
            extra.append(b.rename(names[real], outs[col]))
    plan = b.project(a.plan, extra) if extra else a.plan
    for bd in bound:
        for key, cond in bd.form.exists.items():
            plan = _with_existence(query, plan, bd, key, cond)
    cols = []
    more = []
    for i, bd in enumerate(bound):
        def name(n, i=i, bd=bd):
            if isinstance(n, E.Slot):
                if n.key.startswith("out:"):
                    return outs[n.key[4:]]
                if n.key.startswith("exists:"):
                    return bd.__dict__.setdefault("exists_columns", {})[n.key]
                return f"({a.values[i][n.key]})"
            if isinstance(n, E.Attr) and n.parts[0] == "session":
                return SESSION[n.name]
            return None

        ok = f"coalesce({E.render(bd.form.residual, name)}, false)"
        present = a.present[i] if a.present else None
        applies = present(bd.cover) if present and bd.cover else "true"
        held = present(bd.required) if present and bd.required else "true"
        if bd.missing_required:
            held = "false"
        fine, app = b.fresh("ok"), b.fresh("app")
        more += [b.named(f"not ({applies}) or (({held}) and {ok})", fine), b.named(f"({applies})", app)]
        cols.append((fine, app))
    return b.project(plan, more), cols


def _with_existence(query: QueryPlan, plan, bd: Bound, key: str, cond: E.Node):
    """A one-row relation that says whether some dimension rows satisfy the formula."""
    b = query.bridge
    spark = query.spark
    wanted = list(dict.fromkeys(x.parts[0] for x in E.attrs(cond) if x.parts[0] != "session"))
    frames = {d.name.lower(): spark.table(d.table).alias(d.name.lower()) for d in bd.policy.dimensions if d.name.lower() in wanted}
    sql = lambda n: E.render(n, lambda x: SESSION[x.name] if isinstance(x, E.Attr) and x.parts[0] == "session" else None)
    parts = E.conjuncts(cond)
    joined, have = None, set()
    for alias in wanted:
        have.add(alias)
        here = [p for p in parts if {x.parts[0] for x in E.attrs(p)} - {"session"} <= have]
        on = " and ".join(sql(p) for p in here if len({x.parts[0] for x in E.attrs(p)} - {"session"}) > 1) or "true"
        joined = frames[alias] if joined is None else joined.join(frames[alias], F.expr(on))
    col = b.fresh("ex")
    one = joined.where(sql(cond)).limit(1).selectExpr(f"count(1) > 0 as {col}")
    bd.__dict__.setdefault("exists_columns", {})[key] = col
    return b.join(plan, F.broadcast(one)._jdf.queryExecution().analyzed(), "cross")


#: Instances of one word of a lineage mask.
BITS = 62


def mask_words(query: QueryPlan) -> int:
    return max(1, -(-len(query.instances) // BITS))


def mask_bits(instance: int, words: int) -> list[str]:
    """The words of a mask that holds one instance."""
    return [f"{1 << instance % BITS}L" if instance // BITS == w else "0L" for w in range(words)]


def mask_present(mask: Sequence[str] | None):
    """SQL over the mask's words that says whether all of some instances are present."""

    def present(ids: frozenset) -> str:
        if mask is None:
            return "true"
        tests = []
        for w in sorted({i // BITS for i in ids}):
            bits = sum(1 << i % BITS for i in ids if i // BITS == w)
            tests.append(f"(coalesce({mask[w]}, 0L) & {bits}L) = {bits}L")
        return "(" + " and ".join(tests or ["true"]) + ")"

    return present


__all__ = ["Annotated", "all_components", "check_dimensions", "dimension_column", "join_dimensions", "keyed_dimensions", "leaf_name", "mask_bits", "mask_present", "mask_words", "policy_values", "strip_one", "verdicts"]
