"""Annotation algebra: how each aggregate of a constraint is carried as constant-size columns.

A component has a leaf expression, a way to merge in an aggregate, and says whether it scales
with the other side's multiplicity at joins (sum-like) or not (idempotent)."""

from __future__ import annotations

import math
from dataclasses import dataclass

from . import expr as E


@dataclass(frozen=True)
class Agg:
    """An aggregate of a constraint. ``args`` are scalar trees over source attributes."""

    kind: str
    args: tuple[E.Node, ...] = ()

    @property
    def key(self) -> str:
        return f"{self.kind}({', '.join(E.render(a) for a in self.args)})"


@dataclass(frozen=True)
class Component:
    key: str
    leaf: E.Node
    plus: str
    sumlike: bool


VARIANCE = {"var_samp", "var_pop", "stddev_samp", "stddev_pop"}
PAIRS = {"covar_samp", "covar_pop", "corr", "regr_slope"}
ALIASES = {"mean": "avg", "stddev": "stddev_samp", "variance": "var_samp", "every": "bool_and", "some": "bool_or", "any": "bool_or"}
SIMPLE = {"min", "max", "count", "sum", "avg", "bool_and", "bool_or", "distinct", "approx_distinct"} | VARIANCE | PAIRS
#: Kinds without a constant-size annotation.
HOLISTIC = {"approx_count_distinct", "percentile", "median", "collect_list", "collect_set", "mode"}

_CUSTOM: dict[str, tuple] = {}


def register_semiring(name: str, lift: str, plus: str, finalize: str, sumlike: bool = False) -> None:
    """A decomposable aggregate of one argument: SQL templates over ``{x}`` for the leaf, the
    merging aggregate's function name, and the final value."""
    _CUSTOM[name.lower()] = (lift, plus, finalize, sumlike)
    E.AGGREGATES.add(name.lower())


def custom(name: str):
    return _CUSTOM.get(name)


def _null_case(cond: E.Node, value: E.Node) -> E.Node:
    return E.Case(((cond, value),), None)


def _not_null(*xs: E.Node) -> E.Node:
    parts = tuple(E.Op("is not null", (x,)) for x in xs)
    return parts[0] if len(parts) == 1 else E.Op("and", parts)


def _double(x: E.Node) -> E.Node:
    return E.Call("double", (x,))


def components(agg: Agg) -> list[Component]:
    """The columns that carry the aggregate; empty for kinds that need the whole bag."""
    k, a = agg.kind, agg.args
    x = a[0] if a else E.Lit("1")
    text = ", ".join(E.render(v) for v in a) or "*"
    one = E.Call("if", (_not_null(*a) if a else E.Lit("true"), E.Lit("1L"), E.Lit("0L")))
    cnt = Component(f"n[{text}]", one, "sum", True)
    if k == "count":
        return [cnt]
    if k in ("min", "max"):
        return [Component(f"{k}[{text}]", x, k, False)]
    if k in ("bool_and", "bool_or"):
        return [Component(f"{k}[{text}]", x, k, False)]
    if k == "sum":
        return [Component(f"sum[{text}]", x, "sum", True)]
    if k == "avg":
        return [Component(f"sum[{text}]", x, "sum", True), cnt]
    if k in VARIANCE:
        d = _double(x)
        return [cnt, Component(f"sumd[{text}]", d, "sum", True), Component(f"sumsq[{text}]", E.Op("*", (d, d)), "sum", True)]
    if k in PAIRS:
        u, v = _double(a[0]), _double(a[1])
        both = _not_null(*a)
        part = lambda name, e: Component(f"{name}[{text}]", _null_case(both, e), "sum", True)
        return [cnt, part("su", u), part("sv", v), part("suu", E.Op("*", (u, u))), part("svv", E.Op("*", (v, v))), part("suv", E.Op("*", (u, v)))]
    if k == "distinct":
        return [Component(f"set[{text}]", E.Call("array_compact", (E.Call("array", (x,)),)), "set", False)]
    if k == "approx_distinct":
        # values until the first aggregate, sketches of bounded size from there on
        return [Component(f"hll[{text}]", E.Call("string", (x,)), "hll", False)]
    if (own := custom(k)) is not None:
        lift, plus, _, sumlike = own
        return [Component(f"{k}[{text}]", E.parse(lift.replace("{x}", E.render(x))), plus, sumlike)]
    return []


def merge_sql(plus: str, column: str, single: bool = False, cap: int | None = None) -> str:
    """SQL of the aggregate that merges a component's column (``single``: of values, not sketches;
    ``cap``: the number of elements that a set needs at most)."""
    if plus == "set":
        whole = f"array_distinct(flatten(collect_set({column})))"
        return whole if cap is None else f"slice({whole}, 1, {cap})"
    if plus == "hll":
        return f"hll_sketch_agg({column})" if single else f"hll_union_agg({column})"
    return f"{plus}({column})"


def finalize_sql(agg: Agg, cols: list[str], single: bool = False) -> str:
    """The aggregate's value from its components' columns (``single``: not aggregated yet)."""
    k = agg.kind
    if k in ("min", "max", "bool_and", "bool_or", "sum"):
        return cols[0]
    if k == "count":
        return f"coalesce({cols[0]}, 0L)"
    if k == "avg":
        return f"({cols[0]} / nullif({cols[1]}, 0L))"
    if k == "distinct":
        return f"coalesce(cast(size({cols[0]}) as bigint), 0L)"
    if k == "approx_distinct":
        return f"if({cols[0]} is null, 0L, 1L)" if single else f"coalesce(hll_sketch_estimate({cols[0]}), 0L)"
    if k in VARIANCE:
        n, s, ss = cols
        pop = k.endswith("pop")
        left = f"if({ss} - {s} * {s} / {n} <= 1e-12D * {ss}, 0D, {ss} - {s} * {s} / {n})"
        var = f"({left} / {n if pop else f'nullif({n} - 1, 0)'})"
        var = f"case when {n} > 0 then {var} end"
        return f"sqrt({var})" if k.startswith("stddev") else var
    if k in PAIRS:
        n, su, sv, suu, svv, suv = cols
        co = f"if(abs({suv} - {su} * {sv} / {n}) <= 1e-12D * abs({suv}), 0D, {suv} - {su} * {sv} / {n})"
        if k == "covar_pop":
            return f"case when {n} > 0 then {co} / {n} end"
        if k == "covar_samp":
            return f"case when {n} > 1 then {co} / ({n} - 1) end"
        # what rounding leaves of a constant side is no spread
        spread = lambda ss, x: f"if({ss} - {x} * {x} / {n} <= 1e-12D * {ss}, 0D, {ss} - {x} * {x} / {n})"
        xx, yy = spread(suu, su), spread(svv, sv)
        if k == "corr":
            return f"case when {n} > 1 then {co} / nullif(sqrt({xx} * {yy}), 0D) end"
        return f"case when {n} > 1 then {co} / nullif({yy}, 0D) end"
    if (own := custom(k)) is not None:
        return own[2].replace("{x}", cols[0])
    raise KeyError(k)


def direct_sql(agg: Agg, args: list[str]) -> str:
    """The aggregate over a bag that is present row by row."""
    if agg.kind == "distinct":
        return f"count(distinct {args[0]})"
    if agg.kind == "approx_distinct":
        return f"coalesce(hll_sketch_estimate(hll_sketch_agg(string({args[0]}))), 0L)"
    if agg.kind == "count" and not args:
        return "count(1)"
    if agg.kind in ("corr", "regr_slope"):
        # spelled out, as the built-in ones divide by zero where a side is constant
        u, v = (f"case when {args[1 - i]} is not null then double({args[i]}) end" for i in (0, 1))
        below = f"stddev_pop({u}) * stddev_pop({v})" if agg.kind == "corr" else f"var_pop({v})"
        return f"covar_pop({args[0]}, {args[1]}) / nullif({below}, 0D)"
    if (own := custom(agg.kind)) is not None:
        lift, plus, fin, _ = own
        return fin.replace("{x}", merge_sql(plus, lift.replace("{x}", args[0])))
    return f"{agg.kind}({', '.join(args)})"


def scalar_sql(agg: Agg, args: list[str]) -> str | None:
    """The aggregate over a bag of one row."""
    k = agg.kind
    if k in ("sum", "min", "max", "avg", "bool_and", "bool_or", "median", "mode"):
        return args[0]
    if k == "count":
        return f"if({' and '.join(f'{a} is not null' for a in args)}, 1L, 0L)" if args else "1L"
    if k in ("distinct", "approx_count_distinct", "approx_distinct"):
        return f"if({args[0]} is null, 0L, 1L)"
    if k in ("var_pop", "stddev_pop"):
        return f"if({args[0]} is null, null, 0D)"
    return None


def set_caps(residual: E.Node, keys: dict[str, str]) -> dict[str, int | None]:
    """How many elements each distinct count's set needs (``keys``: slot to component): one above
    the largest number that it is compared with, or all (None) where it is used otherwise."""
    caps: dict[str, int | None] = {}

    def note(key: str, cap: int | None) -> None:
        old = caps.get(key, 0)
        caps[key] = None if cap is None or old is None else max(old, cap)

    def look(n: E.Node) -> None:
        if isinstance(n, E.Op) and n.op in ("=", "!=", "<", "<=", ">", ">="):
            for a, b in (n.args, n.args[::-1]):
                if isinstance(a, E.Slot) and a.key in keys and (k := E.number(b)) is not None:
                    note(keys[a.key], max(0, math.floor(k)) + 1)
                    return
        if isinstance(n, E.Slot) and n.key in keys:
            note(keys[n.key], None)
        for c in E.children(n):
            look(c)

    look(residual)
    return caps


def bounded_distinct(op: str, k: float) -> str | None:
    """A constant-size form of ``count(distinct x) op k`` over min and max, if there is one."""
    if (op, k) in ((">", 1), (">=", 2)):
        return "coalesce({min} < {max}, false)"
    if (op, k) in (("<", 2), ("<=", 1)):
        return "not coalesce({min} < {max}, false)"
    if (op, k) == ("=", 1):
        return "coalesce({min} = {max}, false)"
    if (op, k) == ("!=", 1):
        return "not coalesce({min} = {max}, false)"
    if (op, k) in ((">", 0), (">=", 1), ("!=", 0)):
        return "({min} is not null)"
    if (op, k) in (("=", 0), ("<", 1), ("<=", 0)):
        return "({min} is null)"
    return None
