import itertools
import random

import pytest
from hypothesis import given, settings, strategies as st

from tupleguard import aliases, constraint, expr as E, templates
from tupleguard.algebra import Agg
from tupleguard.errors import PolicySyntaxError, UnknownAttribute
from tupleguard.language import parse_policy, render_policy
from tupleguard.metrics import leaf_count, verdict_f1
from tupleguard.policy import KILL, REMOVE, Dimension, FlowPolicy, SinkRef, SourceRef, rank_resolution, register_resolution

SCHEMA = {"r": ["id", "uid", "cost", "cat"], "s": ["id", "y"], "dim": ["k", "flag"]}
cols = lambda t: SCHEMA[t.lower()]


def test_policy_text_round_trip():
    text = "SOURCE REQUIRED r AS a, s SINK out DIMENSION dim d ON a.id = d.k CONSTRAINT max(a.cost) > 1 AND out.x = 'SINK (ON FAIL' ON FAIL KILL"
    p = parse_policy(text)
    assert p.sources == (SourceRef("r", "a", True), SourceRef("s")) and p.sink == SinkRef("out") and p.on_fail == KILL
    assert p.dimensions == (Dimension("dim", "d", "a.id = d.k"),)
    assert parse_policy(render_policy(p)) == p
    sink_only = parse_policy("SINK t DIMENSION dim CONSTRAINT NOT dim.flag ON FAIL REMOVE")
    assert sink_only.sources == () and sink_only.on_fail == REMOVE


@pytest.mark.parametrize("bad", ["", "CONSTRAINT x ON FAIL REMOVE", "SOURCE r ON FAIL REMOVE", "SOURCE r CONSTRAINT max( ON FAIL REMOVE", "SOURCE r CONSTRAINT 1 = 1 SINK t ON FAIL KILL", "SOURCE r r2 r3 CONSTRAINT true ON FAIL REMOVE", "SOURCE r CONSTRAINT a = ON FAIL REMOVE"])
def test_syntax_errors_have_places(bad):
    with pytest.raises((PolicySyntaxError, ValueError)):
        parse_policy(bad)


_leaf = st.sampled_from([E.Lit("1"), E.Lit("'x'"), E.Attr(("r", "id")), E.Attr(("cost",))])
_scalar = st.recursive(_leaf, lambda c: st.builds(lambda op, a, b: E.Op(op, (a, b)), st.sampled_from("+-*/"), c, c) | st.builds(lambda a: E.Call("max", (a,)), c), max_leaves=6)
_bool = st.recursive(st.builds(lambda op, a, b: E.Op(op, (a, b)), st.sampled_from(["=", "<", ">=", "!="]), _scalar, _scalar), lambda c: st.builds(lambda op, a, b: E.Op(op, (a, b)), st.sampled_from(["and", "or"]), c, c) | st.builds(lambda a: E.Op("not", (a,)), c), max_leaves=5)


@given(_bool)
@settings(max_examples=150, deadline=None)
def test_rendering_parses_back(tree):
    def flat(n):
        n = E.rebuild(n, flat)
        if isinstance(n, E.Op) and n.op in ("and", "or"):
            return E.Op(n.op, tuple(y for x in n.args for y in (x.args if isinstance(x, E.Op) and x.op == n.op else (x,))))
        return n

    assert flat(E.parse(E.render(tree))) == flat(tree)


def test_bare_attributes_must_be_unique():
    f = constraint.analyze(FlowPolicy("p", "r.uid < 5 OR NOT UNIQUE r.cat", (SourceRef("r"),)), cols)
    assert set(f.aggs) == {"min(r.uid)", "max(r.uid)", "min(r.cat)", "max(r.cat)"}
    f = constraint.analyze(FlowPolicy("p", "r.id = out.id", (SourceRef("r"),), SinkRef("out")), cols)
    assert f.outputs == ["id"] and set(f.aggs) == {"min(r.id)", "max(r.id)"}


def test_distinct_counts_against_small_bounds_are_constant_size():
    f = constraint.analyze(FlowPolicy("p", "count(distinct r.uid) > 1 AND count(distinct r.cat) > 4", (SourceRef("r"),)), cols)
    assert {a.kind for a in f.aggs.values()} == {"min", "max", "distinct"}


def test_names_that_do_not_exist():
    for body in ("max(r.nope) > 1", "max(q.id) > 1", "max(id) > 1"):
        with pytest.raises(UnknownAttribute):
            constraint.analyze(FlowPolicy("p", body, (SourceRef("r"), SourceRef("s"))), cols)


def test_sums_split_only_over_known_non_nulls():
    agg = Agg("sum", (E.parse("a.x + b.y - a.z"),))
    assert constraint.split_linear(agg) is None
    got = constraint.split_linear(agg, {"a.x", "b.y", "a.z"})
    assert [(s, E.render(x.args[0])) for s, x in got] == [(1, "a.x"), (1, "b.y"), (-1, "a.z")]


def test_precedence_and_kinds():
    m = register_resolution("fix_it", lambda t: t)
    assert m.kind == "map"

    def whole(df):
        return df

    assert register_resolution("whole_it", whole).kind == "relation"
    assert rank_resolution([m, REMOVE, KILL]) == KILL and rank_resolution([m, REMOVE]) == REMOVE
    assert parse_policy("SOURCE r CONSTRAINT max(id) > 1 ON FAIL fix_it").on_fail.kind == "map"


# -- templates -----------------------------------------------------------------------------
def _holds(clauses, values):
    import duckdb

    con = duckdb.connect()
    con.execute("create table t(x double)")
    con.executemany("insert into t values (?)", [(v,) for v in values])
    return con.execute(f"select coalesce({' and '.join(clauses) or 'true'}, false) from t").fetchone()[0]


def test_collapse_equals_the_conjunction():
    rng = random.Random(7)
    for _ in range(60):
        agg = rng.choice(["min", "max", "avg", "sum"])
        bindings = [templates.PolicyTemplate(agg, rng.choice(["x", "x + 1", "2 * x", "-x", "3 - x"]), rng.choice(["<", "<=", ">", ">=", "=", "!="])).bind(rng.randint(-6, 12)) for _ in range(rng.randint(1, 6))]
        index = templates.TemplateIndex()
        extra = templates.PolicyTemplate("max", "x", ">").bind(1000)
        for b in [*bindings, extra]:
            index.add(b)
        index.remove(extra)
        values = [rng.randint(0, 5) for _ in range(rng.randint(1, 4))]
        assert _holds(index.clauses(), values) == _holds([templates.naive_conjunction(bindings)], values), bindings


def test_ties_contradictions_and_removal():
    t = templates.PolicyTemplate("max", "x", ">=")
    index = templates.TemplateIndex()
    for b in (t.bind(5), templates.PolicyTemplate("max", "x", ">").bind(5)):
        index.add(b)
    assert index.clauses() == ["(max(x) > 5.0)"]
    low = templates.PolicyTemplate("max", "x", "<").bind(5)
    index.add(low)
    assert index.clauses() == ["false"]
    index.remove(low)
    assert index.clauses() == ["(max(x) > 5.0)"]


def test_a_million_bindings_stay_one_clause():
    index = templates.TemplateIndex()
    t = templates.PolicyTemplate("count", "*", ">")
    for i in range(100_000):
        index.add(t.bind(i))
    assert index.clauses() == ["(count(*) > 99999.0)"]


# -- self-joins ----------------------------------------------------------------------------
def _pol(body):
    return FlowPolicy("p", body, (SourceRef("r", "a"), SourceRef("r", "b")))


def test_symmetry():
    assert aliases.is_symmetric(_pol("max(a.cost) = max(b.cost)"))
    assert aliases.is_symmetric(_pol("max(a.cost) != max(b.cost) and max(a.id) > 1 and max(b.id) > 1"))
    assert aliases.is_symmetric(_pol("abs(max(a.cost) - max(b.cost)) <= 3"))
    assert not aliases.is_symmetric(_pol("max(a.cost) <= max(b.cost)"))
    assert not aliases.is_symmetric(_pol("max(a.cost) = max(b.cost) and max(a.id) > 1"))


@pytest.mark.parametrize("body", ["max(a.cost) = max(b.cost)", "max(a.cost) != max(b.cost)", "abs(max(a.cost) - max(b.cost)) <= 2", "max(a.cost) + max(b.cost) > 3", "max(a.cost) = max(b.cost) and max(a.cost) > 1 and max(b.cost) > 1", "max(a.cost) < max(b.cost) + 2"])
def test_linear_clauses_equal_all_permutations(body):
    import duckdb

    p, n = _pol(body), 3
    for vals in itertools.product([0, 1, 2, 3, None], repeat=n):
        frm = " , ".join(f"(select {'null::int' if v is None else v} as cost) t{i}" for i, v in enumerate(vals))
        get = lambda cl: duckdb.execute(f"select coalesce({' and '.join(cl).replace('size(', 'len(').replace('array_distinct(array(', 'list_distinct(list_value(')}, false) from {frm}").fetchone()[0]
        assert get(aliases.linear_clauses(p, n)) == get(aliases.permutation_clauses(p, n)), vals


def test_clause_counts():
    assert aliases.permutation_count(1001, 2) == 1_001_000 and len(aliases.linear_clauses(_pol("max(a.cost) = max(b.cost)"), 1001)) == 1000


def test_measures():
    assert verdict_f1({1, 2}, {2, 3}).f1 == 0.5 and verdict_f1(set(), set()).f1 == 1.0
    # one row joined with two: the flat form repeats it, the factored form doesn't
    assert leaf_count(("+", ("*", "t1", "s1"), ("*", "t1", "s2"))) == 4 and leaf_count(("*", "t1", ("+", "s1", "s2"))) == 3
