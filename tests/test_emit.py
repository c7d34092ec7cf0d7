"""Portable text of guarded queries: run in DuckDB, against the guard in Spark."""

import duckdb
import pytest

from tupleguard import Guard, UnsupportedPlan
from tupleguard.emit import Block, From, UnionAll, write_sql
from tupleguard.policy import FlowPolicy, SourceRef

L, O, C = SourceRef("lineitem"), SourceRef("orders"), SourceRef("customer")

PER_ORDER = Block((("l.l_orderkey", "k"), ("count(*)", "n")), (From("lineitem", "l"),), "l.l_quantity > 5", ("l.l_orderkey",))
NESTED = Block((("o.o_orderpriority", "p"), ("o.o_orderstatus", "s"), ("sum(x.n)", "n")), (From("orders", "o"), From(PER_ORDER, "x", on="o.o_orderkey = x.k")), None, ("o.o_orderpriority", "o.o_orderstatus"))
LEFT = Block((("c.c_mktsegment", "m"), ("o.o_orderstatus", "s"), ("count(*)", "n")), (From("customer", "c"), From("orders", "o", "left", "c.c_custkey = o.o_custkey and o.o_totalprice > 470000")), None, ("c.c_mktsegment", "o.o_orderstatus"))
SEMI = Block((("o.o_orderstatus", "s"), ("o.o_orderpriority", "p"), ("count(*)", "n")), (From("orders", "o"), From("lineitem", "l", "semi", "o.o_orderkey", "l_orderkey")), "o.o_totalprice > 250000", ("o.o_orderstatus", "o.o_orderpriority"))
UNION = Block((("u.k", "k"), ("count(*)", "n")), (From(UnionAll((
    Block((("l.l_suppkey", "k"),), (From("lineitem", "l"),), "l.l_tax > 0.06"),
    Block((("c.c_nationkey", "k"),), (From("customer", "c"),)),
)), "u"),), None, ("u.k",))
SELF = Block((("a.l_orderkey", "k"), ("count(*)", "n")), (From("lineitem", "a"), From("lineitem", "b", on="a.l_orderkey = b.l_orderkey")), "a.l_linenumber = 1 and b.l_linenumber = 2", ("a.l_orderkey",))
KEYLESS = Block((("count(*)", "n"),), (From("lineitem", "l"),), "l.l_quantity > 1000", ())
SELECTION = Block((("l.l_orderkey", "k"), ("l.l_tax", "t")), (From("lineitem", "l"), From("orders", "o", on="l.l_orderkey = o.o_orderkey")), "o.o_totalprice > 400000")
TOP = Block((("l.l_orderkey", "k"), ("sum(l.l_quantity)", "q")), (From("lineitem", "l"),), None, ("l.l_orderkey",), "count(*) > 2", "ORDER BY q DESC, k LIMIT 40")

CASES = [
    (NESTED, [FlowPolicy("a", "avg(l_quantity) < 28 and count(l_tax) > 5", (L,)), FlowPolicy("b", "max(orders.o_totalprice) < 499000", (O,))]),
    (NESTED, [FlowPolicy("a", "count(o_totalprice) > 400 and stddev(o_totalprice) < 146000", (O,))]),
    (LEFT, [FlowPolicy("a", "max(o_totalprice) < 495000 and count(*) > 1", (O,))]),
    (LEFT, [FlowPolicy("a", "min(c_acctbal) < 0", (C,)), FlowPolicy("b", "max(o_totalprice) < 495000", (SourceRef("orders", None, True),))]),
    (SEMI, [FlowPolicy("a", "count(*) > 150 and avg(l_quantity) < 26", (L,)), FlowPolicy("b", "sum(orders.o_orderkey) > 40000", (O,))]),
    (UNION, [FlowPolicy("a", "max(l_quantity) < 45", (L,)), FlowPolicy("b", "sum(c_acctbal) > 20000", (C,))]),
    (SELF, [FlowPolicy("a", "max(x.l_tax) + max(y.l_tax) < 0.1", (SourceRef("lineitem", "x"), SourceRef("lineitem", "y")))]),
    (KEYLESS, [FlowPolicy("a", "max(l_quantity) < 0", (L,))]),
    (KEYLESS, [FlowPolicy("a", "max(l_quantity) < 0", (SourceRef("lineitem", None, True),))]),
    (SELECTION, [FlowPolicy("a", "max(l_tax) < 0.05 and not unique orders.o_custkey or lineitem.l_tax <= 0.04", (L, O))]),
    (TOP, [FlowPolicy("a", "min(l_quantity) >= 10", (L,))]),
]


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in ("lineitem", "orders", "customer"):
        con.execute(f"create view {t} as select * from '/root/testdata/sf0.001/{t}.parquet'")
    return con


def _rows(rows):
    return sorted(tuple(round(float(v), 6) if isinstance(v, float) else str(v) for v in r) for r in rows)


@pytest.mark.parametrize("case", range(len(CASES)))
def test_text_in_another_engine_equals_the_guard(tables, duck, case):
    query, policies = CASES[case]
    schema_of = lambda t: tables.table(t).columns
    base = write_sql(query, [], schema_of)
    guarded = _rows(duck.execute(write_sql(query, policies, schema_of)).fetchall())
    assert guarded == _rows(map(tuple, Guard(tables, policies, linear_self_joins=False).query(base).collect()))
    assert guarded == _rows(map(tuple, tables.sql(write_sql(query, policies, schema_of)).collect()))
    if query is not KEYLESS:
        assert 0 < len(guarded) < len(duck.execute(base).fetchall())


def test_what_the_text_cannot_hold_is_refused(tables):
    schema_of = lambda t: tables.table(t).columns
    for constraint, sources in (("count(distinct l_suppkey) > 3", (L,)), ("median(l_tax) > 0", (L,)), ("max(o_totalprice + l_tax) > 0", (O, L))):
        with pytest.raises(UnsupportedPlan):
            write_sql(NESTED, [FlowPolicy("p", constraint, sources)], schema_of)


def test_the_other_engine_is_timed(tables):
    from tupleguard.workloads.experiments import other_engine

    assert [r["query"] for r in other_engine(tables, "/root/testdata/sf0.001", runs=1)] == ["grouped", "join", "nested", "semi"]
