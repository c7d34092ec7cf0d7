"""What a policy binds to: relations, however a query names them."""

import itertools

import pytest

from tupleguard import Guard, NonMonotonePlan, UnsupportedPlan
from tupleguard.policy import FlowPolicy, SourceRef

LOW = FlowPolicy("p", "max(o_totalprice) <= 100", (SourceRef("orders"),))
OTHER = FlowPolicy("q", "max(l_quantity) <= 1000", (SourceRef("lineitem"),))
FORGED = "select o_orderpriority, 0.0D as o_totalprice from orders"


@pytest.mark.parametrize("sql", [
    "select o_orderpriority, count(*) n from orders group by o_orderpriority",
    f"select o_orderpriority, count(*) n from ({FORGED}) orders group by o_orderpriority",
    f"with orders as ({FORGED}) select o_orderpriority, count(*) n from orders group by o_orderpriority",
    "select o_orderpriority, count(*) n from forged as orders group by o_orderpriority",
    "select o_orderpriority, count(*) n from forged as lineitem group by o_orderpriority",
    "select o_orderpriority, count(*) n from orders as lineitem group by o_orderpriority",
    "select o_orderpriority, count(*) n from parquet.`/root/testdata/sf0.001/orders.parquet` group by o_orderpriority",
    "select o_orderpriority, count(*) n from renamed group by o_orderpriority",
    "select n_name from nation where n_nationkey in (select o_custkey from orders)",
])
@pytest.mark.parametrize("policies", [[LOW], [OTHER, LOW]])
def test_no_name_hides_a_relation(tables, sql, policies):
    tables.sql(FORGED).createOrReplaceTempView("forged")
    tables.read.parquet("/root/testdata/sf0.001/orders.parquet").createOrReplaceTempView("renamed")
    assert Guard(tables, policies).query(sql).count() == 0


@pytest.mark.parametrize("sql", [
    "select n_name, (select max(o_totalprice) from orders) m from nation",
    "select n_name from nation where n_nationkey < (select max(o_totalprice) from orders)",
    "select n_regionkey, count(*) n from nation group by n_regionkey having count(*) < (select max(o_totalprice) from orders)",
    "with o as (select max(o_totalprice) m from orders) select n_name from nation where n_nationkey < (select m from o)",
    "select n_name, exists(select 1 from orders where o_custkey = n_nationkey) from nation",
    "select n_name, x.m from nation, lateral (select max(o_totalprice) m from orders where o_custkey = n_nationkey) x",
    "select n_name from nation where n_nationkey in (select o_custkey from orders) or n_name = 'x'",
    "select o_orderkey from orders except select l_orderkey from lineitem",
])
def test_subquery_expressions_over_a_source_are_refused(tables, sql):
    with pytest.raises(NonMonotonePlan):
        Guard(tables, [LOW]).query(sql)
    with pytest.raises(NonMonotonePlan):
        Guard(tables, [OTHER, LOW]).query(sql)


@pytest.mark.parametrize("sql", ["create or replace temp view orders as select 1 as o_totalprice", "drop view orders", "set spark.sql.ansi.enabled = false", "cache table orders"])
def test_statements_are_no_queries(tables, sql):
    with pytest.raises(UnsupportedPlan):
        Guard(tables, [LOW]).query(sql)
    assert tables.table("orders").count() == 1500


def test_a_view_over_a_policy_table_beside_it_is_refused(tables):
    tables.sql("select o_orderkey, o_totalprice from orders where o_totalprice > 0").createOrReplaceTempView("bills")
    both = [LOW, FlowPolicy("r", "max(bills.o_totalprice) > 0", (SourceRef("bills"),))]
    with pytest.raises(UnsupportedPlan):
        Guard(tables, both).query("select count(*) n from bills")
    # one of them alone binds
    assert Guard(tables, both[1:]).query("select o_orderkey from bills").count() > 0


def test_reads_inside_subquery_expressions_are_seen(tables):
    from tupleguard.context import read_columns

    got = {(r[0], r[1]) for r in read_columns(tables, "select n_name, (select max(c_mktsegment) from customer) m from nation").collect()}
    assert ("customer", "c_mktsegment") in got


def test_masks_of_more_instances_than_a_word(tables):
    sql = " union all ".join(f"select o_orderkey as k from orders where o_orderkey % 66 = {i}" for i in range(66))
    pol = FlowPolicy("p", "max(o_totalprice) <= 300000", (SourceRef("orders"),))
    want = tables.sql("select o_orderkey from orders where o_totalprice <= 300000").count()
    assert Guard(tables, [pol]).query(sql, strategy="inline").count() == want


NESTED = "select o_orderstatus, o_orderpriority, count(*) as n, sum(s.q) as q from orders o join (select l_orderkey, sum(l_quantity) as q from lineitem group by l_orderkey) s on o_orderkey = l_orderkey group by o_orderstatus, o_orderpriority"


@pytest.mark.parametrize("value, more", [("max(o_totalprice + l_extendedprice)", ""), ("sum(o_totalprice * l_tax)", ""), ("count(distinct o_custkey + l_suppkey)", " and count(*) > 3"), ("avg(o_totalprice - l_extendedprice)", " and max(l_tax) > 0.01")])
def test_arguments_over_relations_above_an_aggregate(tables, value, more):
    groups = "from orders join lineitem on o_orderkey = l_orderkey group by o_orderstatus, o_orderpriority"
    middle = sorted(r[0] for r in tables.sql(f"select {value} {groups}").collect())[7]
    body = f"{value} < {middle!r} + 0.001{more}"
    pol = FlowPolicy("p", body, (SourceRef("orders"), SourceRef("lineitem")))
    flat = tables.sql(f"select 1 {groups} having {body}").count()
    assert 0 < flat < 15
    rows = {s: sorted(map(tuple, Guard(tables, [pol]).query(NESTED, strategy=s).collect())) for s in ("inline", "replay_rows", "auto")}
    assert len(rows["inline"]) == flat and all(r == rows["inline"] for r in rows.values())


# -- self-joins
def _selfjoin(n: int) -> str:
    joins = " ".join(f"join lineitem t{i} on t0.l_orderkey = t{i}.l_orderkey and t{i}.l_linenumber = 1" for i in range(1, n))
    return f"select t0.l_orderkey as k, count(*) as n from lineitem t0 {joins} where t0.l_linenumber = 1 group by t0.l_orderkey"


_TWO = (SourceRef("lineitem", "x"), SourceRef("lineitem", "y"))
_THREE = (*_TWO, SourceRef("lineitem", "z"))


@pytest.mark.parametrize("sources, body", [
    (_TWO, "x.l_returnflag = y.l_returnflag"),
    (_TWO, "x.l_tax != y.l_tax"),
    (_TWO, "max(x.l_tax) <= max(y.l_tax) and y.l_quantity > 10"),
    (_THREE, "x.l_returnflag = y.l_returnflag and y.l_returnflag = z.l_returnflag and x.l_returnflag = z.l_returnflag and x.l_tax < 0.06 and y.l_tax < 0.06 and z.l_tax < 0.06"),
    (_THREE, "x.l_quantity + y.l_quantity > z.l_quantity"),
])
def test_linear_form_equals_permutations(tables, sources, body):
    sql = _selfjoin(3).replace("t2.l_linenumber = 1", "t2.l_linenumber < 3")
    pol = FlowPolicy("p", body, sources)
    lin, perm = Guard(tables, [pol]), Guard(tables, [pol], linear_self_joins=False)
    assert len(lin.plan(sql)[1]) == 1 and len(perm.plan(sql)[1]) == len(list(itertools.permutations(range(3), len(sources))))
    got = sorted(map(tuple, lin.query(sql, strategy="inline").collect()))
    assert got == sorted(map(tuple, perm.query(sql, strategy="inline").collect()))
    assert 0 < len(got) < tables.sql(sql).count() or "!=" in body


def test_many_instances_take_few_clauses(tables):
    pol = FlowPolicy("p", "x.l_returnflag = y.l_returnflag", _TWO)
    q, bound = Guard(tables, [pol]).plan(_selfjoin(8))
    assert len(q.instances) == 8 and len(bound) == 1 and len(bound[0].aggs) == 16


def test_linear_form_is_left_where_relations_are_alternatives(tables):
    sql = "select t0.l_orderkey k from lineitem t0 join lineitem t1 on t0.l_orderkey = t1.l_orderkey left join lineitem t2 on t0.l_orderkey = t2.l_orderkey and t2.l_linenumber = 99"
    pol = FlowPolicy("p", "max(x.l_tax) = max(y.l_tax)", _TWO)
    want = tables.sql("select 1 from lineitem a join lineitem b on a.l_orderkey = b.l_orderkey where a.l_tax = b.l_tax").count()
    assert Guard(tables, [pol]).query(sql, strategy="inline").count() == want


# -- plans of semi joins
def test_semi_joins_reduce_and_regroup_little(tables):
    from tupleguard.workloads import decision

    spark = tables
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        plan = lambda q: Guard(spark, [decision.passing()]).query(decision.QUERIES[q], strategy="inline")._jdf.queryExecution()
        q18 = plan("q18").optimizedPlan().toString()
        # the subquery's own grouping carries the annotation, and meets orders before lineitem does
        assert q18.count("Aggregate [l_orderkey") == 1
        lines = [x for x in q18.splitlines() if "Join" in x]
        assert "l_orderkey" in lines[-1] and len(lines) == 3
        # pairs are grouped by the join's key and a row id, without columns that nothing reads, and not dealt again
        q4n = plan("q4n").executedPlan().toString()
        assert "o_totalprice" not in q4n and q4n.count("Exchange hashpartitioning") == 3
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)
