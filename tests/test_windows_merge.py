"""Window functions under a guard on demand, and guarded merges."""

import pytest

from tupleguard import Guard, UnsupportedPlan
from tupleguard.errors import ConcurrentWrite, NonMonotonePlan, PolicyViolation
from tupleguard.policy import KILL, FlowPolicy, SinkRef, SourceRef
from tupleguard.sinks import VersionedTable

O = SourceRef("orders")


def _got(guard, sql):
    return sorted(map(tuple, guard.query(sql, strategy="inline", windows=True).collect()))


def test_windows_are_refused_unless_asked_for(tables):
    sql = "select o_orderkey, row_number() over (partition by o_custkey order by o_orderkey) as r from orders"
    for strategy in ("inline", "two_pass", "replay_rows", "auto"):
        with pytest.raises((NonMonotonePlan, UnsupportedPlan)):
            Guard(tables, [FlowPolicy("p", "max(o_totalprice) < 1", (O,))]).query(sql, strategy=strategy)


@pytest.mark.parametrize(
    "function,frame",
    [
        ("sum(o_orderkey) over (partition by o_custkey order by o_orderkey)", "partition by o_custkey order by o_orderkey"),
        ("sum(o_orderkey) over (partition by o_custkey order by o_orderkey rows between 1 preceding and current row)", "partition by o_custkey"),
        ("lag(o_orderkey) over (partition by o_custkey order by o_orderkey)", "partition by o_custkey"),
        ("rank() over (partition by o_custkey order by o_orderdate desc)", "partition by o_custkey order by o_orderdate desc rows between unbounded preceding and current row"),
        ("count(*) over ()", ""),
    ],
)
def test_a_row_derives_from_its_frame(tables, function, frame):
    for constraint in ("max(o_totalprice) < 450000", "count(*) <= 5 and avg(o_totalprice) < 300000", "count(distinct o_orderpriority) <= 3"):
        window = f"over ({frame})"
        test = {"max(o_totalprice) < 450000": f"max(o_totalprice) {window} < 450000", "count(*) <= 5 and avg(o_totalprice) < 300000": f"count(*) {window} <= 5 and avg(o_totalprice) {window} < 300000"}.get(constraint, f"size(collect_set(o_orderpriority) {window}) <= 3")
        sql = f"select o_orderkey, {function} as f from orders"
        want = tables.sql(f"select o_orderkey, f from (select o_orderkey, {function} as f, {test} as fine from orders) where fine")
        assert _got(Guard(tables, [FlowPolicy("p", constraint, (O,))]), sql) == sorted(map(tuple, want.collect()))


def test_functions_of_unlike_orders_share_the_partition_and_unlike_partitions_are_refused(tables):
    guard = Guard(tables, [FlowPolicy("p", "sum(o_totalprice) < 2000000", (O,))])
    sql = "select o_orderkey, row_number() over (partition by o_custkey order by o_orderkey) as a, row_number() over (partition by o_custkey order by o_orderdate, o_orderkey) as b from orders"
    want = tables.sql(sql.replace(" from ", ", sum(o_totalprice) over (partition by o_custkey) as t from ")).where("t < 2000000").drop("t")
    assert _got(guard, sql) == sorted(map(tuple, want.collect()))
    with pytest.raises(UnsupportedPlan):
        guard.query("select count(*) over (partition by o_custkey) as a, count(*) over (partition by o_orderstatus) as b from orders", strategy="inline", windows=True)


def test_windows_below_an_aggregate_keep_their_bags(tables):
    sql = "select o_orderstatus, count(*) as n from (select o_orderstatus, row_number() over (partition by o_custkey order by o_orderkey) as r from orders) where r = 1 group by o_orderstatus"
    want = tables.sql("select o_orderstatus, count(*) as n from (select o_orderstatus, o_totalprice as m, row_number() over (partition by o_custkey order by o_orderkey) as r from orders) where r = 1 group by o_orderstatus having max(m) < 499000")
    assert _got(Guard(tables, [FlowPolicy("p", "max(o_totalprice) < 499000", (O,))]), sql) == sorted(map(tuple, want.collect()))


SOURCE = "select * from values (1, 'x'), (2, 'bad'), (5, 'y'), (6, 'bad'), (cast(null as int), 'z') as v(id, state)"


@pytest.fixture
def merged(spark, tmp_path):
    spark.sql(SOURCE).createOrReplaceTempView("incoming")
    table = VersionedTable(spark, "items", f"file://{tmp_path}/items").create(spark.createDataFrame([(1, "a"), (2, "a"), (3, "a"), (None, "a")], "id int, state string"))
    return Guard(spark, [FlowPolicy("p", "max(incoming.state) <> 'bad'", (SourceRef("incoming"),), SinkRef("items"))]), table


KEEP = [(None, "a"), (2, "a"), (3, "a")]


@pytest.mark.parametrize(
    "matched,not_matched,want",
    [
        ("update", "insert", [*KEEP, (1, "x"), (5, "y"), (None, "z")]),
        ("update", "skip", [*KEEP, (1, "x")]),
        ("delete", "insert", [*KEEP, (5, "y"), (None, "z")]),
        ("delete", "skip", KEEP),
        ("keep", "insert", [*KEEP, (1, "a"), (5, "y"), (None, "z")]),
    ],
)
def test_merge(merged, matched, not_matched, want):
    guard, table = merged
    report = guard.merge(table, "id", "select id, state from incoming", matched, not_matched)
    assert sorted(map(str, map(tuple, table.read().collect()))) == sorted(map(str, want))
    assert report.violations == {"p": 2} and (report.rows_in, report.rows_written) == (5, 3)


def test_merges_that_fail_leave_the_table_as_it_was(merged, spark):
    guard, table = merged
    before = sorted(map(str, table.read().collect()))
    with pytest.raises(ConcurrentWrite):
        guard.merge(table, "id", "select 1 as id, 'q' as state union all select 1, 'r'")
    kill = Guard(spark, [FlowPolicy("p", "max(incoming.state) <> 'bad'", (SourceRef("incoming"),), SinkRef("items"), on_fail=KILL)])
    with pytest.raises(PolicyViolation):
        kill.merge(table, "id", "select id, state from incoming")
    assert sorted(map(str, table.read().collect())) == before
    # unknown keys may repeat, as nothing is matched
    guard.merge(table, "id", "select 9 as id, 'q' as state union all select 9, 'r'")
    assert table.read().where("id = 9").count() == 2


def test_sets_below_aggregates_hold_no_more_than_their_bounds_ask(tables):
    sql = "select c_nationkey, sum(x.n) as n from (select o_custkey, count(*) as n from orders join lineitem on o_orderkey = l_orderkey group by o_custkey) x join customer on c_custkey = x.o_custkey group by c_nationkey"
    flat = "select c_nationkey, count(*) as n from orders, lineitem, customer where o_orderkey = l_orderkey and c_custkey = o_custkey group by c_nationkey having "
    for constraint in ("count(distinct l_suppkey) > 9", "count(distinct l_suppkey) = 10 or count(distinct l_linenumber) <= 6.5", "count(distinct l_partkey) - 100 > count(distinct l_suppkey)", "6 < count(distinct l_linenumber)"):
        guarded = Guard(tables, [FlowPolicy("p", constraint, (SourceRef("lineitem"),))]).query(sql, strategy="inline")
        assert ("slice(" in guarded._jdf.queryExecution().optimizedPlan().toString()) == ("- 100" not in constraint)
        assert sorted(map(tuple, guarded.collect())) == sorted(map(tuple, tables.sql(flat + constraint).collect()))
