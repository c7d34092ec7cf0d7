"""Thirteen decision-support queries on the given tables, with a policy that never fails and one
that splits each query's output. Money is summed as whole cents times percents, so results are
exact in every engine."""

from __future__ import annotations

from ..policy import FlowPolicy, SourceRef

REV = "cast(round(l_extendedprice * 100) as bigint) * (100 - cast(round(l_discount * 100) as bigint))"
_L = (SourceRef("lineitem"),)

QUERIES = {
    "q1": "select l_returnflag, l_linestatus, sum(l_quantity) as sum_qty, sum(cast(round(l_extendedprice * 100) as bigint)) as sum_base, count(*) as n from lineitem where l_shipdate <= timestamp_ntz '2001-08-01 00:00:00' group by l_returnflag, l_linestatus",
    "q3": f"select o_orderkey, o_orderdate, sum({REV}) as revenue from customer join orders on c_custkey = o_custkey join lineitem on l_orderkey = o_orderkey where c_mktsegment = 'BUILDING' and o_orderdate < timestamp_ntz '1998-03-15 00:00:00' and l_shipdate > timestamp_ntz '1998-03-15 00:00:00' group by o_orderkey, o_orderdate",
    "q4": "select o_orderpriority, count(*) as n from orders where o_orderdate >= timestamp_ntz '1997-07-01 00:00:00' and o_orderdate < timestamp_ntz '1997-10-01 00:00:00' and exists (select 1 from lineitem where l_orderkey = o_orderkey and l_tax < l_discount) group by o_orderpriority",
    "q4n": "select o_orderpriority, count(*) as n from orders where o_orderdate >= timestamp_ntz '1997-07-01 00:00:00' and o_orderdate < timestamp_ntz '1997-10-01 00:00:00' and exists (select 1 from lineitem where l_orderkey = o_orderkey and l_shipdate > o_orderdate) group by o_orderpriority",
    "q5": f"select n_name, sum({REV}) as revenue from customer join orders on c_custkey = o_custkey join lineitem on l_orderkey = o_orderkey join supplier on l_suppkey = s_suppkey and c_nationkey = s_nationkey join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey where r_name = 'ASIA' and year(o_orderdate) = 1996 group by n_name",
    "q6": "select sum(cast(round(l_extendedprice * 100) as bigint) * cast(round(l_discount * 100) as bigint)) as revenue from lineitem where year(l_shipdate) = 1996 and l_discount between 0.045 and 0.075 and l_quantity < 24",
    "q7": f"select n1.n_name as supp_nation, n2.n_name as cust_nation, year(l_shipdate) as l_year, sum({REV}) as revenue from supplier join lineitem on s_suppkey = l_suppkey join orders on o_orderkey = l_orderkey join customer on c_custkey = o_custkey join nation n1 on s_nationkey = n1.n_nationkey join nation n2 on c_nationkey = n2.n_nationkey where ((n1.n_name = 'NATION_6' and n2.n_name = 'NATION_7') or (n1.n_name = 'NATION_7' and n2.n_name = 'NATION_6')) and year(l_shipdate) between 1995 and 1996 group by n1.n_name, n2.n_name, year(l_shipdate)",
    "q8": f"select year(o_orderdate) as o_year, sum(case when n2.n_name = 'NATION_6' then {REV} else 0 end) as nation_rev, sum({REV}) as total_rev from part join lineitem on p_partkey = l_partkey join supplier on s_suppkey = l_suppkey join orders on l_orderkey = o_orderkey join customer on o_custkey = c_custkey join nation n1 on c_nationkey = n1.n_nationkey join region on n1.n_regionkey = r_regionkey join nation n2 on s_nationkey = n2.n_nationkey where r_name = 'AMERICA' and year(o_orderdate) between 1995 and 1996 and p_type = 'ECONOMY' group by year(o_orderdate)",
    "q9": f"select n_name, year(o_orderdate) as o_year, sum({REV}) as profit from part join lineitem on p_partkey = l_partkey join supplier on s_suppkey = l_suppkey join orders on o_orderkey = l_orderkey join nation on s_nationkey = n_nationkey where p_name like '%red%' group by n_name, year(o_orderdate)",
    "q10": f"select c_custkey, c_name, sum({REV}) as revenue from customer join orders on c_custkey = o_custkey join lineitem on l_orderkey = o_orderkey where o_orderdate >= timestamp_ntz '1996-10-01 00:00:00' and o_orderdate < timestamp_ntz '1997-01-01 00:00:00' and l_returnflag = 'R' group by c_custkey, c_name",
    "q12": "select l_linestatus, sum(case when o_orderpriority in ('1-URGENT', '2-HIGH') then 1 else 0 end) as high_lines, sum(case when o_orderpriority not in ('1-URGENT', '2-HIGH') then 1 else 0 end) as low_lines from orders join lineitem on o_orderkey = l_orderkey where year(l_shipdate) = 1996 and l_shipdate > o_orderdate group by l_linestatus",
    "q14": f"select sum(case when p_type = 'PROMO' then {REV} else 0 end) as promo, sum({REV}) as total from lineitem join part on l_partkey = p_partkey where l_shipdate >= timestamp_ntz '1995-09-01 00:00:00' and l_shipdate < timestamp_ntz '1995-10-01 00:00:00'",
    "q18": "select c_name, c_custkey, o_orderkey, sum(l_quantity) as qty from customer join orders on c_custkey = o_custkey join lineitem on o_orderkey = l_orderkey where o_orderkey in (select l_orderkey from lineitem group by l_orderkey having sum(l_quantity) > 250) group by c_name, c_custkey, o_orderkey",
    "q19": f"select sum({REV}) as revenue from lineitem join part on p_partkey = l_partkey where (p_brand = 'Brand#12' and l_quantity between 1 and 25 and p_size between 1 and 25) or (p_brand = 'Brand#23' and l_quantity between 10 and 35 and p_size between 1 and 40) or (p_brand = 'Brand#4' and l_quantity between 20 and 45 and p_size between 1 and 50)",
}

#: Constraints over lineitem that split each output.
SPLITS = {
    "q1": "avg(l_quantity) <= 25.42", "q3": "max(l_quantity) <= 40", "q4": "avg(l_quantity) <= 25.4", "q4n": "avg(l_quantity) <= 25.5", "q5": "count(*) >= 20", "q6": "max(l_quantity) < 23",
    "q7": "count(*) >= 25", "q8": "avg(l_quantity) <= 25.5", "q9": "avg(l_quantity) <= 25.5", "q10": "count(*) >= 2", "q12": "avg(l_quantity) <= 25.5", "q14": "max(l_quantity) < 50",
    "q18": "min(l_quantity) >= 5", "q19": "max(l_quantity) < 45",
}


#: Bounds that keep the one row of the queries without keys.
KEPT = {"q6": "max(l_quantity) < 24", "q14": "max(l_quantity) <= 50", "q19": "max(l_quantity) <= 45"}


def passing() -> FlowPolicy:
    """The policy that no row breaks."""
    return FlowPolicy("min_qty", "max(l_quantity) >= 1", _L)


def splitting(q: str) -> FlowPolicy:
    return FlowPolicy(f"split_{q}", SPLITS[q], _L)


def keeping(q: str) -> FlowPolicy:
    return FlowPolicy(f"keep_{q}", KEPT[q], _L)


def many(n: int, q: str = "q1") -> list[FlowPolicy]:
    """``n`` threshold policies on lineitem, about half of them violated."""
    out = []
    for i in range(n):
        agg, col, lo, hi = (("avg", "l_quantity", 20, 31), ("min", "l_quantity", 0, 2), ("max", "l_quantity", 45, 55), ("count", "l_quantity", 1, 10**9))[i % 4]
        op = ">=" if i % 2 else "<="
        k = lo if (i // 4 + i) % 2 == 0 else hi
        out.append(FlowPolicy(f"p{i}", f"{agg}({col}) {op} {k + i / 1000}", _L))
    return out
