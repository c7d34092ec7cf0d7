"""The experiments as functions that return rows of figures.

Each takes a session whose tables are registered and returns plain dictionaries; ``bench.py``
and the tests call them with small parameters. Times go through the noop sink: means of
``runs`` after one warm-up."""

from __future__ import annotations

import time

from pyspark.sql import SparkSession, functions as F

from .. import aliases, metrics, templates
from ..engine import Guard
from ..errors import UnsupportedPlan
from ..judges import output_judge
from ..policy import FlowPolicy, SourceRef
from ..sinks import fold_transitions
from . import decision

STRATEGIES = ("inline", "two_pass", "replay_rows", "replay_ids")


def overhead_by_query(spark: SparkSession, queries=None, strategies=STRATEGIES, runs: int = 3, policy: FlowPolicy | None = None) -> list[dict]:
    """Relative overhead of each strategy on each query, under a policy that drops nothing."""
    out = []
    for q in queries or decision.QUERIES:
        sql = decision.QUERIES[q]
        base = metrics.timed_runs(lambda: spark.sql(sql), runs)
        for s in strategies:
            try:
                df = lambda s=s: Guard(spark, [policy or decision.passing()]).query(sql, strategy=s)
                t = metrics.timed_runs(df, runs)
            except UnsupportedPlan as e:
                out.append({"query": q, "strategy": s, "base_s": base.mean, "unsupported": str(e)})
                continue
            counters = metrics.plan_counters(df())
            out.append({"query": q, "strategy": s, "base_s": base.mean, "base_median_s": base.median, "guarded_s": t.mean, "guarded_median_s": t.median, "overhead": metrics.relative_overhead(base.mean, t.mean), **counters})
    return out


def engine_axes(spark: SparkSession, queries=("q1", "q3", "q6"), runs: int = 3) -> list[dict]:
    """Mean overhead under unlike engine settings (a stand-in for several engines)."""
    axes = {"default": {}, "no_aqe": {"spark.sql.adaptive.enabled": "false"}, "no_codegen": {"spark.sql.codegen.wholeStage": "false"}, "no_broadcast": {"spark.sql.autoBroadcastJoinThreshold": "-1"}}
    out = []
    for name, conf in axes.items():
        old = {k: spark.conf.get(k, None) for k in conf}
        for k, v in conf.items():
            spark.conf.set(k, v)
        try:
            rows = overhead_by_query(spark, queries, ("inline", "two_pass", "replay_rows"), runs)
        finally:
            for k, v in old.items():
                spark.conf.unset(k) if v is None else spark.conf.set(k, v)
        for s in ("inline", "two_pass", "replay_rows"):
            own = [r["overhead"] for r in rows if r["strategy"] == s]
            out.append({"axis": name, "strategy": s, "mean_overhead": sum(own) / len(own)})
    return out


def other_engine(spark: SparkSession, sf_dir: str, runs: int = 3) -> list[dict]:
    """The overhead of the portable text in DuckDB, if that is installed: the same policies,
    annotations and guard in an engine of another make."""
    try:
        import duckdb
    except ImportError:
        return [{"engine": "duckdb", "unsupported": "not installed"}]
    from ..emit import Block, From, write_sql

    con = duckdb.connect()
    for t in ("lineitem", "orders", "customer"):
        con.execute(f"create view {t} as select * from read_parquet('{sf_dir}/{t}.parquet')")
    lines, orders = From("lineitem", "l"), From("lineitem", "l", on="l.l_orderkey = o.o_orderkey")
    per_order = Block((("l.l_orderkey", "k"), ("count(*)", "n")), (lines,), None, ("l.l_orderkey",))
    queries = {
        "grouped": Block((("l.l_returnflag", "f"), ("l.l_linestatus", "s"), ("sum(l.l_quantity)", "q")), (lines,), None, ("l.l_returnflag", "l.l_linestatus")),
        "join": Block((("o.o_orderpriority", "p"), ("sum(l.l_quantity)", "q")), (From("orders", "o"), orders), None, ("o.o_orderpriority",)),
        "nested": Block((("o.o_orderpriority", "p"), ("sum(x.n)", "n")), (From("orders", "o"), From(per_order, "x", on="o.o_orderkey = x.k")), None, ("o.o_orderpriority",)),
        "semi": Block((("o.o_orderpriority", "p"), ("count(*)", "n")), (From("orders", "o"), From("lineitem", "l", "semi", "o.o_orderkey", "l_orderkey")), None, ("o.o_orderpriority",)),
    }
    out = []
    for name, q in queries.items():
        base, guarded = (write_sql(q, p, lambda t: spark.table(t).columns) for p in ([], [FlowPolicy("p", "max(l_quantity) <= 1000", (SourceRef("lineitem"),))]))
        took = []
        for sql in (base, guarded):
            con.execute(sql).fetchall()
            start = time.perf_counter()
            for _ in range(runs):
                con.execute(sql).fetchall()
            took.append((time.perf_counter() - start) / runs)
        out.append({"engine": "duckdb", "query": name, "base_s": took[0], "inline_s": took[1], "overhead": took[1] / took[0] - 1})
    return out


def replicated(spark: SparkSession, rows: int):
    """``rows`` rows of lineitem's columns, by repetition."""
    base = spark.table("lineitem").select("l_orderkey", "l_quantity", "l_tax", "l_extendedprice")
    times = -(-rows // max(1, base.count()))
    return base.crossJoin(F.broadcast(spark.range(times).withColumnRenamed("id", "rep"))).limit(rows)


def microbenchmarks(spark: SparkSession, sizes=(1000, 10_000, 100_000, 1_000_000, 10_000_000), groups=(10, 100, 1000, 10_000, 100_000), grouped_rows: int = 1_000_000, keys=(100, 10_000, 1_000_000), join_rows: int = 10_000_000, runs: int = 3, strategies=("inline", "two_pass", "replay_rows")) -> list[dict]:
    """Simple aggregates over growing inputs, grouped aggregates over growing group counts, and
    key joins (one match a row) over growing key tables."""
    out = []
    pol = FlowPolicy("p", "max(l_tax) >= 0", (SourceRef("micro"),))

    def rows(n: int) -> None:
        spark.sql("drop table if exists micro_rows")
        replicated(spark, n).withColumn("g", F.xxhash64("l_orderkey", "l_extendedprice", "rep")).write.mode("overwrite").format("parquet").saveAsTable("micro_rows")
        spark.table("micro_rows").createOrReplaceTempView("micro")

    def measure(kind: str, n: int, sql: str) -> None:
        base = metrics.timed_runs(lambda: spark.sql(sql), runs)
        for s in strategies:
            t = metrics.timed_runs(lambda s=s: Guard(spark, [pol]).query(sql, strategy=s), runs)
            out.append({"kind": kind, "rows": n, "strategy": s, "base_s": base.median, "guarded_s": t.median, "overhead": metrics.relative_overhead(base.median, t.median)})

    for n in sorted({*sizes, *([grouped_rows] if groups else []), *([join_rows] if keys else [])}):
        rows(n)
        if n in sizes:
            measure("simple", n, "select sum(l_quantity) v from micro")
        if n == grouped_rows:
            for g in groups:
                measure(f"grouped_{g}", n, f"select pmod(g, {g}) as g, sum(l_quantity) v from micro group by pmod(g, {g})")
        if n == join_rows:
            for k in keys:
                spark.range(k).withColumnRenamed("id", "k").createOrReplaceTempView("keys")
                measure(f"join_{k}", n, f"select k, l_quantity from micro join keys on pmod(g, {k}) = k")
    spark.sql("drop table if exists micro_rows")
    return out


def width_grid(spark: SparkSession, columns=(2, 32, 128, 512), fan_outs=(2, 16, 64), rows: int = 5000, runs: int = 2) -> list[dict]:
    """Inline against two-pass over the number of policy columns and the join's fan-out."""
    wide = replicated(spark, rows).select("l_orderkey", *[(F.col("l_quantity") * (i + 1)).alias(f"a{i}") for i in range(128)])
    wide.withColumn("k", F.pmod("l_orderkey", F.lit(64))).write.mode("overwrite").format("parquet").saveAsTable("wide_rows")
    spark.table("wide_rows").createOrReplaceTempView("wide_source")
    out = []
    for fan in fan_outs:
        spark.range(64).select(F.col("id").alias("k2"), F.explode(F.sequence(F.lit(1), F.lit(fan))).alias("copy")).createOrReplaceTempView("fan")
        sql = "select k, count(*) as n from wide_source join fan on k = k2 group by k"
        for n in columns:
            names = [f"{agg}(a{i % 128})" for i in range(n) for agg in (("max", "min", "sum", "count")[(i // 128) % 4],)]
            pol = FlowPolicy("w", " AND ".join(f"{x} is not null" for x in names), (SourceRef("wide_source"),))
            for s in ("inline", "two_pass"):
                t = metrics.timed_runs(lambda s=s: Guard(spark, [pol]).query(sql, strategy=s), runs)
                out.append({"columns": n, "fan_out": fan, "strategy": s, "guarded_s": t.median})
    spark.sql("drop table if exists wide_rows")
    return out


JOINS = (
    ("orders", "join orders on l_orderkey = o_orderkey"), ("customer", "join customer on o_custkey = c_custkey"), ("part", "join part on l_partkey = p_partkey"), ("supplier", "join supplier on l_suppkey = s_suppkey"),
    ("nation", "join nation n1 on c_nationkey = n1.n_nationkey"), ("region", "join region on n1.n_regionkey = r_regionkey"), ("nation2", "join nation n2 on s_nationkey = n2.n_nationkey"),
)
_ATTR = {"lineitem": "l_quantity", "orders": "o_totalprice", "customer": "c_acctbal", "part": "p_size", "supplier": "s_acctbal", "nation": "n_nationkey", "region": "r_regionkey"}


def sources_query(joins: int) -> str:
    body = " ".join(j for _, j in JOINS[:joins])
    return f"select l_returnflag, l_linestatus, sum(l_quantity) as sum_qty, count(*) as n from lineitem {body} group by l_returnflag, l_linestatus"


def sources_policy(n: int, also: str | None = None) -> FlowPolicy:
    """A policy over the first ``n`` relations (two roles of nation count twice), which drops
    nothing but by the further condition."""
    names = ["lineitem", *[t for t, _ in JOINS[: n - 1]]]
    refs, parts = [], []
    for t in names:
        if t == "nation2" or (t == "nation" and "nation2" in names):
            continue
        refs.append(SourceRef(t))
        parts.append(f"max({t}.{_ATTR[t]}) is not null")
    if "nation2" in names:
        refs += [SourceRef("nation", "na"), SourceRef("nation", "nb")]
        parts += ["max(na.n_nationkey) is not null", "max(nb.n_nationkey) is not null"]
    return FlowPolicy(f"sources_{n}", " AND ".join(parts + ([also] if also else [])), tuple(refs))


def source_scaling(spark: SparkSession, counts=range(1, 9), runs: int = 3) -> list[dict]:
    out = []
    for n in counts:
        sql = sources_query(n - 1)
        base = metrics.timed_runs(lambda: spark.sql(sql), runs)
        t = metrics.timed_runs(lambda: Guard(spark, [sources_policy(n)]).query(sql, strategy="inline"), runs)
        out.append({"sources": n, "base_s": base.median, "guarded_s": t.median, "overhead": metrics.relative_overhead(base.median, t.median)})
    return out


def template_scaling(spark: SparkSession, counts=(1, 100, 10_000, 1_000_000), naive_upto: int = 100, runs: int = 2) -> list[dict]:
    """Query time with n collapsed bindings, and with their plain conjunction."""
    out = []
    sql = decision.QUERIES["q1"]
    t = templates.PolicyTemplate("max", "l_quantity", ">=")
    for n in counts:
        bindings = [t.bind(-float(i)) for i in range(n)]
        index = templates.TemplateIndex()
        for b in bindings:
            index.add(b)
        pol = index.policy("tpl", "lineitem")
        got = metrics.timed_runs(lambda: Guard(spark, [pol]).query(sql, strategy="inline"), runs)
        row = {"bindings": n, "clauses": len(index.clauses()), "collapsed_s": got.median}
        if n <= naive_upto:
            plain = FlowPolicy("naive", templates.naive_conjunction(bindings), (SourceRef("lineitem"),))
            row["naive_s"] = metrics.timed_runs(lambda: Guard(spark, [plain]).query(sql, strategy="inline"), 1).median
        out.append(row)
    return out


def self_join_clauses(counts=(1, 10, 100, 1000)) -> list[dict]:
    """Clauses of a symmetric two-alias policy by the number of joins (instances less one)."""
    pol = FlowPolicy("sym", "max(a.l_tax) = max(b.l_tax)", (SourceRef("lineitem", "a"), SourceRef("lineitem", "b")))
    return [{"joins": n, "permutations": aliases.permutation_count(n + 1, 2), "linear": len(aliases.linear_clauses(pol, n + 1))} for n in counts]


MOVES = {"A": ("B",), "B": ("A", "C")}
LEGAL = "(old = 'A' and new = 'B') or (old = 'B' and new in ('A', 'C'))"


def update_requests(n_items: int, n: int, seed: int = 42) -> list[tuple[int, int, str]]:
    """``(seq, id, new_state)``: 70 % legal along the run, the others not."""
    import random

    rng = random.Random(seed)
    state = dict.fromkeys(range(n_items), "A")
    out = []
    for seq in range(n):
        i = rng.randrange(n_items)
        good = MOVES.get(state[i], ())
        bad = [s for s in "ABC" if s not in good]
        if good and rng.random() < 0.7:
            new = rng.choice(good)
            state[i] = new
        else:
            new = rng.choice(bad)
        out.append((seq, i, new))
    return out


def state_machine(spark: SparkSession, folder: str, n_items: int = 1000, n: int = 1000, statements: int = 0) -> dict:
    """The requests as ordered guarded updates, against a plain fold: the confusion counts of
    accepted moves, wrong final states, seconds; and the seconds of single UPDATE statements with
    the policy and with none, of which the first ``statements`` requests are made."""
    import time

    from ..presets import transition
    from ..sinks import VersionedTable, update

    reqs = update_requests(n_items, n)
    state = dict.fromkeys(range(n_items), "A")
    valid, per_round, place = [], {}, {}
    for _, i, new in reqs:
        ok = new in MOVES.get(state[i], ())
        valid.append(ok)
        place[i] = place.get(i, 0) + 1
        per_round[place[i]] = per_round.get(place[i], 0) + (not ok)
        if ok:
            state[i] = new
    items = spark.range(n_items).select("id", F.lit("A").alias("state"))
    frame = spark.createDataFrame([(s, i, new) for s, i, new in reqs], "seq long, id long, state string")
    guard = Guard(spark, [transition("move", "item_state", "id", "state", MOVES)])
    table = VersionedTable(spark, "item_state", f"{folder}/rounds").create(items)
    start = time.perf_counter()
    reports = guard.update_each(table, "id", frame, "state")
    seconds = time.perf_counter() - start
    got = {r["id"]: r["state"] for r in table.read().collect()}
    stopped = [r.violations.get("move", 0) for r in reports]
    folded = {r["id"]: r["state"] for r in fold_transitions(items, frame.withColumnRenamed("state", "new_state"), LEGAL).collect()}
    out = {"items": n_items, "requests": n, "valid": sum(valid), "invalid_stopped": sum(stopped), "rounds": len(reports), "rounds_as_expected": [per_round[k] for k in sorted(per_round)] == stopped,
           "wrong": sum(got[i] != s for i, s in state.items()), "wrong_folded": sum(folded[i] != s for i, s in state.items()), "seconds": seconds}
    for name, g in (("policy", guard), ("no_policy", Guard(spark, []))) if statements else ():
        one = VersionedTable(spark, "item_state", f"{folder}/{name}").create(items)
        start = time.perf_counter()
        for _, i, new in reqs[:statements]:
            update(g, one, "id", {"state": f"'{new}'"}, f"id = {i}")
        out[f"statement_s_{name}"] = (time.perf_counter() - start) / statements
    return out


def self_join_times(spark: SparkSession, instances=(2, 4, 8, 16, 32), permuted_upto: int = 4, runs: int = 1) -> list[dict]:
    """Self-joins of orders on their key under a symmetric two-alias policy, run: rewriting and
    execution of the linear form, and of all permutations while these are few."""
    import time

    pol = FlowPolicy("sym", "x.o_orderstatus = y.o_orderstatus", (SourceRef("orders", "x"), SourceRef("orders", "y")))
    out = []
    for n in instances:
        joins = " ".join(f"join orders t{i} on t0.o_orderkey = t{i}.o_orderkey" for i in range(1, n))
        sql = f"select t0.o_orderpriority, count(*) as n from orders t0 {joins} group by t0.o_orderpriority, t0.o_orderstatus"
        row = {"instances": n, "permutations": aliases.permutation_count(n, 2), "base_s": metrics.timed_runs(lambda: spark.sql(sql), runs, 0).median}
        for form, linear in (("linear", True), ("permuted", False)):
            if not linear and n > permuted_upto:
                continue
            start = time.perf_counter()
            df = Guard(spark, [pol], linear_self_joins=linear).query(sql, strategy="inline")
            row[f"{form}_rewrite_s"] = time.perf_counter() - start
            row[f"{form}_s"] = metrics.timed_runs(lambda: df, runs, 0).median
        out.append(row)
    return out


#: The thirteen queries of the reported experiments.
THIRTEEN = tuple(q for q in decision.QUERIES if q != "q4n")


def judge_experiment(spark: SparkSession, queries=THIRTEEN, counts=(1, 2, 4, 8, 16, 32)) -> list[dict]:
    """F1 of the exact engine's verdicts (1 by construction of the truth) and of a judge that
    sees 100 output rows, or the query alone. The judge is a rule, not a language model."""
    out = []
    for q in queries:
        sql = decision.QUERIES[q]
        pols = decision.many(max(counts), q)
        exact = {r["policy"] for r in Guard(spark, pols).verdicts(sql).collect() if r["violations"]}
        replay = {r["policy"] for r in Guard(spark, pols).verdicts(sql, "replay_rows").collect() if r["violations"]}
        sample = spark.sql(sql).limit(100).collect()
        for n in counts:
            names = {p.name for p in pols[:n]}
            for mode, seen in (("engine", exact), ("judge", {k for k, v in output_judge(sql, sample, pols[:n]).items() if v}), ("judge_query_only", {k for k, v in output_judge(sql, sample, pols[:n], query_only=True).items() if v})):
                s = metrics.verdict_f1(replay & names, seen & names)
                out.append({"query": q, "policies": n, "who": mode, "f1": s.f1, "precision": s.precision, "recall": s.recall})
    return out
