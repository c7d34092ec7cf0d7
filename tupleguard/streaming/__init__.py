"""Guarded streams: policy aggregates travel as further streaming aggregates of the same query.

The rewriting is the inline strategy's, on the stream's plan; uniqueness uses min and max, as
streams allow no distinct aggregates. Verdicts are final when a window closes, so guarded
aggregates belong to append mode. Late rows are dropped by the watermark before annotation."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from ..plan import QueryPlan, bind, alias_assignments
from .. import constraint, resolve
from ..errors import NonMonotonePlan, UnsupportedPlan
from ..strategies.inline import Annotator
from ..strategies.common import Annotated, mask_present, policy_values


def guard_stream(guard, source: DataFrame, build) -> DataFrame:
    """``build(source)`` guarded; the source is named by the first policy's table."""
    policies = [p for p in guard.policies if p.sink is None]
    name = policies[0].sources[0].table
    source.createOrReplaceTempView(name)
    df = build(guard.spark.table(name))
    query = QueryPlan(df, [s.table for p in policies for s in p.sources])
    bound = []
    for p in policies:
        form = constraint.analyze(p, lambda t: list(next(i.columns for i in query.instances if i.table == t.lower())))
        bound += [bind(p, form, w) for w in alias_assignments(p, query.instances)]
    query.check_monotone()
    if query.hidden:
        raise NonMonotonePlan(f"subquery expressions over {', '.join(sorted(query.hidden))}")
    an = Annotator(query, bound)
    # without aggregates below joins all multiplicities are 1 and need no streaming count
    if an.sumlike and _aggregate_below_join(query):
        raise UnsupportedPlan("stream", "sums over a join with an aggregate")
    an.sumlike = False
    st = an.visit(query.plan)
    values = policy_values(query, bound, st.cols, st.counted)
    a = Annotated(query, st.plan, an.base(st), values, st.mask, [mask_present(st.mask)] * len(bound))
    return resolve.apply(a, bound)


def _aggregate_below_join(query: QueryPlan) -> bool:
    b = query.bridge

    def look(node, below: bool) -> bool:
        k = b.kind(node)
        if below and k in ("Aggregate", "Distinct", "Deduplicate", "Intersect"):
            return True
        return any(look(c, below or k in ("Join", "Intersect")) for c in b.children(node))

    return look(query.plan, False)


def transition_stream(requests: DataFrame, legal: dict[str, tuple[str, ...]], start: str) -> DataFrame:
    """Stateful moves per key: rows ``(id, seq, old_state, new_state, accepted)``. Illegal requests
    leave the state and come out with ``accepted`` false (for a quarantine)."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def step(key, frames, state):
        now = state.get[0] if state.exists else start
        rows = []
        for pdf in frames:
            for seq, new in pdf.sort_values("seq")[["seq", "new_state"]].itertuples(index=False):
                ok = new in legal.get(now, ())
                rows.append((key[0], seq, now, new, ok))
                now = new if ok else now
        state.update((now,))
        yield pd.DataFrame(rows, columns=["id", "seq", "old_state", "new_state", "accepted"])

    shape = "id long, seq long, old_state string, new_state string, accepted boolean"
    return requests.groupBy("id").applyInPandasWithState(step, shape, "state string", "append", GroupStateTimeout.NoTimeout)


def micro_batch_guard(guard, source_name: str, sql: str, on_batch):
    """A ``foreachBatch`` function: each batch is queried through the guard, then handed on."""

    def run(batch: DataFrame, batch_id: int) -> None:
        batch.createOrReplaceTempView(source_name)
        on_batch(guard.query(batch.sparkSession.sql(sql)), batch_id)

    return run


__all__ = ["F", "guard_stream", "micro_batch_guard", "transition_stream"]
