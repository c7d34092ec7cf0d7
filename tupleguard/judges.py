"""Judges that see only a query and a sample of its output: the baseline without provenance.

A judge function stands where a language model would; the rule judge here checks what is
visible and is never presented as a model's result."""

from __future__ import annotations

from typing import Callable, Sequence

from . import expr as E
from .policy import FlowPolicy


def output_judge(sql: str, sample: Sequence, policies: Sequence[FlowPolicy], judge_fn: Callable | None = None, query_only: bool = False) -> dict[str, bool]:
    """Policy name to whether the judge thinks that some row violates it; 100 rows are shown."""
    fn = judge_fn or rule_judge
    return {p.name: bool(fn(sql, [] if query_only else list(sample)[:100], p)) for p in policies}


def rule_judge(sql: str, rows: list, p: FlowPolicy) -> bool:
    """Says violation if an output column's values, taken at face value for the aggregate of the
    same attribute, break a threshold."""
    ops = {"<": lambda a, b: a < b, "<=": lambda a, b: a <= b, ">": lambda a, b: a > b, ">=": lambda a, b: a >= b, "=": lambda a, b: a == b, "!=": lambda a, b: a != b}
    for c in E.conjuncts(p.tree):
        if not (isinstance(c, E.Op) and c.op in ops and E.is_aggregate(c.args[0])):
            continue
        k = E.number(c.args[1])
        names = {a.name.lower() for a in E.attrs(c.args[0])}
        for r in rows:
            for col, v in r.asDict().items():
                close = col.lower() in names or any(n.endswith(col.lower()) or col.lower().endswith(n.split("_")[-1]) for n in names)
                if close and isinstance(v, (int, float)) and k is not None and not ops[c.op](v, k):
                    return True
    return False


def transition_judge(legal: set[tuple[str, str]]) -> Callable[[str, str], bool]:
    """A judge of state moves by a table of legal ones."""
    return lambda old, new: (old, new) in legal
