"""Cost and accuracy measures."""

from __future__ import annotations

import statistics
import time
from dataclasses import dataclass

from pyspark.sql import DataFrame


@dataclass
class Timing:
    runs: list[float]

    @property
    def mean(self) -> float:
        return statistics.mean(self.runs)

    @property
    def median(self) -> float:
        return statistics.median(self.runs)


def force(df: DataFrame) -> None:
    df.write.format("noop").mode("overwrite").save()


def timed_runs(fn, runs: int = 5, warmup: int = 1) -> Timing:
    """Wall seconds of ``fn() -> DataFrame`` forced through the noop sink."""
    out = []
    for i in range(runs + warmup):
        start = time.perf_counter()
        force(fn())
        if i >= warmup:
            out.append(time.perf_counter() - start)
    return Timing(out)


def relative_overhead(base: float, guarded: float) -> float:
    return (guarded - base) / base


overhead = relative_overhead


@dataclass
class Scores:
    precision: float
    recall: float
    f1: float
    tp: int
    fp: int
    fn: int


def verdict_f1(expected: set, predicted: set) -> Scores:
    """Over (query, policy) pairs that are said to violate."""
    tp, fp, fn = len(expected & predicted), len(predicted - expected), len(expected - predicted)
    p = tp / (tp + fp) if tp + fp else 1.0
    r = tp / (tp + fn) if tp + fn else 1.0
    return Scores(p, r, 2 * p * r / (p + r) if p + r else 0.0, tp, fp, fn)


def transition_counts(expected: list[bool], allowed: list[bool]) -> dict[str, int]:
    pairs = list(zip(expected, allowed))
    return {"valid_allowed": pairs.count((True, True)), "valid_stopped": pairs.count((True, False)), "invalid_allowed": pairs.count((False, True)), "invalid_stopped": pairs.count((False, False))}


def plan_counters(df: DataFrame) -> dict[str, int]:
    """Figures of the executed plan: scans, exchanges, joins, the widest operator's rows."""
    jdf = df._jdf
    qe = jdf.queryExecution()
    qe.toRdd().count()
    out = {"scans": 0, "exchanges": 0, "joins": 0, "widest_rows": 0, "shuffle_bytes": 0, "spill_bytes": 0}

    def walk(p):
        name = p.getClass().getSimpleName()
        if name == "AdaptiveSparkPlanExec":
            return walk(p.executedPlan())
        if name.endswith("QueryStageExec"):
            return walk(p.plan())
        out["scans"] += "Scan" in name
        out["exchanges"] += name == "ShuffleExchangeExec"
        out["joins"] += "Join" in name
        m = p.metrics()
        for key, to, how in (("numOutputRows", "widest_rows", max), ("dataSize", "shuffle_bytes", int.__add__), ("spillSize", "spill_bytes", int.__add__)):
            got = m.get(key)
            if got.isDefined():
                out[to] = how(out[to], int(got.get().value()))
        kids = p.children()
        for i in range(kids.size()):
            walk(kids.apply(i))

    walk(qe.executedPlan())
    return out


def derivation_count(guard, q, strategy: str = "replay_rows") -> int:
    """Monomials over all output rows: rows of the widened output."""
    from .strategies.replay_rows import Widener

    query, bound = guard.plan(q)
    w = Widener(query, bound).visit(query.plan)
    return query.bridge.frame(w.plan).count()


def leaf_count(polynomial) -> int:
    """Leaves of a provenance expression given as nested tuples: a plan-dependent quantity."""
    return sum(map(leaf_count, polynomial[1:])) if isinstance(polynomial, tuple) else 1
