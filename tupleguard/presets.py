"""Common policy classes as constructors."""

from __future__ import annotations

from .policy import KILL, REMOVE, Dimension, FlowPolicy, Resolution, SinkRef, SourceRef


def non_leakage(name: str, table: str, user: str, on_fail: Resolution = REMOVE) -> FlowPolicy:
    """Output rows mix more than one distinct user."""
    return FlowPolicy(name, f"NOT UNIQUE {table}.{user}", (SourceRef(table),), on_fail=on_fail)


def k_anonymous(name: str, table: str, user: str, k: int, on_fail: Resolution = REMOVE) -> FlowPolicy:
    return FlowPolicy(name, f"count(distinct {table}.{user}) > {k}", (SourceRef(table),), on_fail=on_fail)


def grounded(name: str, table: str, sink: str, pairs: dict[str, str], on_fail: Resolution = KILL) -> FlowPolicy:
    """Every written row derives from the table, with the sink's columns copied from one row."""
    body = " AND ".join(f"{table}.{s} = {sink}.{t}" for s, t in pairs.items())
    return FlowPolicy(name, body, (SourceRef(table, None, True),), SinkRef(sink), on_fail=on_fail)


def bounded(name: str, table: str, column: str, sink: str, out: str, factor: float, on_fail: Resolution = REMOVE) -> FlowPolicy:
    """The written value is at most ``factor`` times the largest contributing one."""
    return FlowPolicy(name, f"{sink}.{out} <= {factor} * max({table}.{column})", (SourceRef(table),), SinkRef(sink), on_fail=on_fail)


def disaggregated(name: str, table: str, column: str, on_fail: Resolution = REMOVE) -> FlowPolicy:
    """Never aggregate across the classes of a column."""
    return FlowPolicy(name, f"UNIQUE {table}.{column}", (SourceRef(table),), on_fail=on_fail)


def isolated(name: str, table: str, key: str, tenants: str, tenant_key: str, tenant: str, value: str, on_fail: Resolution = REMOVE) -> FlowPolicy:
    """All contributing rows belong to one tenant, the given one."""
    return FlowPolicy(name, f"tn.{tenant} = '{value}'", (SourceRef(table),), dimensions=(Dimension(tenants, "tn", f"{table}.{key} = tn.{tenant_key}"),), on_fail=on_fail)


def untrusted(name: str, table: str, key: str, labels: str, label_key: str, flag: str, sink: str | None = None, on_fail: Resolution = REMOVE) -> FlowPolicy:
    """No contributing row is flagged."""
    return FlowPolicy(
        name, f"max(coalesce(lb.{flag}, 0)) = 0", (SourceRef(table),), SinkRef(sink) if sink else None, (Dimension(labels, "lb", f"{table}.{key} = lb.{label_key}"),), on_fail
    )


def transition(name: str, table: str, key: str, state: str, moves: dict[str, tuple[str, ...]], on_fail: Resolution = REMOVE) -> FlowPolicy:
    """An update of the table moves its state only along the given edges."""
    whens = " ".join(f"WHEN old.{state} = '{a}' THEN new.{state} IN ({', '.join(repr(b) for b in bs)})" for a, bs in moves.items())
    return FlowPolicy(name, f"old.{key} = new.{key} AND CASE {whens} ELSE false END", (SourceRef(table, "old"),), SinkRef(table, "new"), on_fail=on_fail)


def covers(name: str, table: str, column: str, values: tuple, on_fail: Resolution = REMOVE) -> FlowPolicy:
    """Every output row draws on each of the column's listed classes."""
    return FlowPolicy(name, " AND ".join(f"bool_or({table}.{column} = {v!r})" for v in values), (SourceRef(table),), on_fail=on_fail)


def within(name: str, table: str, column: str, values: tuple, on_fail: Resolution = REMOVE) -> FlowPolicy:
    """All contributing rows are of the listed classes."""
    return FlowPolicy(name, f"bool_and(coalesce({table}.{column} IN ({', '.join(map(repr, values))}), false))", (SourceRef(table),), on_fail=on_fail)


def apart(name: str, one: str, other: str, on_fail: Resolution = REMOVE) -> FlowPolicy:
    """Each table may be read, but no output row may derive from both."""
    return FlowPolicy(name, "false", (SourceRef(one), SourceRef(other)), on_fail=on_fail)


def consented(name: str, one: str, other: str, key: str, consents: str, consent_key: str, given: str, on_fail: Resolution = REMOVE) -> FlowPolicy:
    """Rows of two tables meet only where a consent for ``one``'s key is on record and given."""
    return FlowPolicy(
        name, f"bool_and(coalesce(cs.{given}, false))", (SourceRef(one), SourceRef(other)), dimensions=(Dimension(consents, "cs", f"{one}.{key} = cs.{consent_key}"),), on_fail=on_fail
    )
