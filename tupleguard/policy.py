"""Flow policies: what is said about how output rows may be derived."""

from __future__ import annotations

from dataclasses import dataclass
from typing import Any

from . import expr as E

RESERVED = "__tg_"
OUTPUT = "_OUTPUT_"


@dataclass(frozen=True)
class SourceRef:
    table: str
    alias: str | None = None
    required: bool = False

    @property
    def name(self) -> str:
        return self.alias or self.table


@dataclass(frozen=True)
class Dimension:
    """A relation that constraints may read. ``on`` makes it keyed: an equality between a source
    attribute and the dimension's unique key."""

    table: str
    alias: str | None = None
    on: str | None = None

    @property
    def name(self) -> str:
        return self.alias or self.table


@dataclass(frozen=True)
class SinkRef:
    table: str
    alias: str | None = None

    @property
    def name(self) -> str:
        return self.alias or self.table


@dataclass(frozen=True)
class Resolution:
    """``remove``, ``kill``, or a registered function: of a tuple (``map``) or of the whole
    annotated relation (``relation``)."""

    kind: str
    name: str | None = None


REMOVE, KILL = Resolution("remove"), Resolution("kill")
#: Precedence: the lowest number wins.
RANK = {"kill": 0, "relation": 1, "remove": 2, "map": 3}


@dataclass(frozen=True)
class FlowPolicy:
    name: str
    constraint: str
    sources: tuple[SourceRef, ...] = ()
    sink: SinkRef | None = None
    dimensions: tuple[Dimension, ...] = ()
    on_fail: Resolution = REMOVE

    def __post_init__(self):
        if not self.sources and self.sink is None:
            raise ValueError("a policy without sources needs a sink")
        names = [s.name for s in self.sources] + [d.name for d in self.dimensions]
        if len({n.lower() for n in names}) != len(names):
            raise ValueError("aliases must differ")

    @property
    def tree(self) -> E.Node:
        return E.parse(self.constraint)

    @property
    def required(self) -> tuple[SourceRef, ...]:
        return tuple(s for s in self.sources if s.required)


_RESOLUTIONS: dict[str, tuple[str, Any, Any]] = {}
_PREDICATES: dict[str, Any] = {}


def register_resolution(name: str, fn, schema=None) -> Resolution:
    """Names a resolution. One whose parameter is called ``df`` or annotated as a DataFrame is a
    relation-level function; any other takes the output tuple's struct column and returns a
    struct column, null to drop the tuple."""
    import inspect

    params = list(inspect.signature(fn).parameters.values())
    note = str(params[0].annotation) if params else ""
    kind = "relation" if params and (params[0].name == "df" or "DataFrame" in note) else "map"
    _RESOLUTIONS[name.lower()] = (kind, fn, schema)
    return Resolution(kind, name)


def resolution_function(name: str):
    return _RESOLUTIONS[name.lower()]


def resolution_named(word: str) -> Resolution:
    low = word.lower()
    if low in ("remove", "kill"):
        return Resolution(low)
    kind = _RESOLUTIONS[low][0] if low in _RESOLUTIONS else "map"
    return Resolution(kind, word)


def register_predicate(spark, name: str, fn, returns: str = "boolean") -> None:
    """A user-supplied predicate (a model call, say) that constraints may name."""
    spark.udf.register(name, fn, returns)
    _PREDICATES[name.lower()] = fn


def rank_resolution(resolutions) -> Resolution:
    """The one of highest precedence; among equals the first."""
    return min(resolutions, key=lambda r: RANK[r.kind])
