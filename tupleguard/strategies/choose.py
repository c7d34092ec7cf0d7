"""Which strategy a query gets: inline, unless the annotations are so wide over so large an
intermediate that a second scan of narrow rows is cheaper."""

from __future__ import annotations

from typing import Sequence

from ..plan import Bound, QueryPlan, all_components

#: Bytes of one carried component, and the width from which wide rows dominate a second scan.
COLUMN_BYTES, WIDE = 8, 1024


def choose_strategy(query: QueryPlan, bound: Sequence[Bound], fan_out: float = 1.0) -> str:
    comps, holistic = all_components(bound)
    if holistic:
        return "two_pass" if query.has("Aggregate") else "replay_rows"
    width = COLUMN_BYTES * len(comps)
    return "two_pass" if query.has("Aggregate") and query.has("Join") and width * max(1.0, fan_out) > WIDE else "inline"
