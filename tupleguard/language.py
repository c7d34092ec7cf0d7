"""The policy language: text to policy and back.

Clauses, in order: SOURCE [REQUIRED] table [AS alias], ... ; optional SINK table; optional
DIMENSION table [alias] [ON key equality], ... ; CONSTRAINT expression; ON FAIL REMOVE, KILL or
a function's name. Keywords inside quotes or parentheses are left alone."""

from __future__ import annotations

import re

from . import expr as E
from .errors import PolicySyntaxError
from .policy import Dimension, FlowPolicy, SinkRef, SourceRef, resolution_named

_CLAUSES = ("SOURCE", "SINK", "DIMENSION", "CONSTRAINT", "ON FAIL")
_SPLIT = re.compile(r"'(?:[^']|'')*'|`[^`]*`|\(|\)|\bSOURCE\b|\bSINK\b|\bDIMENSION\b|\bCONSTRAINT\b|\bON\s+FAIL\b", re.I)


def _clauses(text: str) -> dict[str, tuple[str, int]]:
    found, depth = [], 0
    for m in _SPLIT.finditer(text):
        token = m.group(0)
        if token == "(":
            depth += 1
        elif token == ")":
            depth -= 1
        elif token[0] not in "'`" and depth == 0:
            found.append((re.sub(r"\s+", " ", token.upper()), m.start(), m.end()))
    if not found or text[: found[0][1]].strip():
        raise PolicySyntaxError("expected SOURCE or SINK", 0)
    order = [_CLAUSES.index(f[0]) for f in found]
    for a, b, f in zip(order, order[1:], found[1:]):
        if b <= a:
            raise PolicySyntaxError(f"{f[0]} is out of place", f[1])
    ends = [f[1] for f in found[1:]] + [len(text)]
    return {name: (text[start:end].strip().rstrip(";").strip(), start) for (name, _, start), end in zip(found, ends)}


_ITEM = re.compile(r"^(REQUIRED\s+)?([\w.]+)(?:\s+(?:AS\s+)?(?!ON\b)(\w+))?(?:\s+ON\s+(.+))?$", re.I | re.S)


def _items(text: str, pos: int) -> list[re.Match]:
    out, depth, start = [], 0, 0
    for i, c in enumerate(text + ","):
        depth += (c == "(") - (c == ")")
        if c == "," and depth == 0:
            m = _ITEM.match(text[start:i].strip())
            if not m:
                raise PolicySyntaxError(f"bad relation {text[start:i].strip()!r}", pos + start)
            out.append(m)
            start = i + 1
    return out


def parse_policy(text: str, name: str = "policy") -> FlowPolicy:
    parts = _clauses(text)
    for need in ("CONSTRAINT", "ON FAIL"):
        if need not in parts:
            raise PolicySyntaxError(f"{need} is missing", len(text))
    body, pos = parts["CONSTRAINT"]
    try:
        E.parse(body)
    except PolicySyntaxError as e:
        raise PolicySyntaxError(str(e).rsplit(" (at", 1)[0], pos + e.pos) from None
    sources, dims, sink = [], [], None
    if "SOURCE" in parts:
        for m in _items(*parts["SOURCE"]):
            sources.append(SourceRef(m[2], m[3], bool(m[1])))
    if "SINK" in parts:
        m = _items(*parts["SINK"])[0]
        sink = SinkRef(m[2], m[3])
    if "DIMENSION" in parts:
        dims = [Dimension(m[2], m[3], m[4]) for m in _items(*parts["DIMENSION"])]
    word, at = parts["ON FAIL"]
    if not re.fullmatch(r"\w+", word):
        raise PolicySyntaxError(f"bad resolution {word!r}", at)
    return FlowPolicy(name, body, tuple(sources), sink, tuple(dims), resolution_named(word))


def render_policy(p: FlowPolicy) -> str:
    ref = lambda r: r.table + (f" AS {r.alias}" if r.alias else "")
    out = []
    if p.sources:
        out.append("SOURCE " + ", ".join(("REQUIRED " if s.required else "") + ref(s) for s in p.sources))
    if p.sink:
        out.append("SINK " + ref(p.sink))
    if p.dimensions:
        out.append("DIMENSION " + ", ".join(ref(d) + (f" ON {d.on}" if d.on else "") for d in p.dimensions))
    out += ["CONSTRAINT " + p.constraint, "ON FAIL " + (p.on_fail.name or p.on_fail.kind.upper())]
    return "\n".join(out)
