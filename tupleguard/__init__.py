"""Declarative policies about how output rows may be derived, enforced inside Spark plans."""

from .errors import (
    DimensionNotUnique, NonDeterministicPlan, NonMonotonePlan, PolicySyntaxError, PolicyViolation, ReservedName, SchemaMismatch, UnknownAttribute, UnsupportedPlan,
)
from .language import parse_policy, render_policy
from .policy import KILL, REMOVE, Dimension, FlowPolicy, SinkRef, SourceRef, register_predicate, register_resolution

__all__ = [
    "Dimension", "DimensionNotUnique", "FlowPolicy", "Guard", "KILL", "NonDeterministicPlan", "NonMonotonePlan", "PolicySyntaxError", "PolicyViolation", "REMOVE", "ReservedName", "SchemaMismatch",
    "SinkRef", "SourceRef", "UnknownAttribute", "UnsupportedPlan", "parse_policy", "register_predicate", "register_resolution", "render_policy",
]


def __getattr__(name: str):
    if name == "Guard":
        from .engine import Guard

        return Guard
    raise AttributeError(name)
