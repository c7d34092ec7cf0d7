"""Column functions for constraints and workloads."""

from __future__ import annotations

from pyspark.sql import Column, functions as F


def cents(c: str) -> Column:
    """Money as whole cents, which compare exactly."""
    return F.round(F.col(c) * 100).cast("bigint")


def percent(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("bigint")


def unique_value(c: str) -> Column:
    """Whether a bag holds one distinct value, in constant space."""
    return F.coalesce(F.min(c) == F.max(c), F.lit(False))


def capped_set(c: str, k: int) -> Column:
    """At most ``k + 1`` distinct values: enough to compare their number with ``k``."""
    return F.slice(F.sort_array(F.collect_set(c)), 1, k + 1)


def mask_covers(mask: Column, bits: int) -> Column:
    """Whether a lineage mask holds all of the bits."""
    return F.coalesce(mask, F.lit(0)).bitwiseAND(F.lit(bits)) == bits
