"""Connected components of a link table by minimum-label propagation with pointer jumping.

Labels and links stay distributed; every round is a join, a pre-aggregated minimum and a
jump, cut by a table in the shared folder. Rounds needed grow with the logarithm of the
longest path."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from .state import keep, release

MAX_ROUNDS = 60


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """``links`` of longs to ``(id, component)``: each linked id and the smallest id reachable.

    Nulls and self links are ignored, repeats are fine, no link gives an empty table."""
    both = links.select(F.col(a).alias("u"), F.col(b).alias("v")).where("u <> v")
    edges = keep(both.union(both.select(F.col("v"), F.col("u"))).toDF("u", "v").distinct(), "cc-links")
    labels = keep(edges.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("id"), F.least("u", "m").alias("label")), "cc-labels")
    kept = labels
    for _ in range(MAX_ROUNDS):
        # what the neighbours offer; the smallest offer goes to the vertex and to its present root
        offer = edges.join(labels.withColumnRenamed("id", "v"), "v").groupBy("u").agg(F.min("label").alias("offer"))
        seen = labels.join(offer, labels["id"] == offer["u"]).select("id", "label", F.least("label", "offer").alias("best"))
        hooked = seen.select(F.col("id"), F.col("best")).union(seen.select("label", "best")).toDF("id", "best").groupBy("id").agg(F.min("best").alias("hook"))
        jump = hooked.select(F.col("id").alias("hook"), F.col("hook").alias("jump"))
        moved = labels.join(hooked, "id").join(jump, "hook", "left").select("id", F.col("label").alias("old"), F.least("hook", F.coalesce("jump", "hook")).alias("label"))
        moved = keep(moved, "cc-labels")
        changed = moved.where("label < old").limit(1).count()
        release(kept)
        kept, labels = moved, moved.select("id", "label")
        if not changed:
            release(edges)
            out = labels.withColumnRenamed("label", "component")
            out.kept_path = kept.kept_path
            return out
    raise RuntimeError("components did not settle")
