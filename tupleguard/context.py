"""Context relations that constraints may read as dimensions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .plan import QueryPlan


def session_frame(spark: SparkSession, **values) -> DataFrame:
    """One row: the current user and any further values."""
    extra = ", ".join(f"{v!r} as {k}" for k, v in values.items())
    return spark.sql(f"select current_user() as user_name{', ' + extra if extra else ''}")


def read_columns(spark: SparkSession, q) -> DataFrame:
    """``(table_name, column_name)``: the source columns that a query really reads."""
    df = spark.sql(q) if isinstance(q, str) else q
    query = QueryPlan(df)
    b = query.bridge
    used: set[int] = {a.exprId().id() for a in b.output(query.plan)}
    leaves = []

    def look(node):
        if b.kind(node) not in ("SubqueryAlias", "View"):
            for e in b.items(node.expressions()):
                if b.kind(node) == "Project" and b.kind(e) == "AttributeReference":
                    continue
                used.update(b.ids(e))
        _, names, inner = query.names(node)
        if not b.children(inner) and names:
            leaves.append((names[-1], b.output(node)))
            return
        for c in b.children(node):
            look(c)

    look(query.plan)
    for sub in b.items(query.plan.subqueriesAll()):
        used.update(a.exprId().id() for a in b.output(sub))
        look(sub)
    rows = sorted({(t, a.name()) for t, out in leaves for a in out if a.exprId().id() in used})
    return spark.createDataFrame(rows, "table_name string, column_name string")
