"""A thin bridge to Catalyst: analyzed plans are walked, rebuilt and turned back into
DataFrames, so that the base query keeps its own resolved expressions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

_LOGICAL = "org.apache.spark.sql.catalyst.plans.logical"


class Bridge:
    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.jvm = spark.sparkContext._jvm
        self.session = spark._jsparkSession
        self.logical = self.jvm.org.apache.spark.sql.catalyst.plans.logical
        self.utils = self.jvm.org.apache.spark.sql.classic.ExpressionUtils
        self._n = 0
        # plan nodes are walked several times: their children and kinds are fetched once
        self._kids: dict[str, list] = {}
        self._kinds: dict[str, str] = {}

    def fresh(self, stem: str) -> str:
        self._n += 1
        return f"__tg_{stem}{self._n}"

    # -- sequences and nodes
    def seq(self, items: list):
        return self.jvm.PythonUtils.toSeq(items)

    @staticmethod
    def items(seq) -> list:
        return [seq.apply(i) for i in range(seq.size())]

    def kind(self, node) -> str:
        at = node._target_id
        if at not in self._kinds:
            self._kinds[at] = node.getClass().getSimpleName().rstrip("$")
        return self._kinds[at]

    def children(self, node) -> list:
        at = node._target_id
        if at not in self._kids:
            self._kids[at] = [node, self.items(node.children())]
        return self._kids[at][1]

    def output(self, node) -> list:
        return self.items(node.output())

    def with_children(self, node, new: list):
        return self.resolve(node.withNewChildren(self.seq(new)))

    def resolve(self, plan):
        return self.session.sessionState().analyzer().execute(plan)

    # -- expressions
    def expression(self, col):
        return self.session.expression(col._jc)

    def sql(self, text: str):
        return self.expression(F.expr(text))

    def named(self, text: str, name: str):
        return self.expression(F.expr(text).alias(name))

    def rename(self, attr, name: str):
        return self.session.expression(self.utils.column(attr).alias(name))

    def expression_first(self, attr, name: str):
        """``first`` of an attribute, named."""
        jfirst = self.jvm.org.apache.spark.sql.functions.first(self.utils.column(attr))
        return self.session.expression(jfirst.alias(name))

    def same(self, attr, like):
        """An attribute under the name and identity of another."""
        none = self.jvm.scala.Option.apply(None)
        return self.jvm.org.apache.spark.sql.catalyst.expressions.Alias(attr, like.name(), like.exprId(), like.qualifier(), none, self.seq([]))

    def conjuncts(self, cond) -> list:
        return self.conjuncts(cond.left()) + self.conjuncts(cond.right()) if self.kind(cond) == "And" else [cond]

    def ids(self, node) -> set:
        """Expression ids that an expression refers to."""
        return {a.exprId().id() for a in self.items(node.references().toSeq())}

    # -- plans
    def project(self, plan, extra: list, base: list | None = None):
        return self.resolve(self.logical.Project(self.seq((self.output(plan) if base is None else base) + extra), plan))

    def filter(self, plan, text: str):
        return self.resolve(self.logical.Filter(self.sql(text), plan))

    def aggregate(self, keys: list, outputs: list, plan):
        return self.resolve(self.logical.Aggregate(self.seq(keys), self.seq(outputs), plan, self.jvm.scala.Option.apply(None)))

    def join(self, left, right, how: str = "inner", condition=None):
        kind = self.jvm.org.apache.spark.sql.catalyst.plans.JoinType.apply(how)
        return self.resolve(self.logical.Join(left, right, kind, self.jvm.scala.Option.apply(condition), self.logical.JoinHint.NONE()))

    def attr(self, plan, name: str):
        for a in self.output(plan):
            if a.name() == name:
                return a
        raise KeyError(name)

    def frame(self, plan) -> DataFrame:
        # the helper object's apply is reached by its Java name
        jdf = self.jvm.org.apache.spark.sql.classic.Dataset.ofRows(self.session, plan)
        return DataFrame(jdf, self.spark)

    def analyzed(self, df: DataFrame):
        """The analyzed plan with common table expressions inlined and subquery predicates
        turned into semi and anti joins (Catalyst's own decorrelation)."""
        plan = df._jdf.queryExecution().analyzed()
        opt = self.jvm.org.apache.spark.sql.catalyst.optimizer
        text = plan.toString()
        if "CTE" in text and self._has(plan, ("WithCTE", "CTERelationRef")):
            plan = opt.InlineCTE(True, False).apply(plan)
        if self._has_subquery(plan, text):
            plan = opt.PullupCorrelatedPredicates.apply(plan)
            plan = opt.RewritePredicateSubquery.apply(plan)
        return plan

    def _has(self, plan, kinds: tuple) -> bool:
        return self.kind(plan) in kinds or any(self._has(c, kinds) for c in self.children(plan))

    def _has_subquery(self, plan, text: str) -> bool:
        # the plan's text names subquery expressions; only then are expressions walked
        if "more fields" not in text and not any(m in text for m in ("exists#", "list#", "lateral-subquery#")):
            return False
        return self._subquery_below(plan)

    def _subquery_below(self, plan) -> bool:
        own = any(self._expr_has(e) for e in self.items(plan.expressions()))
        return own or any(self._subquery_below(c) for c in self.children(plan))

    def _expr_has(self, e) -> bool:
        return self.kind(e) in ("Exists", "InSubquery", "ListQuery", "LateralSubquery") or any(self._expr_has(c) for c in self.items(e.children()))

    def scalar_subqueries(self, plan) -> bool:
        return self._mentions(plan, ("scalar-subquery#",)) and self._scalar_below(plan)

    @staticmethod
    def _mentions(plan, marks: tuple) -> bool:
        """Whether the plan's text holds a mark, or was cut so that it might."""
        text = plan.toString()
        return "more fields" in text or any(m in text for m in marks)

    def _scalar_below(self, plan) -> bool:
        def look(e):
            return self.kind(e) == "ScalarSubquery" or any(look(c) for c in self.items(e.children()))

        return any(look(e) for e in self.items(plan.expressions())) or any(self._scalar_below(c) for c in self.children(plan))
