"""SQL text to the multiway aggregate: the analysed plan is read, not the text.

What is understood: one GROUP BY of count(*), sum, min, max or avg over inner equi-joins of tables
or subqueries, with filters on single inputs. Anything else runs as Spark plans it, and the reason
is kept in `why_not`.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from multiagg.operators.multiway import multiway_aggregate
from multiagg.plans.spec import Agg, GroupedJoinSpec, Rel, SpecError

last_reason: dict[str, str] = {}


class _Unsupported(Exception):
    pass


def _seq(x) -> list:
    return [x.apply(i) for i in range(x.size())]


def _kind(node) -> str:
    return node.getClass().getSimpleName().rstrip("$")


def _refs(expr) -> set[int]:
    it, out = expr.references().iterator(), set()
    while it.hasNext():
        out.add(it.next().exprId().id())
    return out


def _conjuncts(expr) -> list:
    if _kind(expr) == "And":
        return _conjuncts(expr.left()) + _conjuncts(expr.right())
    return [expr]


class _Reader:
    def __init__(self, spark: SparkSession):
        self.spark, self.leaves, self.conditions = spark, [], []

    def read(self, plan) -> None:
        kind = _kind(plan)
        if kind == "SubqueryAlias" and _kind(plan.child()) in ("Join", "SubqueryAlias"):
            return self.read(plan.child())
        if kind == "Filter" and self._joins(plan.child()):
            self.conditions += _conjuncts(plan.condition())
            return self.read(plan.child())
        if kind == "Project" and self._joins(plan.child()) and all(_kind(e) == "AttributeReference" for e in _seq(plan.projectList())):
            return self.read(plan.child())
        if kind == "Join":
            if plan.joinType().sql() not in ("INNER", "CROSS"):
                raise _Unsupported(f"a {plan.joinType().sql()} join")
            if plan.condition().isDefined():
                self.conditions += _conjuncts(plan.condition().get())
            self.read(plan.left())
            return self.read(plan.right())
        self.leaves.append(plan)

    def _joins(self, plan) -> bool:
        return _kind(plan) == "Join" or (_kind(plan) in ("Filter", "Project", "SubqueryAlias") and self._joins(plan.child()))


def _frame(spark: SparkSession, plan) -> DataFrame:
    """A data frame over an analysed plan, its columns named by their expression ids."""
    jdf = spark._jvm.org.apache.spark.sql.classic.Dataset.ofRows(spark._jsparkSession, plan)
    df = DataFrame(jdf, spark)
    return df.toDF(*(f"e{a.exprId().id()}" for a in _seq(plan.output())))


def _spec(spark: SparkSession, plan) -> tuple[GroupedJoinSpec, list[str]]:
    if _kind(plan) != "Aggregate":
        raise _Unsupported(f"the plan's top is {_kind(plan)}")
    reader = _Reader(spark)
    reader.read(plan.child())
    if len(reader.leaves) < 2:
        raise _Unsupported("one input only")
    owner = {a.exprId().id(): i for i, leaf in enumerate(reader.leaves) for a in _seq(leaf.output())}
    same: dict[int, int] = {}

    def root(x: int) -> int:
        while same.get(x, x) != x:
            x = same[x]
        return x

    frames = list(reader.leaves)
    for c in reader.conditions:
        refs = _refs(c)
        homes = {owner[r] for r in refs}
        if len(homes) == 1:
            i = homes.pop()
            frames[i] = spark._jvm.org.apache.spark.sql.catalyst.plans.logical.Filter(c, frames[i])
        elif _kind(c) == "EqualTo" and _kind(c.left()) == _kind(c.right()) == "AttributeReference":
            a, b = root(c.left().exprId().id()), root(c.right().exprId().id())
            same[a] = b
        else:
            raise _Unsupported(f"condition {c.sql()}")
    joining: dict[int, set[int]] = {}
    for x in owner:
        joining.setdefault(root(x), set()).add(x)
    joining = {k: v for k, v in joining.items() if len({owner[x] for x in v}) > 1}
    attrs: list[dict[str, str]] = [{} for _ in frames]
    for k, members in joining.items():
        taken: set[int] = set()
        for x in members:
            if owner[x] in taken:
                raise _Unsupported("two columns of one input join on the same value")
            taken.add(owner[x])
            attrs[owner[x]][f"j{k}"] = f"e{x}"
    groups: list[list[str]] = [[] for _ in frames]
    measures: list[dict[str, str]] = [{} for _ in frames]
    extra: list[dict[str, object]] = [{} for _ in frames]
    by_text: dict[str, str] = {}

    def on_leaf(expr, name: str) -> int:
        homes = {owner[r] for r in _refs(expr)}
        if len(homes) != 1:
            raise _Unsupported(f"expression {expr.sql()} over several inputs")
        i = homes.pop()
        extra[i][name] = expr
        return i

    for n, g in enumerate(_seq(plan.groupingExpressions())):
        i = on_leaf(g, f"g{n}")
        attrs[i][f"g{n}"] = f"g{n}"
        groups[i].append(f"g{n}")
        by_text[g.canonicalized().toString()] = f"g{n}"
    names, aggs = [], []
    for e in _seq(plan.aggregateExpressions()):
        inner = e.child() if _kind(e) == "Alias" else e
        text = inner.canonicalized().toString()
        if text in by_text:
            names.append((by_text[text], e.name()))
            continue
        if _kind(inner) != "AggregateExpression" or inner.isDistinct() or inner.filter().isDefined():
            raise _Unsupported(f"result {e.sql()}")
        f = inner.aggregateFunction()
        kind, alias = _kind(f), f"a{len(names)}"
        arg = f.children().apply(0)
        if kind == "Count" and not _refs(arg):
            aggs.append(Agg.count(alias))
        elif kind in ("Sum", "Min", "Max", "Average", "Count"):
            i = on_leaf(arg, f"m{len(names)}")
            measures[i][f"m{len(names)}"] = f"m{len(names)}"
            at = (f"r{i}", f"m{len(names)}", alias)
            aggs.append({"Sum": Agg.sum, "Min": Agg.min, "Max": Agg.max, "Average": Agg.avg, "Count": Agg.count_of}[kind](*at))
        else:
            raise _Unsupported(f"aggregate {kind}")
        names.append((alias, e.name()))
    rels = []
    for i, leaf in enumerate(frames):
        df = _frame(spark, leaf)
        if extra[i]:
            project = spark._jvm.org.apache.spark.sql.catalyst.plans.logical.Project
            aliased = [*_seq(leaf.output())]
            jvm = spark._jvm
            made = jvm.java.util.ArrayList()
            for a in aliased:
                made.add(a)
            for name, expr in extra[i].items():
                made.add(jvm.org.apache.spark.sql.catalyst.expressions.Alias(expr, name, jvm.org.apache.spark.sql.catalyst.expressions.NamedExpression.newExprId(), _empty(jvm), jvm.scala.Option.empty(), _empty(jvm)))
            full = project(jvm.org.apache.spark.api.python.PythonUtils.toSeq(made), leaf)
            jdf = jvm.org.apache.spark.sql.classic.Dataset.ofRows(spark._jsparkSession, full)
            df = DataFrame(jdf, spark).toDF(*(f"e{a.exprId().id()}" for a in aliased), *extra[i])
        rels.append(Rel(f"r{i}", df, attrs[i], tuple(groups[i]), measures[i]))
    return GroupedJoinSpec(tuple(rels), tuple(aggs)), names


def _empty(jvm):
    return jvm.org.apache.spark.api.python.PythonUtils.toSeq(jvm.java.util.ArrayList())


def recognise(spark: SparkSession, text: str) -> tuple[GroupedJoinSpec, list]:
    """The spec behind a query, and its result columns as (spec name, name)."""
    plan = spark.sql(text)._jdf.queryExecution().analyzed()
    return _spec(spark, plan)


def multiway_sql(spark: SparkSession, text: str, strategy: str = "shared_arms") -> DataFrame:
    try:
        spec, names = recognise(spark, text)
        out = multiway_aggregate(spec, strategy)
    except (_Unsupported, SpecError) as e:
        last_reason[text] = str(e)
        return spark.sql(text)
    last_reason.pop(text, None)
    return out.select(*(F.col(a).alias(n) for a, n in names))


def why_not(text: str) -> str | None:
    """Why the last run of this text went to Spark's own plan, if it did."""
    return last_reason.get(text)
