"""The bridge to Catalyst: analyzed plans and resolved expressions.

All use of Spark's JVM classes is here.  Analyzed plans are read, never changed;
expressions go back into DataFrames as resolved columns, so that attribute ids
tell columns apart and no name has to be guessed.
"""

from __future__ import annotations

import re
from collections.abc import Callable, Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def _jvm():
    return SparkSession.active()._jvm


def seq(items) -> object:
    return _jvm().org.apache.spark.api.python.PythonUtils.toSeq(list(items))


def items(s) -> list:
    return [s.apply(i) for i in range(s.size())]


def column(expression) -> Column:
    from pyspark.sql.classic.column import Column as ClassicColumn

    return ClassicColumn(_jvm().org.apache.spark.sql.classic.ExpressionUtils.column(expression))


def frame(plan) -> DataFrame:
    spark = SparkSession.active()
    return DataFrame(_jvm().org.apache.spark.sql.classic.Dataset.ofRows(spark._jsparkSession, plan), spark)


def analyzed(df: DataFrame):
    return df._jdf.queryExecution().analyzed()


def output(df: DataFrame) -> list:
    return items(analyzed(df).output())


def name_of(node) -> str:
    return node.getClass().getSimpleName()


def children(node) -> list:
    return items(node.children())


def rebuilt(node, kids: list):
    """The node over other children, its own expressions kept."""
    return node.withNewChildren(seq(kids))


def transform(expression, change: Callable) -> object:
    """Bottom-up copy; ``change`` gives a replacement or None."""
    kids = children(expression)
    new = [transform(k, change) for k in kids]
    if any(a is not b for a, b in zip(kids, new, strict=True)):
        expression = expression.withNewChildren(seq(new))
    found = change(expression)
    return expression if found is None else found


def walk(expression) -> Iterator:
    yield expression
    for k in children(expression):
        yield from walk(k)


def references(expression) -> set[int]:
    """Ids of the attributes that the expression reads (not inside subquery plans)."""
    return {e.exprId().id() for e in walk(expression) if name_of(e) == "AttributeReference"}


def conjuncts(expression) -> list:
    if name_of(expression) == "And":
        return conjuncts(expression.left()) + conjuncts(expression.right())
    return [expression]


def outer_references(expression) -> list:
    return [e for e in walk(expression) if name_of(e) == "OuterReference"]


def without_outer(expression):
    return transform(expression, lambda e: e.e() if name_of(e) == "OuterReference" else None)


def alias_as(attribute, like) -> Column:
    """``attribute`` under the name and id of ``like``."""
    jvm = _jvm()
    none = getattr(getattr(jvm.scala, "None$"), "MODULE$")
    return column(jvm.org.apache.spark.sql.catalyst.expressions.Alias(attribute, like.name(), like.exprId(), seq([]), none, seq([])))


_EQUALS_SUBQUERY = re.compile(r"= (?:outer\()?scalar-subquery#|scalar-subquery#\d+ \[[^\]]*\] =")


def equals_subquery(df: DataFrame) -> bool:
    """Whether the query asks for equality with a scalar subquery's value."""
    return bool(_EQUALS_SUBQUERY.search(analyzed(df).toString()))


def steady_sum(named) -> Column:
    """A SUM of doubles, added in the order of its values, under its own name and id;
    anything else as it is."""
    body = named.child() if name_of(named) == "Alias" else named
    if name_of(body) != "AggregateExpression" or body.isDistinct() or body.filter().isDefined():
        return column(named)
    f = body.aggregateFunction()
    if name_of(f) != "Sum" or f.child().dataType().simpleString() != "double":
        return column(named)
    total = F.aggregate(F.sort_array(F.collect_list(column(f.child()))), F.lit(None).cast("double"), lambda a, x: F.coalesce(a, F.lit(0.0)) + x)
    return alias_as(_jvm().org.apache.spark.sql.classic.ExpressionUtils.expression(total._jc), named)


def or_zero(attribute):
    """coalesce(attribute, 0 of its type)."""
    e = _jvm().org.apache.spark.sql.catalyst.expressions
    return e.Coalesce(seq([attribute, e.Literal.default(attribute.dataType())]))


def option(o):
    return o.get() if o.isDefined() else None


#: A comparison of two attributes, as plans print it.
_OF_ATTRIBUTES = re.compile(r"isnotnull\([^()]*\)|[\w.`]+#\d+L? (?:=|<=>|<|<=|>|>=) [\w.`]+#\d+L?")


def filtered(df: DataFrame) -> bool:
    """Whether a filter of the plan compares with more than other attributes."""
    for line in analyzed(df).toString().split("\n"):
        at = line.find("Filter ")
        if at >= 0 and re.search(r"[=<>]|\b(?:IN|LIKE|StartsWith|EndsWith|Contains)\b", _OF_ATTRIBUTES.sub("", line[at:])):
            return True
    return False


def ends_in_groups(df: DataFrame) -> bool:
    """Whether the result's rows are the groups of an aggregation, some of them maybe
    filtered out."""
    plan = analyzed(df)
    while name_of(plan) in ("Project", "Filter", "Sort", "SubqueryAlias"):
        plan = plan.child()
    return name_of(plan) == "Aggregate" and name_of(plan.child()) != "Expand"


def outer_in(plan) -> bool:
    """Whether the plan reads from an outer query."""
    return "outer(" in plan.toString()
