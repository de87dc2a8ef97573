"""Rules where aggregated columns are operands: comparisons, joins, re-aggregation."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import replace

from pyspark.sql import Column
from pyspark.sql import functions as F

from polyprov.functions.algebra import Shape, concatenated, written
from polyprov.operators.basic import AggSpec, group_agg, group_by, join
from polyprov.operators.frame import AnnotatedFrame, constant, value_text
from polyprov.plans import catalyst

COMPARE = {
    "=": lambda a, b: a == b, "<>": lambda a, b: a != b, "<": lambda a, b: a < b,
    "<=": lambda a, b: a <= b, ">": lambda a, b: a > b, ">=": lambda a, b: a >= b,
}


def _value(af: AnnotatedFrame, operand) -> Column:
    return F.col(operand) if isinstance(operand, str) and operand in af.df.columns else F.lit(operand)


def _operand(af: AnnotatedFrame, operand) -> Column:
    """Text of an operand: a formal sum, or 1⊗value."""
    if isinstance(operand, str) and operand in af.df.columns:
        agg = af.agg(operand)
        return F.col(agg.tensor) if agg else constant(value_text(af.df, F.col(operand), af.options))
    return constant(value_text(af.df, F.lit(operand), af.options))


def factor(af: AnnotatedFrame, left, op: str, right) -> Column:
    return concatenated(written("["), _operand(af, left), written(f" {op} "), _operand(af, right), written("]"))


def select_agg(af: AnnotatedFrame, left: str, op: str, right) -> AnnotatedFrame:
    """Selection on an aggregated column.

    Symbolic mode drops no row; valued mode filters first, so that rows that go
    never build their factor.  Operands that are not columns are constants.
    """
    if not af.options.symbolic or not af.algebra.symbolic:
        af = af.with_df(af.df.where(COMPARE[op](_value(af, left), _value(af, right))))
    return af.with_factor(factor(af, left, op, right), Shape.CMP) if af.algebra.symbolic else af


def select_agg_tree(af: AnnotatedFrame, tree) -> AnnotatedFrame:
    """Selection by a tree: ("and"|"or", t, ...), ("not", t), ("between", c, a, b),
    ("in", c, [values]), or (left, op, right)."""
    if tree[0] == "and":
        for t in tree[1:]:
            af = select_agg_tree(af, t)
        return af
    if tree[0] == "between":
        return select_agg_tree(af, ("and", (tree[1], ">=", tree[2]), (tree[1], "<=", tree[3])))
    if not af.options.symbolic or not af.algebra.symbolic:
        af = af.with_df(af.df.where(_truth(af, tree)))
    return af.with_factor(concatenated(written("["), _tree_text(af, tree), written("]")), Shape.CMP) if af.algebra.symbolic else af


def _truth(af: AnnotatedFrame, tree) -> Column:
    if tree[0] in ("and", "or"):
        out = _truth(af, tree[1])
        for t in tree[2:]:
            out = (out & _truth(af, t)) if tree[0] == "and" else (out | _truth(af, t))
        return out
    if tree[0] == "not":
        return ~_truth(af, tree[1])
    if tree[0] == "between":
        return F.col(tree[1]).between(tree[2], tree[3])
    if tree[0] == "in":
        return F.col(tree[1]).isin(tree[2])
    return COMPARE[tree[1]](_value(af, tree[0]), _value(af, tree[2]))


def _tree_text(af: AnnotatedFrame, tree) -> Column:
    if tree[0] in ("and", "or"):
        out = [written("("), _tree_text(af, tree[1]), written(")")]
        for t in tree[2:]:
            out += [written(f" {tree[0]} ("), _tree_text(af, t), written(")")]
        return concatenated(*out)
    if tree[0] == "not":
        return concatenated(written("not ("), _tree_text(af, tree[1]), written(")"))
    if tree[0] == "between":
        return _tree_text(af, ("and", (tree[1], ">=", tree[2]), (tree[1], "<=", tree[3])))
    if tree[0] == "in":
        return _tree_text(af, ("or", *[(tree[1], "=", v) for v in tree[2]])) if len(tree[2]) > 1 else _tree_text(af, (tree[1], "=", tree[2][0]))
    return concatenated(_operand(af, tree[0]), written(f" {tree[1]} "), _operand(af, tree[2]))


def having(af: AnnotatedFrame, left: str, op: str, right) -> AnnotatedFrame:
    return select_agg(af, left, op, right)


def join_agg(left: AnnotatedFrame, right: AnnotatedFrame, a: str, op: str, b: str, max_rows: int | None = None) -> AnnotatedFrame:
    """Join on a comparison of which a side, or both, is aggregated.

    Symbolic mode cannot evaluate it: all pairs stay (``max_rows`` guards their
    number).  Valued mode joins on the values.
    """
    if left.options.symbolic and left.algebra.symbolic:
        if max_rows is not None and (n := left.df.count() * right.df.count()) > max_rows:
            raise MemoryError(f"{n} pairs in symbolic mode; use valued mode or a circuit")
        out = join(left, right)
    else:
        out = join(left, right, COMPARE[op](F.col(a), F.col(b)))
    return out.with_factor(factor(out, a, op, b), Shape.CMP) if out.algebra.symbolic else out


def reaggregate(af: AnnotatedFrame, keys: Sequence[str], aggs: Sequence[AggSpec]) -> AnnotatedFrame:
    """Aggregation of aggregated columns: formal sums of formal sums."""
    return group_agg(af, keys, aggs)


def group_over_agg(af: AnnotatedFrame, keys: Sequence[str]) -> AnnotatedFrame:
    """GROUP BY over a relation with aggregated columns that are no keys."""
    return group_by(af, keys)


def group_on_agg(af: AnnotatedFrame, keys: Sequence[str], aggs: Sequence[AggSpec] = ()) -> AnnotatedFrame:
    """GROUP BY an aggregated column: its values are the keys."""
    return group_agg(af, keys, aggs)


def order_limit(af: AnnotatedFrame, keys: Sequence[Column], n: int | None = None) -> AnnotatedFrame:
    """ORDER BY and LIMIT, by original values in either mode.

    LIMIT is not monotone: the annotation does not say why other rows are absent.
    """
    out = af.with_df(af.df.orderBy(*keys))
    return out if n is None else out.with_df(out.df.limit(n)).noted("limit: rows were chosen on original values")


def uses_agg(af: AnnotatedFrame, expression) -> bool:
    """Whether a resolved expression reads an aggregated column."""
    return bool(catalyst.references(expression) & af.aggs.keys())


def renamed(af: AnnotatedFrame, names: dict[str, str]) -> AnnotatedFrame:
    """Columns under other names, aggregated ones still known."""
    before = {a.name(): a.exprId().id() for a in catalyst.output(af.df)}
    df = af.df.withColumnsRenamed(names)
    after = {a.name(): a.exprId().id() for a in catalyst.output(df)}
    return replace(af, df=df, aggs={after[names.get(n, n)]: af.aggs[i] for n, i in before.items() if i in af.aggs})
