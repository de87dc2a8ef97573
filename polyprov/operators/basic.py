"""Annotation rules for the positive operators.

Rules take and give AnnotatedFrames.  Columns may be given as names or Columns.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from polyprov.errors import UnsupportedForProvenance
from polyprov.functions.algebra import ALGEBRAS, ZERO, Algebra, Shape, bracketed, concatenated, ordered_listagg, written
from polyprov.operators.frame import Agg, AnnotatedFrame, constant, fresh, tensor, value_text
from polyprov.options import Options
from polyprov.plans import catalyst
from polyprov.sources.tokens import TokenPolicy

MONOIDS = ("sum", "count", "min", "max", "avg", "stddev", "variance", "covar")


def as_column(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def annotate_base(df: DataFrame, policy: TokenPolicy, options: Options = Options(), algebra: Algebra | None = None) -> AnnotatedFrame:
    """Base annotation: a token per row, by a narrow projection."""
    algebra = algebra or ALGEBRAS[options.algebra]
    name = fresh("prov")
    return AnnotatedFrame(df.withColumn(name, algebra.token(policy.column(df.columns))), ((name, Shape.ATOM),), {}, algebra, options)


def select_rows(af: AnnotatedFrame, condition: Column | str) -> AnnotatedFrame:
    """Selection on plain columns: annotations stay."""
    return af.with_df(af.df.where(condition))


def project_bag(af: AnnotatedFrame, columns: Sequence[Column | str]) -> AnnotatedFrame:
    """Bag projection: the annotation, and the formal sums of kept aggregates, go along."""
    kept = af.df.select(*map(as_column, columns), *af.hidden)
    there = {a.exprId().id() for a in catalyst.output(kept)}
    return replace(af, df=kept, aggs={k: v for k, v in af.aggs.items() if k in there})


def join(left: AnnotatedFrame, right: AnnotatedFrame, on: Column | str | list[str] | None = None, how: str = "inner") -> AnnotatedFrame:
    """Join on plain columns, or product: annotations multiply.

    Outer joins multiply by 1 where the optional side has no row; that a row has
    no partner is not monotone, which a caveat says.
    """
    if how in ("left_semi", "semi", "leftsemi", "left_anti", "anti", "leftanti"):
        raise UnsupportedForProvenance("use the unnesting rules for semi and anti joins")
    df = left.df.crossJoin(right.df) if on is None or how == "cross" else left.df.join(right.df, on, how)
    out = replace(left, df=df, factors=left.factors + right.factors, aggs=left.aggs | right.aggs, caveats=left.caveats + right.caveats)
    optional = {"left": [right], "leftouter": [right], "left_outer": [right], "right": [left], "rightouter": [left], "right_outer": [left], "full": [left, right], "outer": [left, right], "fullouter": [left, right], "full_outer": [left, right]}.get(how, [])
    for side in optional:
        out = out.with_df(out.df.withColumns({c: F.coalesce(F.col(c), out.algebra.one()) for c, _ in side.factors}))
    return out.noted(f"{how} join: rows without a partner do not say why they have none") if optional else out


def join_many(frames: Sequence[AnnotatedFrame], conditions: Sequence[Column | str | list[str] | None]) -> AnnotatedFrame:
    """Left-deep n-way join; one product at the end."""
    out = frames[0]
    for f, c in zip(frames[1:], conditions, strict=True):
        out = join(out, f, c)
    return out


def union_all(*frames: AnnotatedFrame, by_name: bool = False) -> AnnotatedFrame:
    """Bag union: rows keep their annotations."""
    parts = [f.one_factor() for f in frames]
    shape = parts[0].factors[0][1] if len({p.factors[0][1] for p in parts}) == 1 else Shape.SUM
    first = parts[0]
    tensors = [a.tensor for a in first.aggs.values()]
    df = first.df.select(*first.columns, *tensors, first.factors[0][0])
    for p in parts[1:]:
        names = [p.aggs[i].tensor for i in p.aggs]
        if len(names) != len(tensors):
            raise UnsupportedForProvenance("union of an aggregated with a plain column")
        right = p.df.select(*p.columns, *[F.col(n).alias(t) for n, t in zip(names, tensors, strict=True)], F.col(p.factors[0][0]).alias(first.factors[0][0]))
        df = df.unionByName(right, allowMissingColumns=True) if by_name else df.union(right)
    ids = {a.name(): a.exprId().id() for a in catalyst.output(df)}
    before = {a.exprId().id(): a.name() for a in catalyst.output(first.df)}
    return replace(first, df=df, factors=((first.factors[0][0], shape),), aggs={ids[before[i]]: a for i, a in first.aggs.items()}, caveats=tuple(c for f in frames for c in f.caveats))


def union_set(*frames: AnnotatedFrame) -> AnnotatedFrame:
    """Set union: bag union, then grouping by all columns; a plain sum, without δ."""
    out = union_all(*frames)
    return _grouped(out, [F.col(f"`{c}`") for c in out.columns], [], [], delta=False)


def project_set(af: AnnotatedFrame, columns: Sequence[Column | str]) -> AnnotatedFrame:
    """DISTINCT: grouping by the projected columns."""
    return group_by(af, columns)


def drop_duplicates(af: AnnotatedFrame, columns: Sequence[str]) -> AnnotatedFrame:
    """dropDuplicates on some columns: δ of all, the others from one of the rows."""
    rest = [c for c in af.columns if c not in columns]
    return _grouped(af, [F.col(c) for c in columns], [F.first(c).alias(c) for c in rest], [])


def group_by(af: AnnotatedFrame, keys: Sequence[Column | str]) -> AnnotatedFrame:
    """GROUP BY without aggregates: δ of the sum of the group's annotations.

    Over a relation with aggregated columns that are no keys, the sum has each
    annotation scaled by them instead (no δ).
    """
    return _grouped(af, [as_column(k) for k in keys], [], [])


@dataclass(frozen=True)
class AggSpec:
    """One aggregate: name of its column, monoid, argument (None: COUNT(*))."""

    name: str
    monoid: str
    argument: Column | str | None = None
    distinct: bool = False
    where: Column | None = None
    value: Column | None = None

    def value_column(self) -> Column:
        if self.value is not None:
            return self.value
        c = F.lit(1) if self.argument is None else as_column(self.argument)
        if self.where is not None:
            c = F.when(self.where, c)
        return {"sum": F.sum, "count": F.count, "min": F.min, "max": F.max, "avg": F.avg, "stddev": F.stddev, "variance": F.variance}[self.monoid](c).alias(self.name)


def group_agg(af: AnnotatedFrame, keys: Sequence[Column | str], aggs: Sequence[AggSpec]) -> AnnotatedFrame:
    """GROUP BY with aggregates: all values, formal sums and the annotation in one aggregation."""
    distinct = [a for a in aggs if a.distinct]
    if distinct and af.options.rewrite_distinct and af.algebra.symbolic:
        if len(aggs) > 1:
            raise UnsupportedForProvenance("DISTINCT aggregates beside others")
        return count_distinct(af, keys, distinct[0])
    return _grouped(af, [as_column(k) for k in keys], [a.value_column() for a in aggs], [formal(af, a) for a in aggs])


def aggregate(af: AnnotatedFrame, aggs: Sequence[AggSpec]) -> AnnotatedFrame:
    """Aggregation of the whole relation to one row, whose annotation is 1."""
    return group_agg(af, [], aggs)


def count_distinct(af: AnnotatedFrame, keys: Sequence[Column | str], spec: AggSpec) -> AnnotatedFrame:
    """f(DISTINCT x): set projection on keys and x, then f per key."""
    keys = [as_column(k) for k in keys]
    x = fresh("x")
    named = af.df.withColumn(x, as_column(spec.argument))
    inner = _grouped(af.with_df(named if keys else named.where(F.col(x).isNotNull())), [*keys, F.col(x)], [], [])
    outer = replace(spec, argument=F.col(x), distinct=False, value=None)
    kept = [catalyst.column(a) for a in catalyst.output(inner.df)[: len(keys)]]
    return _grouped(inner, kept, [outer.value_column()], [formal(inner, outer)])


@dataclass(frozen=True)
class Formal:
    """A formal sum to be built: of ``text`` per row (already annotation ⊗ value)."""

    name: str
    monoid: str
    value: Column | None
    where: Column | None = None
    inner: Column | None = None
    inner_monoid: str | None = None


def empty_sum(monoid: str) -> str:
    """The formal sum of no rows: NULL, written 0; a count of none is the value 0."""
    return "1⊗0" if monoid == "count" else ZERO


def formal(af: AnnotatedFrame, a: AggSpec) -> Formal:
    if a.argument is None:
        return Formal(a.name, a.monoid, written("1"), a.where)
    c = as_column(a.argument)
    if isinstance(a.argument, str) and (inner := af.agg(a.argument)) is not None:
        return Formal(a.name, a.monoid, None, a.where, F.col(inner.tensor), inner.monoid)
    if a.monoid == "count":
        return Formal(a.name, a.monoid, F.when(c.isNotNull(), written("1")), a.where)
    return Formal(a.name, a.monoid, value_text(af.df, c, af.options), a.where)


def _key_ids(df: DataFrame, keys: Sequence[Column]) -> list[int | None]:
    """Attribute id of each key; None for expressions."""
    mine = {a.exprId().id() for a in catalyst.output(df)}
    return [i if (i := a.exprId().id()) in mine else None for a in catalyst.output(df.select(*keys))] if keys else []


def _grouped(af: AnnotatedFrame, keys: list[Column], values: list[Column], formals: list[Formal], delta: bool = True) -> AnnotatedFrame:
    """Grouping whose formal sums belong to the value columns of their names."""
    out, sums = grouped_sums(af, keys, values, formals, delta)
    ids = {a.name(): a.exprId().id() for a in catalyst.output(out.df)}
    return replace(out, aggs={ids[n]: a for n, a in sums.items() if n in ids})


def grouped_sums(af: AnnotatedFrame, keys: list[Column], values: list[Column], formals: list[Formal], delta: bool = True, spread: bool = False) -> tuple[AnnotatedFrame, dict[str, Agg]]:
    """The one aggregation behind all grouping rules, and its formal sums by name.

    Aggregated key columns become ordinary ones: each row's annotation first gets
    the factor [formal sum = 1⊗value].  ``spread``: the addends of a group's annotation
    (without keys: of its first formal sum) stay in rows of their own beside its values.
    """
    algebra, options = af.algebra, af.options
    if algebra.recorder is not None:
        return algebra.recorder.group(af, keys, values, formals, delta)
    key_ids = set(_key_ids(af.df, keys))
    if algebra.symbolic:
        for i in [i for i in af.aggs if i in key_ids]:
            attr = next(a for a in catalyst.output(af.df) if a.exprId().id() == i)
            af = af.with_factor(concatenated(written("["), F.col(af.aggs[i].tensor), written(" = "), constant(value_text(af.df, catalyst.column(attr), options)), written("]")), Shape.CMP)
        af = replace(af, aggs={i: a for i, a in af.aggs.items() if i not in key_ids})
    af = af.one_factor() if af.factors else af.with_factor(algebra.one(), Shape.ATOM)
    prov, shape = af.factors[0]
    df = af.df
    sums: list[Column] = []
    scaled = [f for f in formals if f.inner is not None]
    if algebra.symbolic:
        texts = {}
        if scaled:
            texts[prov] = _scaled(F.col(prov), shape, [(f.monoid, f.inner) for f in scaled])
        elif af.aggs and delta:
            texts[prov] = _scaled(F.col(prov), shape, [(a.monoid, F.col(a.tensor)) for a in {a.tensor: a for a in af.aggs.values()}.values()])
        names = {}
        for f in formals:
            t = fresh("term")
            if f.inner is None:
                c = tensor(F.col(prov), shape, f.value)
            elif options.reagg_style == "evaluable":
                c = concatenated(bracketed(F.col(prov), shape), written(f" *{f.monoid} ("), f.inner, written(")"))
            else:
                # Sums of another monoid keep together in brackets.
                c = f.inner if f.inner_monoid == f.monoid else concatenated(written("("), f.inner, written(")"))
            texts[t] = c if f.where is None else F.when(f.where, c)
            names[t] = (f, fresh("sum"))
        df = df.withColumns(texts)
        for t, (f, s) in names.items():
            sums.append(F.coalesce(ordered_listagg(t, f" +{f.monoid} "), written(empty_sum(f.monoid))).alias(s))
        aggs_by_name = {f.name: Agg(f.monoid, s) for f, s in names.values()}
        plain = not (scaled or (af.aggs and delta))
    else:
        aggs_by_name, plain = {}, True
    if spread:
        return _spread(replace(af, df=df, factors=((prov, shape if plain else Shape.PROD),), aggs={}), keys, values, None if keys or not formals else F.col(next(iter(names))).isNotNull()), {}
    out_prov = fresh("prov")
    whole = algebra.plus(prov)
    if not keys and plain:
        annotation, out_shape = None, Shape.ATOM
    elif not plain:
        annotation, out_shape = (whole if keys else F.coalesce(whole, written(ZERO))), Shape.SUM
    elif delta:
        annotation, out_shape = algebra.delta(whole), Shape.DELTA
    else:
        annotation, out_shape = whole, Shape.SUM
    exprs = [*values, *sums, *([annotation.alias(out_prov)] if annotation is not None else [])]
    if not exprs:
        exprs = [F.count(F.lit(1)).alias(fresh("n"))]
    grouped = df.groupBy(*keys).agg(*exprs)
    if annotation is None:
        grouped = grouped.withColumn(out_prov, algebra.one())
    return replace(af, df=grouped, factors=((out_prov, out_shape),), aggs={}), aggs_by_name


def _spread(af: AnnotatedFrame, keys: list[Column], values: list[Column], kept: Column | None) -> AnnotatedFrame:
    names = [fresh("k") for _ in keys]
    whole = af.df.groupBy(*keys).agg(*(values or [F.count(F.lit(1)).alias(fresh("n"))]))
    rows = (af.df if kept is None else af.df.where(kept)).select(*[k.alias(n) for k, n in zip(keys, names, strict=True)], af.factors[0][0])
    if not keys:
        return af.with_df(rows.crossJoin(F.broadcast(whole)))
    same = F.lit(True)
    for a, n in zip(catalyst.output(whole)[: len(keys)], names, strict=True):
        same = same & catalyst.column(a).eqNullSafe(F.col(n))
    return af.with_df(whole.join(rows, same).drop(*names))


def _scaled(prov: Column, shape: Shape, inner: Sequence[tuple[str, Column]]) -> Column:
    out = bracketed(prov, shape)
    for monoid, t in inner:
        out = concatenated(out, written(f" *{monoid} ("), t, written(")"))
    return out
