"""Unnesting rules: subqueries as joins with a grouped inner side.

A semi-join would hide the inner annotation; an inner join with a right side that
is unique per key has the same multiplicity and keeps it.  Helper relations
(distinct outer values) are neutral: their annotation is 1.

Conditions are given as (outer column, op, inner column) by name; the two frames
must not share column names.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from polyprov.errors import UnsupportedForProvenance
from polyprov.functions.algebra import PLUS, Shape, concatenated, measuring, text_only, written
from polyprov.operators.basic import AggSpec, _grouped, empty_sum, formal, group_agg
from polyprov.operators.extended import COMPARE, factor, select_agg
from polyprov.operators.frame import Agg, AnnotatedFrame, fresh
from polyprov.plans import catalyst

Condition = tuple[str, str, str]


def grouped_inner(inner: AnnotatedFrame, keys: Sequence[Column]) -> tuple[AnnotatedFrame, list[str]]:
    """The inner side with one row per key: δ of the sum.  Keys get names of ours."""
    names = [fresh("k") for _ in keys]
    plain = replace(inner, aggs={})
    if not keys:
        out = _grouped(plain, [F.lit(1).alias(fresh("k"))], [], [])
    else:
        out = _grouped(plain, [k.alias(n) for k, n in zip(keys, names, strict=True)], [], [])
    return out, names


def attach(outer: AnnotatedFrame, inner: AnnotatedFrame, condition: Column | None) -> AnnotatedFrame:
    """Inner join with a grouped side, adding its annotation."""
    df = outer.df.crossJoin(inner.df) if condition is None else outer.df.join(inner.df, condition)
    return replace(outer, df=df, factors=outer.factors + inner.factors, aggs=outer.aggs | inner.aggs, caveats=outer.caveats + inner.caveats)


def beside(df: DataFrame, one: DataFrame, certain: bool = False) -> DataFrame:
    """Every row with the one row of ``one``, or with nulls if that has none (never, if
    ``certain``).

    The row may hold megabytes of text, as it lists a whole relation.  An outer nested
    loop join would copy it for all rows at once; a product takes it row by row, over
    several tasks, and sends nothing through the driver.  The row is made once and
    shuffled; each task of the product reads it.
    """
    spark = df.sparkSession
    held = one.repartition(1)
    if not certain:
        held = F.broadcast(spark.range(1).select(F.lit(1).alias(fresh("k")))).join(held, F.lit(True), "left")
    return df.repartition(4 * spark.sparkContext.defaultParallelism).crossJoin(held.hint("shuffle_replicate_nl"))


def exists_equal(outer: AnnotatedFrame, inner: AnnotatedFrame, pairs: Sequence[tuple]) -> AnnotatedFrame:
    """EXISTS with equalities only: group the inner side by them, equi-join.

    Pairs are (outer, inner) or (outer, inner, null-safe).
    """
    grouped, names = grouped_inner(inner, [p[1] for p in pairs])
    return attach(outer, grouped, _same(pairs, names))


def _same(pairs: Sequence[tuple], names: Sequence[str]) -> Column | None:
    condition = None
    for p, n in zip(pairs, names, strict=True):
        c = p[0].eqNullSafe(F.col(n)) if len(p) > 2 and p[2] else p[0] == F.col(n)
        condition = c if condition is None else condition & c
    return condition


def either(outer: AnnotatedFrame, plain: Column | None, inners: Sequence[tuple[AnnotatedFrame, Sequence[tuple]]]) -> AnnotatedFrame:
    """A disjunction of a plain condition and of EXISTS with equalities.

    Rows that meet any part stay, times δ of the sum of the parts they meet: 1 for
    the plain condition, δ of the inner rows for each EXISTS.
    """
    if not outer.algebra.symbolic or outer.algebra.recorder is not None:
        raise UnsupportedForProvenance("the inner side of a disjunction needs text annotations")
    text_only("a disjunction")
    parts = [] if plain is None else [F.when(plain, outer.algebra.one())]
    for inner, pairs in inners:
        grouped, names = grouped_inner(inner, [p[1] for p in pairs])
        condition = _same(pairs, names)
        outer = replace(outer, df=outer.df.join(grouped.df, F.lit(True) if condition is None else condition, "left"), caveats=outer.caveats + grouped.caveats)
        parts.append(grouped.product()[0])
    met = F.array_compact(F.array(*parts))
    return outer.with_df(outer.df.where(F.size(met) > 0)).with_factor(concatenated(written("δ("), F.array_join(met, " + "), written(")")), Shape.DELTA)


def subtracted(outer: AnnotatedFrame, inner: AnnotatedFrame, pairs: Sequence[tuple]) -> AnnotatedFrame:
    """k ⊖ δ(Σ inner) (experimental): rows stay; the annotation tells what is subtracted."""
    if not outer.algebra.symbolic or outer.algebra.recorder is not None:
        raise UnsupportedForProvenance("monus needs text annotations")
    grouped, names = grouped_inner(inner, [p[1] for p in pairs])
    condition = _same(pairs, names)
    outer = outer.one_factor()
    (p, shape), (q, _) = outer.factors[0], grouped.factors[0]
    minus = concatenated(written("("), F.col(p), written(" ⊖ "), F.col(q), written(")"))
    df = outer.df.join(grouped.df, F.lit(True) if condition is None else condition, "left").withColumn(p, F.when(F.col(q).isNull(), F.col(p)).otherwise(minus)).drop(q, *names)
    return replace(outer, df=df, factors=((p, shape),)).noted("monus is experimental: it evaluates in counts and booleans only")


def exists_domain(outer: AnnotatedFrame, inner: AnnotatedFrame, domain: Sequence[Column], condition: Column) -> AnnotatedFrame:
    """EXISTS with any condition: distinct outer values, joined with the inner side
    under the condition and grouped, then equi-joined (null-safe) to the outer side."""
    values = outer.df.select(*domain).distinct()
    ids = catalyst.output(values)
    matched = inner.with_df(values.join(inner.df, condition))
    grouped, names = grouped_inner(matched, [catalyst.column(a) for a in ids])
    same = None
    for o, n in zip(domain, names, strict=True):
        c = o.eqNullSafe(F.col(n))
        same = c if same is None else same & c
    return attach(outer, grouped, same)


def _condition(conditions: Sequence[Condition]) -> Column:
    out = None
    for o, op, i in conditions:
        c = COMPARE[op](F.col(o), F.col(i))
        out = c if out is None else out & c
    return out


def exists(outer: AnnotatedFrame, inner: AnnotatedFrame, conditions: Sequence[Condition]) -> AnnotatedFrame:
    strategy = outer.options.exists_strategy
    if strategy in ("prefix", "auto") and len(conditions) == 1 and conditions[0][1] in ("<", "<=", ">", ">="):
        return prefix_exists(outer, inner, *conditions[0])
    if all(op == "=" for _, op, _ in conditions) and strategy != "domain":
        return exists_equal(outer, inner, [(F.col(o), F.col(i)) for o, _, i in conditions])
    return exists_domain(outer, inner, [F.col(c) for c in dict.fromkeys(o for o, _, _ in conditions)], _condition(conditions))


def any_(outer: AnnotatedFrame, inner: AnnotatedFrame, a: str, op: str, b: str, conditions: Sequence[Condition] = ()) -> AnnotatedFrame:
    """a op ANY (inner.b): EXISTS with the comparison as one more condition."""
    return exists(outer, inner, [(a, op, b), *conditions])


def in_(outer: AnnotatedFrame, inner: AnnotatedFrame, u: Sequence[str], v: Sequence[str], conditions: Sequence[Condition] = ()) -> AnnotatedFrame:
    """u IN (inner.v): group the inner side by v and equi-join; EXISTS if correlated."""
    return exists(outer, inner, [*((a, "=", b) for a, b in zip(u, v, strict=True)), *conditions])


def all_(outer: AnnotatedFrame, inner: AnnotatedFrame, a: str, op: str, b: str, conditions: Sequence[Condition] = ()) -> AnnotatedFrame:
    """a op ALL (inner.b): compared with the inner maximum (>, >=) or minimum (<, <=).

    Every inner annotation is kept, in the formal sum and as δ of their sum.  An empty
    inner side makes ALL true: such rows stay, times 1.  A null among the inner
    values makes the comparison unknown.  ``=`` needs minimum and maximum equal;
    ``<>`` is NOT IN.  With a correlation other than equality the inner side is
    grouped by the distinct outer values that it is met for.
    """
    if op == "<>":
        return not_in(outer, inner, [a], [b], conditions)
    safe = any(c[1] != "=" for c in conditions)
    if safe:
        domain = {c: fresh("o") for c in dict.fromkeys(o for o, _, _ in conditions)}
        values = outer.df.select(*[F.col(c).alias(n) for c, n in domain.items()]).distinct()
        inner = inner.with_df(values.join(inner.df, _condition([(domain[o], x, i) for o, x, i in conditions])))
        conditions = [(c, "=", n) for c, n in domain.items()]
    keys = [i for _, _, i in conditions]
    bound, n, nulls = fresh("bound"), fresh("n"), fresh("nulls")
    monoid = "max" if op in (">", ">=", "=") else "min"
    # δ of all inner annotations: grouped by the correlation keys, or by a constant.
    one = fresh("k")
    inner = inner.with_df(inner.df.withColumn(one, F.lit(1)))
    aggs = [AggSpec(bound, monoid, b), AggSpec(n, "count"), AggSpec(nulls, "count", value=(F.count(F.lit(1)) - F.count(F.col(b))).alias(nulls))]
    other = fresh("other")
    if op == "=":
        aggs.append(AggSpec(other, "min", b))
    grouped = _grouped(replace(inner, aggs={}), [F.col(k) for k in [*keys, one]], [x.value_column() for x in aggs], [formal(inner, aggs[0])])
    grouped = replace(grouped, df=grouped.df.drop(one))
    if keys:
        condition = None
        for o, _, i in conditions:
            c = F.col(o).eqNullSafe(F.col(i)) if safe else F.col(o) == F.col(i)
            condition = c if condition is None else condition & c
        df = outer.df.join(grouped.df, condition, "left")
    else:
        df = beside(outer.df, grouped.df)
    algebra = outer.algebra
    fills = {c: F.coalesce(F.col(c), algebra.one()) for c, _ in grouped.factors}
    out = replace(outer, df=df.withColumns(fills), factors=outer.factors + grouped.factors, aggs=outer.aggs | grouped.aggs)
    empty = F.col(n).isNull()
    held = COMPARE[op](F.col(a), F.col(bound)) & (F.col(nulls) == 0)
    if op == "=":
        held = held & (F.col(bound) == F.col(other))
    if not out.options.symbolic or not algebra.symbolic:
        out = out.with_df(out.df.where(empty | held))
    if algebra.symbolic:
        text = factor(out, a, op, bound)
        out = out.with_factor(F.when(empty, algebra.one()).otherwise(text), Shape.CMP)
    gone = [bound, n, nulls, *([other] if op == "=" else []), *[i for i in keys if i in out.df.columns]]
    ids = {out.attribute(bound)}
    tensors = [out.aggs[i].tensor for i in ids if i in out.aggs]
    return replace(out, df=out.df.drop(*gone, *tensors), aggs={k: v for k, v in out.aggs.items() if k not in ids})


def scalar(outer: AnnotatedFrame, inner: AnnotatedFrame, a: str, op: str, spec: AggSpec, conditions: Sequence[Condition] = ()) -> AnnotatedFrame:
    """a op (SELECT agg FROM inner WHERE correlation): join with the aggregated inner side.

    COUNT keeps outer rows without inner rows, as 0 (the count bug).
    """
    if any(c[1] != "=" for c in conditions):
        raise UnsupportedForProvenance("use the SQL front end for other correlations")
    keys = [i for _, _, i in conditions]
    grouped = group_agg(replace(inner, aggs={}), keys, [spec])
    condition = None
    for o, _, i in conditions:
        c = F.col(o) == F.col(i)
        condition = c if condition is None else condition & c
    if spec.monoid == "count" and keys:
        out = outer_attach(outer, grouped, condition, spec.name)
    elif condition is None:
        out = attach(outer, grouped, None)
    else:
        out = attach(outer, grouped, condition)
    return select_agg(out, a, op, spec.name)


def outer_attach(outer: AnnotatedFrame, inner: AnnotatedFrame, condition: Column, count: str) -> AnnotatedFrame:
    """Left join with a counted side: no row counts as 0, times 1."""
    before = inner.agg(count)
    zero = fresh("c")
    df = outer.df.join(inner.df, condition, "left").withColumn(zero, F.coalesce(F.col(count), F.lit(0)))
    fills = {c: F.coalesce(F.col(c), outer.algebra.one()) for c, _ in inner.factors}
    if before:
        fills[before.tensor] = F.coalesce(F.col(before.tensor), written(empty_sum("count")))
    df = df.withColumns(fills).drop(count).withColumnRenamed(zero, count)
    out = replace(outer, df=df, factors=outer.factors + inner.factors, caveats=outer.caveats)
    return replace(out, aggs=outer.aggs | ({out.attribute(count): Agg("count", before.tensor)} if before else {}))


def not_exists(outer: AnnotatedFrame, inner: AnnotatedFrame, conditions: Sequence[Condition]) -> AnnotatedFrame:
    """NOT EXISTS is not monotone: by default a plain anti join that keeps the outer
    annotation; *reject* raises; *monus* records what is subtracted."""
    return _negated(outer, inner, conditions, null_aware=False)


def not_in(outer: AnnotatedFrame, inner: AnnotatedFrame, u: Sequence[str], v: Sequence[str], conditions: Sequence[Condition] = ()) -> AnnotatedFrame:
    return _negated(outer, inner, [*((a, "=", b) for a, b in zip(u, v, strict=True)), *conditions], null_aware=True)


def _negated(outer: AnnotatedFrame, inner: AnnotatedFrame, conditions: Sequence[Condition], null_aware: bool) -> AnnotatedFrame:
    if outer.options.negation == "reject":
        raise UnsupportedForProvenance("a negated subquery is not monotone")
    if outer.options.negation == "monus":
        return monus(outer, inner, conditions)
    condition = None
    for o, op, i in conditions:
        c = COMPARE[op](F.col(o), F.col(i))
        # An unknown comparison keeps the row from NOT IN.
        c = F.coalesce(c, F.lit(True)) if null_aware else c
        condition = c if condition is None else condition & c
    df = outer.df.join(inner.df, F.lit(True) if condition is None else condition, "left_anti")
    return outer.with_df(df).noted("negated subquery: only the outer annotation is kept")


def monus(outer: AnnotatedFrame, inner: AnnotatedFrame, conditions: Sequence[Condition]) -> AnnotatedFrame:
    """k ⊖ Σ inner (experimental): rows stay; the annotation tells what is subtracted."""
    if any(op != "=" for _, op, _ in conditions):
        raise UnsupportedForProvenance("monus needs equality conditions")
    return subtracted(outer, inner, [(F.col(o), F.col(i)) for o, _, i in conditions])


def intersect(left: AnnotatedFrame, right: AnnotatedFrame) -> AnnotatedFrame:
    """Set intersection: both sides grouped by all columns, null-safe equi-join, product."""
    l, names = grouped_inner(left, [F.col(f"`{c}`") for c in left.columns])
    r, other = grouped_inner(right, [F.col(f"`{c}`") for c in right.columns])
    condition = None
    for a, b in zip(names, other, strict=True):
        c = F.col(a).eqNullSafe(F.col(b))
        condition = c if condition is None else condition & c
    out = attach(l, r, condition)
    return out.with_df(out.df.drop(*other).withColumnsRenamed(dict(zip(names, left.columns, strict=True))))


def except_(left: AnnotatedFrame, right: AnnotatedFrame) -> AnnotatedFrame:
    """Set difference: not monotone; left rows without an equal right row, left annotation."""
    if left.options.negation == "reject":
        raise UnsupportedForProvenance("EXCEPT is not monotone")
    l, names = grouped_inner(left, [F.col(f"`{c}`") for c in left.columns])
    other = right.df.select(*[F.col(f"`{c}`").alias(fresh("k")) for c in right.columns])
    condition = None
    for a, b in zip(names, other.columns, strict=True):
        c = F.col(a).eqNullSafe(F.col(b))
        condition = c if condition is None else condition & c
    df = l.df.join(other, condition, "left_anti").withColumnsRenamed(dict(zip(names, left.columns, strict=True)))
    return l.with_df(df).noted("except: only the left annotation is kept")


def prefix_exists(outer: AnnotatedFrame, inner: AnnotatedFrame, a: str, op: str, b: str) -> AnnotatedFrame:
    """EXISTS with one order comparison, without pairs of rows.

    The inner side is listed once, in the order of its annotations; each distinct
    outer value takes from the list what it compares with.  Results equal the domain
    rule's: annotations of equal inner values are terms of their own, in one order.
    """
    if op not in ("<", "<=", ">", ">="):
        raise UnsupportedForProvenance("order comparisons only")
    if not outer.algebra.symbolic or outer.algebra.recorder is not None or measuring():
        return exists_domain(outer, inner, [F.col(a)], COMPARE[op](F.col(a), F.col(b)))
    inner = inner.one_factor()
    terms, value, prov = fresh("terms"), fresh("k"), fresh("prov")
    listed = inner.df.where(F.col(b).isNotNull()).agg(F.sort_array(F.collect_list(F.struct(F.col(inner.factors[0][0]).alias("p"), F.col(b).alias("b")))).alias(terms))
    values = outer.df.select(F.col(a).alias(value)).where(F.col(value).isNotNull()).distinct()
    met = F.filter(F.col(terms), lambda t: COMPARE[op](F.col(value), t["b"]))
    df = beside(values, listed, certain=True).select(value, met.alias(terms)).where(F.size(terms) > 0)
    df = df.select(value, outer.algebra.delta(F.array_join(F.transform(terms, lambda t: t["p"]), PLUS)).alias(prov))
    return attach(outer, replace(inner, df=df, factors=((prov, Shape.DELTA),), aggs={}), F.col(a) == F.col(value))
