"""Baselines that the method is compared with.

* *plain*: the query itself.
* *full witness*: each result row once per contributing combination, with all
  columns of every base row that took part.  Aggregates are left-joined
  (null-safe on the keys) with the witnesses of their input; subqueries are joined
  by their rows, not grouped.
* *token witness*: the same with one token column per base table; it refuses
  subqueries in WHERE and count-of-counts, as reported, unless ``strict=False``.
* *function circuit*: polynomials put together by row-at-a-time functions that
  Catalyst cannot see into; no subqueries, no ORDER BY on aggregates, no HAVING.
"""

from __future__ import annotations

from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType

from polyprov.engine import Engine
from polyprov.errors import UnsupportedForBaseline, UnsupportedForProvenance
from polyprov.functions.algebra import TEXT, Algebra, Shape
from polyprov.operators.frame import AnnotatedFrame, fresh
from polyprov.options import Options
from polyprov.plans import catalyst as cat
from polyprov.plans.annotate import Annotator

SUBQUERIES = {"Exists", "InSubquery", "ScalarSubquery"}


def plain(engine: Engine, query: str | DataFrame) -> DataFrame:
    return engine.plain(query)


# A witness run carries columns, not annotations: nothing symbolic is written.
_WITNESS = Algebra("witness", lambda t: t, lambda: F.lit(None).cast("string"), lambda p: p[0], lambda n: F.first(f"`{n}`"), lambda c: c)


class WitnessAnnotator(Annotator):
    """Factors are witness columns; ``names`` maps them to what they are called."""

    def __init__(self, policies, columns: str = "all", strict: bool = False, sublink: str = "left"):
        super().__init__(policies, Options(), _WITNESS)
        self.columns, self.strict, self.sublink = columns, strict, sublink
        self.names: dict[str, str] = {}
        self.uses: dict[str, int] = {}
        self.uncorrelated: set[str] = set()
        #: Aggregated rows that have no witness stay, with nulls; else, nor do result rows
        #: repeat for each witness of an uncorrelated scalar subquery.
        self.lone = True
        #: The next aggregation gives its values alone.
        self.bare = False

    def scalar(self, af, s):
        before = {c for c, _ in af.factors}
        plan = s.plan().toString()
        # One over aggregated rows keeps their annotations in its own: those witnesses count.
        alike = not s.outerAttrs().size() and plan.count("Aggregate [") < 2 and "CTERelationRef" not in plan
        self.bare = alike and not self.lone
        out, value = super().scalar(af, s)
        self.bare = False
        if alike:
            self.uncorrelated |= {c for c, _ in out.factors} - before
        return out, value

    def on_SubqueryAlias(self, plan, sub):
        child = plan.child()
        if cat.name_of(child) not in ("View", "LogicalRelation", "LocalRelation", "LogicalRDD"):
            return self.node(child, sub)
        table = plan.identifier().name()
        n = self.uses[table] = self.uses.get(table, 0) + 1
        label = table if n == 1 else f"{table}_{n}"
        df = cat.frame(plan)
        added = {}
        if self.columns == "token":
            added[fresh("prov")] = (self.policies(table).column(df.columns), f"prov_{label}")
        else:
            for a in cat.items(plan.output()):
                added[fresh("prov")] = (cat.column(a), f"prov_{label}_{a.name()}")
        self.names |= {k: name for k, (_, name) in added.items()}
        return AnnotatedFrame(df.withColumns({k: c for k, (c, _) in added.items()}), tuple((k, Shape.ATOM) for k in added), {}, _WITNESS, self.options)

    def on_CTERelationRef(self, plan, sub):
        _, af = self.ctes[plan.cteId()]
        out = super().on_CTERelationRef(plan, sub)
        self.names |= {new: f"{self.names[old]}_{plan.output().apply(0).exprId().id()}" for (old, _), (new, _) in zip(af.factors, out.factors, strict=True)}
        return out

    def on_GlobalLimit(self, plan, sub):
        """The limit holds for result rows: those of the plain query keep their witnesses."""
        below = plan.child().child() if cat.name_of(plan.child()) == "LocalLimit" else plan.child()
        af, chosen = self.node(below, sub), cat.frame(plan)
        exact = [a for a in cat.items(plan.output()) if a.dataType().simpleString() not in ("double", "float")]
        names = [fresh("k") for _ in exact]
        chosen = chosen.select(*[cat.column(a).alias(n) for a, n in zip(exact, names, strict=True)]).distinct()
        condition = F.lit(True)
        for a, n in zip(exact, names, strict=True):
            condition = condition & cat.column(a).eqNullSafe(F.col(n))
        return af.with_df(af.df.join(chosen, condition).drop(*names))

    def on_Aggregate(self, plan, sub):
        """Aggregated result, left-joined with the rows it was made of."""
        met = len(sub.conditions) if sub is not None else 0
        bare, self.bare = self.bare, False
        child = self.node(plan.child(), sub)
        groups, named = cat.items(plan.groupingExpressions()), cat.items(plan.aggregateExpressions())
        keys = [cat.column(g) for g in groups]
        if sub is not None and len(sub.conditions) > met:
            child, extra = self.correlated_keys(child, sub, met)
            keys += extra
        names = [fresh("k") for _ in keys]
        values = [cat.column(e) for e in named if any(cat.name_of(x) == "AggregateExpression" for x in cat.walk(e))]
        copies = [cat.column(e) for e in named if not any(cat.name_of(x) == "AggregateExpression" for x in cat.walk(e)) and cat.name_of(e) != "AttributeReference"]
        exprs = [*values, *copies] or [F.count(F.lit(1)).alias(fresh("n"))]
        # Values come from the query's own rows: those of `child` may repeat per inner witness.
        base = child.df if sub is not None or "CTERelationRef" in plan.toString() else cat.frame(plan.child())
        result = base.groupBy(*keys).agg(*exprs)
        if bare:
            return replace(child, df=result, factors=(), aggs={})
        own = cat.output(result)[: len(keys)]
        rows = child.df.select(*[k.alias(n) for k, n in zip(keys, names, strict=True)], *[c for c, _ in child.factors])
        condition = F.lit(True)
        for a, n in zip(own, names, strict=True):
            condition = condition & cat.column(a).eqNullSafe(F.col(n))
        if not self.lone:
            # The side that is small is known when it is there: an outer join could not take it so.
            return replace(child, df=result.join(rows, condition).drop(*names) if keys else rows.crossJoin(F.broadcast(result)), aggs={})
        return replace(child, df=result.join(rows, condition, "left").drop(*names), aggs={})

    def on_Distinct(self, plan, sub):
        # A witness per derivation: rows are kept.
        return self.node(plan.child(), sub)

    def on_Union(self, plan, sub):
        parts, slots = [], []
        for child in cat.items(plan.children()):
            af = self.node(child)
            parts.append((af, [cat.column(a) for a in cat.items(child.output())]))
            slots += [c for c, _ in af.factors]
        types = {c: af.df.schema[c].dataType for af, _ in parts for c, _ in af.factors}
        df = None
        for af, cols in parts:
            mine = {c for c, _ in af.factors}
            part = af.df.select(*cols, *[F.col(c) if c in mine else F.lit(None).cast(types[c]).alias(c) for c in slots])
            df = part if df is None else df.union(part)
        return replace(parts[0][0], df=df, factors=tuple((c, Shape.ATOM) for c in slots))

    def condition(self, af, c):
        if self.strict and SUBQUERIES & {cat.name_of(e) for e in cat.walk(c)}:
            raise UnsupportedForBaseline("subquery in WHERE")
        return super().condition(af, c)

    def exists(self, outer, inner, conditions, keys=(), pairs=()):
        """Joined with every matching inner row: outer rows repeat."""
        condition = F.lit(True)
        for c in conditions:
            condition = condition & cat.column(cat.without_outer(c))
        for o, i in pairs:
            condition = condition & (o == i)
        for o, k, safe in keys:
            condition = condition & (o.eqNullSafe(F.col(k)) if safe else o == F.col(k))
        df = outer.df.join(inner.df, condition)
        if self.sublink == "left" and not conditions and not keys and pairs:
            # Uncorrelated: a left join, and those without a partner filtered out after it.
            mark = fresh("hit")
            df = outer.df.join(inner.df.withColumn(mark, F.lit(1)), condition, "left").where(F.col(mark).isNotNull()).drop(mark)
        kept = [cat.column(a) for a in cat.output(outer.df)]
        return replace(outer, df=df.select(*kept, *[c for c, _ in inner.factors]), factors=outer.factors + inner.factors)

    def result(self, query: DataFrame, uncorrelated: bool = True) -> DataFrame:
        """Result columns and witness columns; those of uncorrelated scalar subqueries,
        which every row has alike, can be left out."""
        af, out = self.run(query)
        return af.df.select(*map(cat.column, out), *[F.col(c).alias(self.names[c]) for c, _ in af.factors if uncorrelated or c not in self.uncorrelated])


def full_witness(engine: Engine, query: str | DataFrame, sublink: str = "left") -> DataFrame:
    return WitnessAnnotator(engine.policy, "all", False, sublink).result(engine.plain(query))


def token_witness(engine: Engine, query: str | DataFrame, strict: bool = True, columns: str = "token") -> DataFrame:
    df = engine.plain(query)
    if strict and _groups_aggregated(cat.analyzed(df)):
        raise UnsupportedForBaseline("grouping by an aggregated column")
    return WitnessAnnotator(engine.policy, columns, strict).result(df)


def _groups_aggregated(plan) -> bool:
    """Whether a column made by an aggregate is a grouping key further up."""
    made: set[int] = set()

    def visit(p) -> bool:
        if any(visit(k) for k in cat.children(p)):
            return True
        if cat.name_of(p) == "Aggregate":
            keys = set().union(*[cat.references(g) for g in cat.items(p.groupingExpressions())], set())
            if keys & made:
                return True
            made.update(e.exprId().id() for e in cat.items(p.aggregateExpressions()) if any(cat.name_of(x) == "AggregateExpression" for x in cat.walk(e)))
        return False

    return visit(plan)


# ------------------------------------------------------------ function circuit


def _row_times(*parts):
    @F.udf("string")
    def run(*xs):
        return " · ".join(xs)

    return run(*parts)


@F.pandas_udf(StringType())
def _group_plus(s: pd.Series) -> str:
    return " + ".join(sorted(s.dropna()))


def _row_delta(c):
    @F.udf("string")
    def run(x):
        return f"δ({x})"

    return run(c)


_OPAQUE = Algebra("function_circuit", TEXT.token, TEXT.one, lambda p: _row_times(*p), lambda n: _group_plus(F.col(f"`{n}`")), _row_delta)


class _CircuitAnnotator(Annotator):
    def condition(self, af, c):
        raise UnsupportedForBaseline("subquery, or HAVING on an aggregate")

    def on_Sort(self, plan, sub):
        child = self.node(plan.child(), sub)
        below = plan.child()
        while cat.name_of(below) in ("Project", "SubqueryAlias"):
            below = below.child()
        if cat.name_of(below) == "Aggregate":
            made = {e.exprId().id() for e in cat.items(below.aggregateExpressions()) if any(cat.name_of(x) == "AggregateExpression" for x in cat.walk(e))}
            if any(cat.references(o) & made for o in cat.items(plan.order())):
                raise UnsupportedForBaseline("ORDER BY on an aggregate")
        return child.with_df(cat.frame(cat.rebuilt(plan, [cat.analyzed(child.df)])))

    def on_Join(self, plan, sub):
        if "outer" in plan.joinType().sql().lower():
            raise UnsupportedForBaseline("outer join")
        return super().on_Join(plan, sub)

    def on_Aggregate(self, plan, sub):
        """Values, the annotation, and formal sums by functions: Python joins, Python groups."""
        below = plan.child()
        while cat.name_of(below) in ("Project", "SubqueryAlias", "Filter"):
            below = below.child()
        if cat.name_of(below) == "Aggregate":
            raise UnsupportedForBaseline("aggregation over an aggregation")
        child = self.node(plan.child(), sub).one_factor()
        groups, named = cat.items(plan.groupingExpressions()), cat.items(plan.aggregateExpressions())
        keys, p = [cat.column(g) for g in groups], child.factors[0][0]
        calls = [(e, x) for e in named for x in cat.walk(e) if cat.name_of(x) == "AggregateExpression"]
        if any(cat.name_of(e.child()) != "AggregateExpression" for e, _ in calls):
            raise UnsupportedForBaseline("expression over aggregates")
        terms = {}

        @F.udf("string")
        def row_tensor(k, m):
            return None if m is None else f"{k}⊗{m}"

        for _, x in calls:
            args = cat.children(x.aggregateFunction())
            value = F.lit("1") if not args or cat.name_of(args[0]) == "Literal" else cat.column(args[0]).cast("string")
            terms[fresh("term")] = row_tensor(F.col(p), value)
        df = child.df.withColumns(terms)
        # Python group functions and built-in ones do not share an aggregation: two, joined.
        names = [fresh("k") for _ in keys]
        values = [cat.column(e) for e in named if cat.name_of(e) != "AttributeReference"]
        prov, sums = fresh("prov"), [fresh("sum") for _ in terms]
        result = df.groupBy(*keys).agg(*(values or [F.count(F.lit(1)).alias(fresh("n"))]))
        texts = df.groupBy(*[k.alias(n) for k, n in zip(keys, names, strict=True)]).agg(_group_plus(F.col(p)).alias(prov), *[_group_plus(F.col(t)).alias(s) for t, s in zip(terms, sums, strict=True)])
        own = cat.output(result)[: len(keys)]
        condition = F.lit(True)
        for a, n in zip(own, names, strict=True):
            condition = condition & cat.column(a).eqNullSafe(F.col(n))
        joined = result.join(texts, condition).drop(*names)
        joined = joined.withColumn(prov, _row_delta(F.col(prov))) if keys else joined
        self.sums = sums
        return replace(child, df=joined, factors=((prov, Shape.DELTA),), aggs={})


def function_circuit(engine: Engine, query: str | DataFrame) -> DataFrame:
    """Result columns, formal sums (``agg_1`` ...) and ``prov``."""
    df = engine.plain(query)
    if _nested(cat.analyzed(df)):
        raise UnsupportedForBaseline("subquery")
    a = _CircuitAnnotator(engine.policy, Options(), _OPAQUE)
    a.sums = []
    try:
        af, out = a.run(df)
    except UnsupportedForProvenance as e:
        raise UnsupportedForBaseline(str(e)) from e
    there = [s for s in a.sums if s in af.df.columns]
    c, _ = af.product()
    return af.df.select(*map(cat.column, out), *[F.col(s).alias(f"agg_{i + 1}") for i, s in enumerate(there)], c.alias("prov"))


def _nested(plan) -> bool:
    found = any(SUBQUERIES & {cat.name_of(e) for e in cat.walk(x)} for x in cat.items(plan.expressions()))
    return found or any(_nested(k) for k in cat.children(plan))
