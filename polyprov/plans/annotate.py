"""From an analyzed plan to an annotated frame, bottom-up.

Every node is either covered by a rule, or rebuilt over its annotated child when
it only passes rows on, or refused.  Subqueries in a filter become joins with
grouped inner sides on the way.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from polyprov.errors import UnsupportedForProvenance
from polyprov.functions.algebra import ALGEBRAS, Algebra, Shape, concatenated, text_only, written
from polyprov.operators.basic import Formal, _grouped, annotate_base, empty_sum, grouped_sums, join, union_all
from polyprov.operators.frame import Agg, AnnotatedFrame, constant, fresh, value_text
from polyprov.operators.unnest import attach, beside, either, except_, exists_domain, exists_equal, intersect, subtracted
from polyprov.options import Options
from polyprov.plans import catalyst as cat
from polyprov.sources.tokens import TokenPolicy

#: Nodes that pass rows on: rebuilt with the annotated child in place.
PASSED = {"Sort", "GlobalLimit", "LocalLimit", "Offset", "Tail", "Window", "Generate", "Sample", "Repartition", "RepartitionByExpression", "RebalancePartitions", "ResolvedHint", "EventTimeWatermark"}
LIMITS = {"GlobalLimit", "LocalLimit", "Offset", "Tail"}
SYMBOL = {"EqualTo": "=", "EqualNullSafe": "<=>", "LessThan": "<", "LessThanOrEqual": "<=", "GreaterThan": ">", "GreaterThanOrEqual": ">="}
ARITHMETIC = {"Add": "+", "Subtract": "-", "Multiply": "*", "Divide": "/", "Remainder": "%"}
MONOID = {"Sum": "sum", "Count": "count", "Min": "min", "Max": "max", "Average": "avg", "StddevSamp": "stddev", "StddevPop": "stddev", "VarianceSamp": "variance", "VariancePop": "variance", "CovSample": "covar", "CovPopulation": "covar"}


@dataclass
class Subquery:
    """What a subquery's plan reads from the outer query, found on the way up."""

    outer: AnnotatedFrame
    conditions: list = field(default_factory=list)
    #: (outer column, inner key column, null-safe) after an aggregation took the conditions in.
    keys: list[tuple[Column, str, bool]] = field(default_factory=list)
    counts: bool = False


class Annotator:
    """One annotation run over a plan."""

    def __init__(self, policies: Callable[[str], TokenPolicy], options: Options = Options(), algebra: Algebra | None = None):
        self.policies, self.options = policies, options
        self.algebra = algebra or ALGEBRAS[options.algebra]
        self.ctes: dict[int, tuple[object, AnnotatedFrame]] = {}
        #: The filter right above the aggregation that comes next.
        self.having = None
        #: Sums of doubles are added in one order: an equality between two of them asks for it.
        self.steady = False
        #: The next aggregation leaves the addends of its groups in rows of their own.
        self.spread = False

    # ------------------------------------------------------------ dispatch

    def run(self, df: DataFrame) -> tuple[AnnotatedFrame, list]:
        plan = cat.analyzed(df)
        self.steady = self.algebra.recorder is None and cat.equals_subquery(df)
        return self.node(plan), cat.items(plan.output())

    def node(self, plan, sub: Subquery | None = None) -> AnnotatedFrame:
        kind = cat.name_of(plan)
        method = getattr(self, f"on_{kind}", None)
        if method is not None:
            return method(plan, sub)
        if kind in PASSED:
            if kind in LIMITS and self.options.limit_policy == "reject":
                raise UnsupportedForProvenance("LIMIT chooses rows on values that the annotation does not follow")
            child = self.node(plan.child(), sub)
            out = child.with_df(cat.frame(cat.rebuilt(plan, [cat.analyzed(child.df)])))
            if kind == "Window" and self.options.frame_prov:
                out = self.framed(plan, out)
            return out.noted("limit: rows were chosen on original values") if kind in LIMITS else out
        raise UnsupportedForProvenance(kind)

    # ------------------------------------------------------------ leaves

    def on_SubqueryAlias(self, plan, sub):
        child = plan.child()
        if cat.name_of(child) in ("View", "LogicalRelation", "LocalRelation", "LogicalRDD"):
            name = plan.identifier().name()
            return annotate_base(cat.frame(plan), self.policies(name), self.options, self.algebra)
        return self.node(child, sub)

    def on_OneRowRelation(self, plan, sub):
        return AnnotatedFrame(cat.frame(plan), (), {}, self.algebra, self.options)

    def on_WithCTE(self, plan, sub):
        for d in cat.items(plan.cteDefs()):
            self.ctes[d.id()] = (d, self.node(d.child()))
        return self.node(plan.plan(), sub)

    def on_CTERelationRef(self, plan, sub):
        """Each use has attribute ids of its own; rows and annotations are shared."""
        d, af = self.ctes[plan.cteId()]
        renamed, cols, aggs = {}, [], {}
        for h in af.hidden:
            renamed[h] = fresh("prov" if h.startswith("__prov") else "sum")
            cols.append(F.col(h).alias(renamed[h]))
        for attr, like in zip(cat.items(d.child().output()), cat.items(plan.output()), strict=True):
            cols.append(cat.alias_as(attr, like))
            if (agg := af.aggs.get(attr.exprId().id())) is not None:
                aggs[like.exprId().id()] = Agg(agg.monoid, renamed[agg.tensor])
        return replace(af, df=af.df.select(*cols), factors=tuple((renamed[c], s) for c, s in af.factors), aggs=aggs)

    # ------------------------------------------------------------ rows

    def on_Project(self, plan, sub):
        child = self.node(plan.child(), sub)
        named = cat.items(plan.projectList())
        for s in [x for e in named for x in cat.walk(e) if cat.name_of(x) == "ScalarSubquery"]:
            # In a select list: rows without an inner row stay, with NULL.
            child, found = self.scalar(child, s, optional=True)
            wanted = s.exprId().id()
            named = [cat.transform(e, lambda x: found if cat.name_of(x) == "ScalarSubquery" and x.exprId().id() == wanted else None) for e in named]
        cols, aggs, extra = [], dict(child.aggs), {}
        there = {a.exprId().id() for a in cat.output(child.df)}
        for e in named:
            i = e.exprId().id()
            if cat.name_of(e) == "AttributeReference":
                if sub is None:
                    cols.append(cat.column(e))
                continue
            if i not in there:
                cols.append(cat.column(e))
            read = cat.references(e) & child.aggs.keys()
            if read and self.algebra.symbolic:
                inner = e.child()
                if cat.name_of(inner) == "AttributeReference":
                    aggs[i] = child.aggs[inner.exprId().id()]
                else:
                    s = fresh("sum")
                    extra[s] = self.term(child, inner)
                    aggs[i] = Agg("+".join(sorted({child.aggs[r].monoid for r in read})), s)
        df = child.df.withColumns(extra) if extra else child.df
        if sub is None:
            ids = {e.exprId().id() for e in named}
            aggs = {k: v for k, v in aggs.items() if k in ids}
            hidden = [c for c, _ in child.factors] + list(dict.fromkeys(a.tensor for a in aggs.values()))
            return replace(child, df=df.select(*cols, *hidden), aggs=aggs)
        # Inside a subquery all columns stay, for conditions that are met further up.
        return replace(child, df=df.select("*", *cols) if cols else df, aggs=aggs)

    def on_Filter(self, plan, sub):
        self.having = plan if cat.name_of(plan.child()) == "Aggregate" and self.lists and not self.options.symbolic else None
        af = self.node(plan.child(), sub)
        later = []
        for c in cat.conjuncts(plan.condition()):
            kinds = {cat.name_of(e) for e in cat.walk(c)}
            if sub is not None and "OuterReference" in kinds and not kinds & {"Exists", "InSubquery", "ScalarSubquery"}:
                sub.conditions.append(c)
            elif kinds & {"Exists", "InSubquery", "ScalarSubquery"} or cat.references(c) & af.aggs.keys():
                later.append(c)
            else:
                af = af.with_df(af.df.where(cat.column(c)))
        for c in later:
            af = self.condition(af, c)
        return af

    def on_Join(self, plan, sub):
        left, right = self.node(plan.left(), sub), self.node(plan.right(), sub)
        how, c = plan.joinType().sql().lower(), cat.option(plan.condition())
        if how in ("left semi", "left anti"):
            return self.semi(left, right, c, how)
        how = {"inner": "inner", "cross": "cross", "left outer": "left", "right outer": "right", "full outer": "full"}.get(how)
        if how is None:
            raise UnsupportedForProvenance(f"{plan.joinType().sql()} join")
        if c is not None and cat.references(c) & (left.aggs.keys() | right.aggs.keys()):
            if how not in ("inner", "cross"):
                raise UnsupportedForProvenance("outer join on an aggregated column")
            out = join(left, right)
            for part in cat.conjuncts(c):
                out = self.condition(out, part)
            return out
        return join(left, right, None if c is None else cat.column(c), how)

    def on_LateralJoin(self, plan, sub):
        """The inner side once per correlated key, joined with its annotation."""
        how, own = plan.joinType().sql().lower(), plan.right().plan()
        if how not in ("inner", "cross", "left outer"):
            raise UnsupportedForProvenance(f"lateral {how} join")
        left = self.node(plan.left(), sub)
        s = Subquery(left)
        right = self.node(own, s)
        kept = cat.items(own.output())
        ids = {a.exprId().id() for a in kept}
        condition = F.lit(True)
        for o, k, safe in s.keys:
            condition = condition & (o.eqNullSafe(F.col(k)) if safe else o == F.col(k))
        for c in s.conditions:
            condition = condition & cat.column(cat.without_outer(c))
        if (c := cat.option(plan.condition())) is not None:
            condition = condition & cat.column(c)
        if s.counts and s.keys:
            raise UnsupportedForProvenance("a lateral COUNT, whose empty groups count 0")
        top = own
        while cat.name_of(top) in ("Project", "SubqueryAlias"):
            top = top.child()
        # An aggregate without GROUP BY has a row for every outer row, of NULLs if there is nothing.
        always = cat.name_of(top) == "Aggregate" and not top.groupingExpressions().size()
        return join(left, replace(right, aggs={i: a for i, a in right.aggs.items() if i in ids}), condition, "left" if how == "left outer" or always else "inner")

    def semi(self, left, right, c, how):
        if how == "left anti":
            if self.options.negation == "reject":
                raise UnsupportedForProvenance("an anti join is not monotone")
            return left.with_df(left.df.join(right.df, F.lit(True) if c is None else cat.column(c), "left_anti")).noted("anti join: only the left annotation is kept")
        return self.exists(left, right, cat.conjuncts(c) if c is not None else [])

    # ------------------------------------------------------------ sets

    def on_Union(self, plan, sub):
        parts = []
        for child in cat.items(plan.children()):
            af = self.node(child)
            cols = [cat.column(a) for a in cat.items(child.output())]
            parts.append(replace(af, df=af.df.select(*cols, *af.hidden)))
        return union_all(*parts)

    def on_Distinct(self, plan, sub):
        child = plan.child()
        af = self.node(child, sub)
        keys = [cat.column(a) for a in cat.items(child.output())]
        return _grouped(af, keys, [], [], delta=cat.name_of(child) != "Union")

    def on_Deduplicate(self, plan, sub):
        af = self.node(plan.child(), sub)
        keys = cat.items(plan.keys())
        ids = {k.exprId().id() for k in keys}
        rest = [a for a in cat.items(plan.child().output()) if a.exprId().id() not in ids]
        firsts = {fresh("first"): a for a in rest}
        out = _grouped(af, [cat.column(k) for k in keys], [F.first(cat.column(a)).alias(n) for n, a in firsts.items()], [])
        by = {a.name(): a for a in cat.output(out.df)}
        return out.with_df(out.df.select(*[cat.column(k) for k in keys], *[cat.alias_as(by[n], a) for n, a in firsts.items()], *out.hidden))

    def _pair(self, plan, rule):
        sides = []
        for child in (plan.left(), plan.right()):
            af = self.node(child)
            sides.append((replace(af, df=af.df.select(*[cat.column(a).alias(fresh("c")) for a in cat.items(child.output())], *af.hidden), aggs={})))
        if plan.isAll():
            raise UnsupportedForProvenance(f"{cat.name_of(plan)} ALL")
        out = rule(*sides)
        mine = cat.output(out.df)
        hidden = set(out.hidden)
        named = [a for a in mine if a.name() not in hidden]
        return out.with_df(out.df.select(*[cat.alias_as(a, like) for a, like in zip(named, cat.items(plan.left().output()), strict=True)], *out.hidden))

    def on_Intersect(self, plan, sub):
        return self._pair(plan, intersect)

    def on_Except(self, plan, sub):
        return self._pair(plan, except_)

    # ------------------------------------------------------------ aggregation

    @property
    def lists(self) -> bool:
        """Whether groups list their rows' annotations: it pays to drop rows before."""
        return self.algebra.symbolic and self.algebra.recorder is None

    def surviving(self, child: AnnotatedFrame, having, plan) -> AnnotatedFrame:
        """Rows of the groups that pass the filter above, found on values alone.

        Values shrink before their shuffle, lists of annotations do not: so those are
        built for the groups that stay.
        """
        groups, named = cat.items(plan.groupingExpressions()), cat.items(plan.aggregateExpressions())
        if not groups or cat.outer_in(having):
            return child
        # The same aggregation under names of its own, so that nothing above is taken for it.
        values = {e.exprId().id(): (e, fresh("v")) for e in named if any(cat.name_of(x) == "AggregateExpression" for x in cat.walk(e))}
        names = [fresh("k") for _ in groups]
        plain = cat.frame(plan.child()).groupBy(*[cat.column(g).alias(n) for g, n in zip(groups, names, strict=True)]).agg(*[cat.column(e.child()).alias(n) for e, n in values.values()])
        by = {a.name(): a for a in cat.output(plain)}
        mine = {i: by[n] for i, (_, n) in values.items()}
        for g, n in zip(groups, names, strict=True):
            for e in named:
                if (e.child() if cat.name_of(e) == "Alias" else e).semanticEquals(g):
                    mine[e.exprId().id()] = by[n]
        known, kept = {a.exprId().id() for a in cat.output(plain)}, None
        for c in cat.conjuncts(having.condition()):
            if not any(cat.name_of(e) in ("ScalarSubquery", "Exists", "InSubquery") for e in cat.walk(c)):
                c = cat.transform(c, lambda e: mine.get(e.exprId().id()) if cat.name_of(e) == "AttributeReference" else None)
                if cat.references(c) and cat.references(c) <= known:
                    kept = (plain if kept is None else kept).where(cat.column(c))
        if kept is None:
            return child
        kept = kept.select(*names)
        same = None
        for g, n in zip(groups, names, strict=True):
            c = cat.column(g).eqNullSafe(F.col(n))
            same = c if same is None else same & c
        return child.with_df(child.df.join(kept, same, "left_semi"))

    def restricted(self, inner: AnnotatedFrame, outer: DataFrame, pairs) -> AnnotatedFrame:
        """Inner rows that some outer row asks for, where the outer side is filtered."""
        if not pairs or not self.lists or not cat.filtered(outer):
            return inner
        asked = outer.select(*[p[0].alias(fresh("k")) for p in pairs]).distinct()
        same = None
        for p, n in zip(pairs, asked.columns, strict=True):
            c = p[1].eqNullSafe(F.col(n)) if len(p) > 2 and p[2] else p[1] == F.col(n)
            same = c if same is None else same & c
        return inner.with_df(inner.df.join(asked, same, "left_semi"))

    def on_Aggregate(self, plan, sub):
        having, self.having = self.having, None
        spread, self.spread = self.spread, False
        child_plan = plan.child()
        expand = cat.name_of(child_plan) == "Expand"
        met = len(sub.conditions) if sub is not None else 0
        child = self.expanded(child_plan, sub) if expand else self.node(child_plan, sub)
        if having is not None and not expand:
            child = self.surviving(child, having, plan)
        groups, named = cat.items(plan.groupingExpressions()), cat.items(plan.aggregateExpressions())
        keys = [cat.column(g) for g in groups]
        extra = []
        if sub is not None and len(sub.conditions) > met:
            child, extra = self.correlated_keys(child, sub, met)
            keys += extra
        values, formals, copies = [], [], []
        calls = []
        for e in named:
            inside = [x for x in cat.walk(e) if cat.name_of(x) == "AggregateExpression"]
            if not inside:
                if cat.name_of(e) != "AttributeReference":
                    copies.append(e)
                continue
            values.append(cat.steady_sum(e) if self.steady else cat.column(e))
            calls.append((e, inside))
        distinct = [x for _, inside in calls for x in inside if x.isDistinct()]
        if distinct and self.options.rewrite_distinct and (self.algebra.symbolic or self.algebra.recorder is not None):
            child = self.distinct_rows(child, keys, distinct, sum(len(i) for _, i in calls))
            keys = [cat.column(g) if cat.name_of(g) == "AttributeReference" else k for g, k in zip(groups, keys, strict=False)] + keys[len(groups) :]
        texts = {}
        if self.algebra.symbolic or self.algebra.recorder is not None:
            for e, inside in calls:
                for x in inside:
                    if (f := self.formal(child, x)) is not None:
                        key = x.resultId().id()
                        texts[key] = f.name
                        formals.append(f)
        if sub is not None and any(cat.name_of(x.aggregateFunction()) == "Count" for _, i in calls for x in i):
            sub.counts = True
        # Copies of keys under other names are outputs of the aggregation as well.
        grouped, sums = grouped_sums(child, keys, [*values, *map(cat.column, copies)], formals, spread=spread)
        return grouped if spread else self.results(grouped, calls, texts, {n: a.tensor for n, a in sums.items()})

    def formal(self, child, x) -> Formal | None:
        """The formal sum of one aggregate call; None for functions that have none."""
        f = x.aggregateFunction()
        monoid = MONOID.get(cat.name_of(f))
        if monoid is None:
            return None
        where = cat.option(x.filter())
        where = None if where is None else cat.column(where)
        args = cat.children(f)
        name = fresh("f")
        if not args or (monoid == "count" and cat.name_of(args[0]) == "Literal"):
            return Formal(name, monoid, written("1"), where)
        read = cat.references(args[0]) & child.aggs.keys()
        if read:
            plain = cat.name_of(args[0]) == "AttributeReference"
            return Formal(name, monoid, None, where, self.term(child, args[0]), child.aggs[args[0].exprId().id()].monoid if plain else None)
        if monoid == "count":
            there = cat.column(args[0]).isNotNull()
            for a in args[1:]:
                there = there & cat.column(a).isNotNull()
            return Formal(name, monoid, F.when(there, written("1")), where)
        if len(args) > 1 and monoid == "covar":
            return Formal(name, monoid, concatenated(*[p for a in args[:2] for p in (value_text(child.df, cat.column(a), self.options), written(","))][:-1]), where)
        return Formal(name, monoid, value_text(child.df, cat.column(args[0]), self.options), where)

    def results(self, grouped, calls, texts, sums):
        """Tie each result column to its formal sum, or to an expression over several."""
        if not self.algebra.symbolic:
            return replace(grouped, aggs={})
        aggs, extra = {}, {}
        for e, inside in calls:
            known = [x for x in inside if x.resultId().id() in texts]
            if not known:
                continue
            i = e.exprId().id()
            body = e.child() if cat.name_of(e) == "Alias" else e
            monoid = MONOID[cat.name_of(known[0].aggregateFunction())]
            if cat.name_of(body) == "AggregateExpression":
                aggs[i] = Agg(monoid, sums[texts[known[0].resultId().id()]])
            else:
                s = fresh("sum")
                by = {x.resultId().id(): sums[texts[x.resultId().id()]] for x in known}
                extra[s] = self.term(grouped, body, by)
                aggs[i] = Agg(monoid, s)
        return replace(grouped, df=grouped.df.withColumns(extra) if extra else grouped.df, aggs=aggs)

    def distinct_rows(self, child, keys, distinct, n_calls):
        """COUNT(DISTINCT x): first the distinct (keys, x), each with δ of its rows."""
        args = [cat.children(x.aggregateFunction()) for x in distinct]
        if len(distinct) != n_calls or len({tuple(a.exprId().id() if cat.name_of(a) == "AttributeReference" else None for a in x) for x in args}) > 1:
            raise UnsupportedForProvenance("DISTINCT aggregates beside others")
        if any(cat.name_of(a) != "AttributeReference" for a in args[0]):
            raise UnsupportedForProvenance("DISTINCT aggregate of an expression; name it in a subquery")
        x = [cat.column(a) for a in args[0]]
        there = None
        for c in x:
            there = c.isNotNull() if there is None else there & c.isNotNull()
        if not keys:
            child = child.with_df(child.df.where(there))
        return _grouped(child, [*keys, *x], [], [])

    def expanded(self, plan, sub):
        """Grouping sets: each row once per set, its annotation with it."""
        child = self.node(plan.child(), sub).one_factor()
        child = replace(child, aggs={})
        attr = next(a for a in cat.output(child.df) if a.name() == child.factors[0][0])
        jvm = cat._jvm()
        projections = [cat.seq([*cat.items(p), attr]) for p in cat.items(plan.projections())]
        # The annotation leaves the expansion under an attribute of its own.
        name = fresh("prov")
        alias = cat.analyzed(child.df.select(F.col(child.factors[0][0]).alias(name))).output().apply(0)
        node = jvm.org.apache.spark.sql.catalyst.plans.logical.Expand(cat.seq(projections), cat.seq([*cat.items(plan.output()), alias]), cat.analyzed(child.df))
        return replace(child, df=cat.frame(node), factors=((name, child.factors[0][1]),))

    def framed(self, plan, af):
        """Each row's annotation times δ of the annotations in its first frame."""
        af = af.one_factor()
        p, shape = af.factors[0]
        spec = cat.items(plan.windowExpressions())[0]
        window = next(e for e in cat.walk(spec) if cat.name_of(e) == "WindowSpecDefinition")
        from pyspark.sql import Window

        w = Window.partitionBy(*[cat.column(e) for e in cat.items(window.partitionSpec())])
        if orders := cat.items(window.orderSpec()):
            w = w.orderBy(*[cat.column(e.child()).asc() if "ASC" in e.direction().sql() else cat.column(e.child()).desc() for e in orders])
        frame = window.frameSpecification()
        if cat.name_of(frame) == "SpecifiedWindowFrame":
            low, high = frame.lower().sql(), frame.upper().sql()
            def bound(t: str) -> int:
                if "UNBOUNDED" in t:
                    return Window.unboundedPreceding if "PRECEDING" in t else Window.unboundedFollowing
                if "CURRENT" in t:
                    return 0
                n = int("".join(c for c in t if c.isdigit()))
                return -n if "-" in t or "PRECEDING" in t else n

            try:
                w = (w.rowsBetween if frame.frameType().sql() == "ROWS" else w.rangeBetween)(bound(low), bound(high))
            except ValueError as e:
                raise UnsupportedForProvenance(f"window frame {low} to {high}") from e
        text_only("a frame's annotation")
        whole = F.array_join(F.array_sort(F.collect_list(F.col(p)).over(w)), " + ")
        name = fresh("prov")
        return replace(af, df=af.df.withColumn(name, concatenated(written("δ("), whole, written(")"))).drop(p), factors=((name, Shape.DELTA),))

    # ------------------------------------------------------------ conditions

    def condition(self, af: AnnotatedFrame, c) -> AnnotatedFrame:
        """A conjunct with a subquery, or on an aggregated column."""
        kind = cat.name_of(c)
        if kind == "Exists":
            sub = Subquery(af)
            inner = self.node(c.plan(), sub)
            return self.exists(af, inner, sub.conditions, sub.keys)
        if kind == "InSubquery":
            sub = Subquery(af)
            plan = c.query().plan()
            inner = self.node(plan, sub)
            values = [cat.column(v) for v in cat.items(c.values())]
            own = [cat.column(v) for v in cat.items(plan.output())[: len(values)]]
            return self.exists(af, inner, sub.conditions, sub.keys, list(zip(values, own, strict=True)))
        kinds = [cat.name_of(e) for e in cat.walk(c)]
        if kind == "Not" and cat.name_of(c.child()) == "Exists" and self.options.negation == "monus":
            inner, pairs = self.positive(af, c.child())
            return subtracted(af, inner, pairs)
        if kind == "Or" and "Not" not in kinds and {"Exists", "InSubquery"} & set(kinds) and self.lists and not cat.references(c) & af.aggs.keys():
            try:
                return self.disjunction(af, c)
            except UnsupportedForProvenance:
                pass  # as below: the outer rows are filtered
        if "Exists" in kinds or "InSubquery" in kinds:
            # Negated, or under OR: the outer rows are filtered, the inner side is not annotated.
            if self.options.negation == "reject":
                raise UnsupportedForProvenance("a subquery under NOT or OR is not monotone")
            if cat.references(c) & af.aggs.keys() and self.options.symbolic:
                raise UnsupportedForProvenance("a negated subquery on an aggregated column in symbolic mode")
            return af.with_df(af.df.where(cat.column(c))).noted("subquery under NOT or OR: only the outer annotation is kept")
        own = set(af.aggs)
        for s in [e for e in cat.walk(c) if cat.name_of(e) == "ScalarSubquery"]:
            af, found = self.scalar(af, s)
            wanted = s.exprId().id()
            c = cat.transform(c, lambda e: found if cat.name_of(e) == "ScalarSubquery" and e.exprId().id() == wanted else None)
        # The subquery's value serves the comparison only: it is no column of the relation.
        return self.without_aggs(self.compared(af, c), own)

    def positive(self, af: AnnotatedFrame, c) -> tuple[AnnotatedFrame, list[tuple]]:
        """The annotated inner side of EXISTS or IN, and its equalities with the outer side."""
        sub = Subquery(af)
        if cat.name_of(c) == "Exists":
            inner, pairs = self.node(c.plan(), sub), []
        else:
            plan = c.query().plan()
            inner = self.node(plan, sub)
            values = [cat.column(v) for v in cat.items(c.values())]
            pairs = list(zip(values, [cat.column(v) for v in cat.items(plan.output())[: len(values)]], strict=True))
        outer_ids = {a.exprId().id() for a in cat.output(af.df)}
        for x in sub.conditions:
            pair = self.equality(x, outer_ids)
            if pair is None:
                raise UnsupportedForProvenance("a correlation other than equality here")
            pairs.append(pair)
        return inner, [*pairs, *((o, F.col(k), safe) for o, k, safe in sub.keys)]

    def disjunction(self, af: AnnotatedFrame, c) -> AnnotatedFrame:
        parts, plain, inners = [c], None, []
        while any(cat.name_of(p) == "Or" for p in parts):
            parts = [x for p in parts for x in ((p.left(), p.right()) if cat.name_of(p) == "Or" else (p,))]
        for p in parts:
            if cat.name_of(p) in ("Exists", "InSubquery"):
                inners.append(self.positive(af, p))
            elif any(cat.name_of(e) in ("Exists", "InSubquery", "ScalarSubquery") for e in cat.walk(p)):
                raise UnsupportedForProvenance("a subquery within a part of a disjunction")
            else:
                plain = cat.column(p) if plain is None else plain | cat.column(p)
        return either(af, plain, inners)

    def without_aggs(self, af: AnnotatedFrame, kept: set[int]) -> AnnotatedFrame:
        gone = [a.tensor for i, a in af.aggs.items() if i not in kept]
        return replace(af, df=af.df.drop(*gone), aggs={i: a for i, a in af.aggs.items() if i in kept})

    def compared(self, af: AnnotatedFrame, c) -> AnnotatedFrame:
        """A comparison on aggregated columns: a factor, and in valued mode a filter."""
        if not cat.references(c) & af.aggs.keys() or not self.algebra.symbolic:
            return af.with_df(af.df.where(cat.column(c)))
        if not self.options.symbolic:
            af = af.with_df(af.df.where(cat.column(c)))
        return af.with_factor(concatenated(written("["), self.truth(af, c), written("]")), Shape.CMP)

    def exists(self, outer, inner, conditions, keys=(), pairs=()):
        equal, other = list(pairs), []
        outer_ids = {a.exprId().id() for a in cat.output(outer.df)}
        for c in conditions:
            pair = self.equality(c, outer_ids)
            if pair and self.options.exists_strategy != "domain":
                equal.append(pair)
            else:
                other.append(c)
        if keys:
            equal += [(o, F.col(k), safe) for o, k, safe in keys]
        if not other:
            return exists_equal(outer, self.restricted(inner, outer.df, equal), equal)
        domain = {}
        for c in other:
            for r in cat.walk(cat.without_outer(c)):
                if cat.name_of(r) == "AttributeReference" and r.exprId().id() in outer_ids:
                    domain[r.exprId().id()] = cat.column(r)
        condition = None
        for c in other:
            x = cat.column(cat.without_outer(c))
            condition = x if condition is None else condition & x
        # Equalities take part through columns of the outer side.
        named = outer.df
        added = []
        for o, i, *safe in equal:
            n = fresh("o")
            named = named.withColumn(n, o)
            added.append(n)
            condition = condition & (F.col(n).eqNullSafe(i) if any(safe) else F.col(n) == i)
        out = exists_domain(outer.with_df(named), inner, [*domain.values(), *map(F.col, added)], condition)
        return out.with_df(out.df.drop(*added))

    def equality(self, c, outer_ids):
        """(outer, inner) columns of an equality between the two sides, else None."""
        if cat.name_of(c) != "EqualTo":
            return None
        a, b = c.left(), c.right()
        for one, two in ((a, b), (b, a)):
            o, i = cat.references(cat.without_outer(one)), cat.references(two)
            if o and o <= outer_ids and i and not i & outer_ids and not cat.outer_references(two):
                return cat.column(cat.without_outer(one)), cat.column(two)
        return None

    def correlated_keys(self, child, sub, met):
        """Conditions met below an aggregation: it groups by their inner sides, or,
        where they are no equalities, by the outer values that they are met for."""
        outer_ids = {a.exprId().id() for a in cat.output(sub.outer.df)}
        mine, sub.conditions = sub.conditions[met:], sub.conditions[:met]
        pairs = [self.equality(c, outer_ids) for c in mine]
        keys = []
        if all(pairs):
            child = self.restricted(child, sub.outer.df, pairs)
            for o, i in pairs:
                n = fresh("k")
                child = child.with_df(child.df.withColumn(n, i))
                sub.keys.append((o, n, False))
                keys.append(F.col(n))
            return child, keys
        domain, condition = {}, None
        for c in mine:
            bare = cat.without_outer(c)
            for r in cat.walk(bare):
                if cat.name_of(r) == "AttributeReference" and r.exprId().id() in outer_ids:
                    domain[r.exprId().id()] = cat.column(r)
            condition = cat.column(bare) if condition is None else condition & cat.column(bare)
        names = [fresh("k") for _ in domain]
        values = sub.outer.df.select(*domain.values()).distinct()
        df = values.join(child.df, condition)
        for o, n in zip(domain.values(), names, strict=True):
            df = df.withColumn(n, o)
            sub.keys.append((o, n, True))
            keys.append(F.col(n))
        return child.with_df(df.drop(*domain.values())), keys

    def scalar(self, af, s, optional: bool = False):
        """Join with a scalar subquery; gives the frame and what stands for its value.

        ``optional``: outer rows without an inner row stay.
        """
        sub = Subquery(af)
        plan = s.plan()
        inner = self.node(plan, sub)
        value = cat.items(plan.output())[0]
        if sub.conditions:
            raise UnsupportedForProvenance("a correlated scalar subquery without an aggregate")
        hidden = [c for c, _ in inner.factors] + list(dict.fromkeys(a.tensor for i, a in inner.aggs.items() if i == value.exprId().id()))
        aggs = {i: a for i, a in inner.aggs.items() if i == value.exprId().id()}
        slim = replace(inner, df=inner.df.select(cat.column(value), *[k for _, k, _ in sub.keys], *hidden), aggs=aggs)
        if not sub.keys:
            # An aggregate over all rows: one row, whatever the size of the data; as text it
            # lists them all, so that it is not sent through the driver.  An equality with
            # its value becomes an equi-join, which holds that row and takes the others
            # past it (the other way round it keeps all rows that match it at once).
            if self.algebra.symbolic and (self.options.symbolic or not self.steady):
                return replace(af, df=beside(af.df, slim.df, certain=True), factors=af.factors + slim.factors, aggs=af.aggs | aggs, caveats=af.caveats + slim.caveats), value
            return attach(af, replace(slim, df=slim.df.hint("shuffle_hash") if self.algebra.symbolic else F.broadcast(slim.df)), None), value
        condition = None
        for o, k, safe in sub.keys:
            c = o.eqNullSafe(F.col(k)) if safe else o == F.col(k)
            condition = c if condition is None else condition & c
        if not sub.counts and not optional:
            return attach(af, slim, condition), value
        # The count bug: outer rows without inner rows count 0.
        fills = {c: F.coalesce(F.col(c), self.algebra.one()) for c, _ in slim.factors} | {a.tensor: F.coalesce(F.col(a.tensor), written(empty_sum(a.monoid))) for a in aggs.values()}
        df = af.df.join(slim.df, condition, "left").withColumns(fills)
        return replace(af, df=df, factors=af.factors + slim.factors, aggs=af.aggs | aggs), cat.or_zero(value) if sub.counts else value

    # ------------------------------------------------------------ texts

    def truth(self, af, c) -> Column:
        """A condition as text."""
        kind = cat.name_of(c)
        if kind in SYMBOL:
            return concatenated(self.side(af, c.left()), written(f" {SYMBOL[kind]} "), self.side(af, c.right()))
        if kind == "Not":
            inner = c.child()
            if cat.name_of(inner) == "EqualTo":
                return concatenated(self.side(af, inner.left()), written(" <> "), self.side(af, inner.right()))
            return concatenated(written("not ("), self.truth(af, inner), written(")"))
        if kind in ("And", "Or"):
            return concatenated(written("("), self.truth(af, c.left()), written(f") {kind.lower()} ("), self.truth(af, c.right()), written(")"))
        if kind == "In":
            parts = []
            for v in cat.items(c.list()):
                parts += [written(" or ("), self.side(af, c.value()), written(" = "), self.side(af, v), written(")")]
            return concatenated(written("("), *parts[1:])
        raise UnsupportedForProvenance(f"{kind} on an aggregated column")

    def side(self, af, e) -> Column:
        if cat.references(e) & af.aggs.keys():
            return self.term(af, e)
        return constant(value_text(af.df, cat.column(e), self.options))

    def term(self, af, e, calls: dict[int, str] | None = None) -> Column:
        """An expression over formal sums, as text."""
        kind = cat.name_of(e)
        if kind == "AggregateExpression" and calls is not None and e.resultId().id() in calls:
            return F.col(calls[e.resultId().id()])
        if kind == "AttributeReference" and e.exprId().id() in af.aggs:
            return F.col(af.aggs[e.exprId().id()].tensor)
        has = bool(cat.references(e) & af.aggs.keys()) or any(cat.name_of(x) == "AggregateExpression" for x in cat.walk(e))
        if not has:
            return value_text(af.df, cat.column(e), self.options)
        kids = cat.children(e)
        if kind in ("Cast", "Alias", "PromotePrecision", "CheckOverflow", "KnownNotNull"):
            return self.term(af, kids[0], calls)
        if kind == "Coalesce":
            # Filled only where there is no row; its formal sum is filled as well.
            return self.term(af, kids[0], calls)
        if kind in ARITHMETIC:
            return concatenated(written("("), self.term(af, kids[0], calls), written(f") {ARITHMETIC[kind]} ("), self.term(af, kids[1], calls), written(")"))
        parts = []
        for k in kids:
            parts += [written(", "), self.term(af, k, calls)]
        return concatenated(written(f"{e.prettyName()}("), *parts[1:], written(")"))
