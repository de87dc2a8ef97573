"""Circuit annotations: gates addressed by hashes, for results of any fan-in.

An annotation is the 16-byte id of a gate.  A token's id hashes the token; a
product's, its factors; a group's, the operator and the group's keys.  So the
edges of a GROUP BY are a narrow projection of its input (no exchange, no string
aggregate), the aggregation itself is an ordinary one, and the result's ids are
made from its own keys.  A comparison refers to the gates of its formal sums
instead of copying them.

Edges are kept per operator, lowest first; expansion and evaluation walk them
level by level with joins, so their depth is that of the plan, not of the data.
"""

from __future__ import annotations

import itertools
from collections.abc import Sequence
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from polyprov.errors import UnsupportedForProvenance
from polyprov.functions.algebra import Algebra, Shape, bracketed
from polyprov.operators import frame as fr
from polyprov.plans import catalyst as cat
from polyprov.plans.annotate import Annotator
from polyprov.sources.storage import cut

_runs = itertools.count()


def gate(*parts: Column) -> Column:
    """128-bit id; parts are length-prefixed and nulls marked, so none run together."""
    texts = []
    for p in parts:
        s = p.cast("string")
        texts += [F.coalesce(F.concat(F.length(s).cast("string"), F.lit(":"), s), F.lit("~"))]
    return F.unhex(F.md5(F.concat(*texts)))


def token_gate(token: Column) -> Column:
    return gate(F.lit("token"), token)


@dataclass
class Level:
    """Edges of one operator: parent, child, ord, value."""

    kind: str
    edges: DataFrame
    #: For products: whether a child has to be bracketed in text.
    shapes: tuple[Shape, ...] = ()
    monoid: str | None = None


@dataclass
class Circuit:
    tokens: list[DataFrame] = field(default_factory=list)
    levels: list[Level] = field(default_factory=list)

    # recording, by the rewriter

    def record_base(self, df: DataFrame, token: Column) -> None:
        self.tokens.append(df.select(token_gate(token).alias("gate"), token.alias("token")))

    def record_product(self, df: DataFrame, factors: Sequence[tuple[str, Shape]], name: str) -> None:
        pairs = F.array(*[F.struct(F.col(c).alias("child"), F.lit(i).alias("ord")) for i, (c, _) in enumerate(factors)])
        self.levels.append(Level("product", df.select(F.col(name).alias("parent"), F.explode(pairs).alias("e")).select("parent", "e.child", "e.ord", F.lit(None).cast("string").alias("value")), tuple(s for _, s in factors)))

    def record_group(self, kind: str, df: DataFrame, parent: Column, child: str, value: Column | None = None, shape: Shape = Shape.ATOM, monoid: str | None = None) -> None:
        v = F.lit(None).cast("string") if value is None else value
        edges = df.select(parent.alias("parent"), F.col(child).alias("child"), F.lit(0).alias("ord"), v.alias("value"))
        self.levels.append(Level(kind, edges if value is None else edges.where(F.col("value").isNotNull()), (shape,), monoid))

    # use

    def tables(self) -> tuple[DataFrame, DataFrame]:
        """(edges with level and kind, tokens), to be written bucketed by parent."""
        edges = None
        for i, x in enumerate(self.levels):
            part = x.edges.select(F.lit(i).alias("level"), F.lit(x.kind).alias("kind"), F.lit(x.monoid).alias("monoid"), "parent", "child", "ord", "value")
            edges = part if edges is None else edges.union(part)
        tokens = None
        for t in self.tokens:
            tokens = t if tokens is None else tokens.union(t)
        return edges, tokens.distinct()

    def _walk(self, leaf: Column, product, plus, delta, tensor, wanted: DataFrame | None) -> DataFrame:
        """gate, x: the image of every gate (below ``wanted`` gates only)."""
        levels = self.levels
        if wanted is not None:
            reach, kept = wanted.select("gate").distinct(), []
            for x in reversed(levels):
                e = cut(x.edges.join(reach.withColumnRenamed("gate", "parent"), "parent", "left_semi"))
                kept.append(replace(x, edges=e))
                reach = cut(reach.union(e.select(F.col("child").alias("gate"))).distinct())
            levels = kept[::-1]
        values = None
        for t in self.tokens:
            part = t.select("gate", leaf.alias("x"))
            values = part if values is None else values.union(part)
        values = values.groupBy("gate").agg(F.first("x").alias("x"))
        if wanted is not None:
            values = values.join(reach, "gate", "left_semi")
        values = cut(values)
        for x in levels:
            e = x.edges.withColumnRenamed("child", "gate").join(values, "gate")
            if x.kind == "product":
                new = product(e, x.shapes)
            elif x.kind == "tensor":
                new = tensor(e, x.shapes[0], x.monoid)
            else:
                new = plus(e)
                if x.kind == "delta":
                    new = new.withColumn("x", delta(F.col("x")))
            # Each level is cut off: a later one would else compute all before it again.
            values = values.union(cut(new.select(F.col("parent").alias("gate"), "x")))
        return values

    def expand(self, wanted: DataFrame | None = None) -> DataFrame:
        """gate, x: annotations and formal sums as canonical text."""

        def product(e, shapes):
            # Products have few children: as many as the join block has relations.
            text = F.col("x")
            for i, s in enumerate(shapes):
                if s is Shape.SUM:
                    text = F.when(F.col("ord") == i, bracketed(F.col("x"), s)).otherwise(text)
            parts = e.select("parent", "ord", text.alias("x")).distinct().groupBy("parent").agg(F.array_sort(F.collect_list(F.struct("ord", "x"))).alias("p"))
            return parts.select("parent", F.array_join(F.transform("p", lambda s: s["x"]), " · ").alias("x"))

        def plus(e):
            return e.groupBy("parent").agg(F.expr("listagg(x, ' + ') WITHIN GROUP (ORDER BY x)").alias("x"))

        def tensor(e, shape, monoid):
            t = e.select("parent", F.concat(bracketed(F.col("x"), shape), F.lit("⊗"), "value").alias("x"))
            return t.groupBy("parent").agg(F.expr(f"listagg(x, ' +{monoid} ') WITHIN GROUP (ORDER BY x)").alias("x"))

        return self._walk(F.col("token"), product, plus, lambda c: F.concat(F.lit("δ("), c, F.lit(")")), tensor, wanted)

    def count(self, deleted: DataFrame | None = None, wanted: DataFrame | None = None) -> DataFrame:
        """gate, x: multiplicities, with ``deleted`` tokens (column ``token``) set to 0."""
        tokens = self.tokens
        if deleted is not None:
            gone = deleted.select("token", F.lit(0).cast("bigint").alias("n"))
            tokens = [t.join(gone, "token", "left").select("gate", F.coalesce("n", F.lit(1).cast("bigint")).alias("token")) for t in tokens]
        one = replace(self, tokens=tokens)

        def product(e, shapes):
            parts = e.select("parent", "ord", "x").distinct().groupBy("parent").agg(F.collect_list("x").alias("p"))
            return parts.select("parent", F.aggregate("p", F.lit(1).cast("bigint"), lambda a, b: a * b).alias("x"))

        def plus(e):
            return e.groupBy("parent").agg(F.sum("x").cast("bigint").alias("x"))

        leaf = F.col("token") if deleted is not None else F.lit(1).cast("bigint")
        return one._walk(leaf, product, plus, lambda c: F.least(c, F.lit(1).cast("bigint")), lambda e, s, m: plus(e), wanted)


class CircuitAnnotator(Annotator):
    """Valued mode with gate ids for annotations and for formal sums."""

    def __init__(self, policies, options):
        self.circuit, self.run_id, self.nodes = Circuit(), next(_runs), itertools.count()
        algebra = Algebra("circuit", token_gate, lambda: gate(F.lit("one")), lambda p: gate(F.lit("product"), *[F.hex(c) for c in p]), lambda n: F.first(f"`{n}`"), lambda c: c, recorder=self)
        super().__init__(policies, options, algebra)

    def on_SubqueryAlias(self, plan, sub):
        af = super().on_SubqueryAlias(plan, sub)
        child = plan.child()
        if cat.name_of(child) in ("View", "LogicalRelation", "LocalRelation", "LogicalRDD"):
            df = cat.frame(plan)
            self.circuit.record_base(df, self.policies(plan.identifier().name()).column(df.columns))
        return af

    def product(self, df, factors, name):
        self.circuit.record_product(df, factors, name)

    def group(self, af, keys, values, formals, delta):
        """Edges from the input; a plain aggregation; ids from the keys."""
        af = af.one_factor() if af.factors else af.with_factor(self.algebra.one(), Shape.ATOM)
        if af.aggs and any(f.inner is not None for f in formals):
            raise UnsupportedForProvenance("re-aggregation in circuits")
        node = f"{self.run_id}.{next(self.nodes)}"
        prov, shape = af.factors[0]
        names = [fr.fresh("k") for _ in keys]
        ids = lambda what, ks: gate(F.lit(f"{node}.{what}"), F.to_json(F.struct(*ks, F.lit(0).alias("z"))))
        keyed = af.df.withColumns(dict(zip(names, keys, strict=True)))
        mine = [F.col(n) for n in names]
        if keys:
            self.circuit.record_group("delta" if delta else "sum", keyed, ids("g", mine), prov)
        sums = {}
        for i, f in enumerate(formals):
            value = f.value if f.where is None else F.when(f.where, f.value)
            self.circuit.record_group("tensor", keyed, ids(f"t{i}", mine), prov, value, shape, f.monoid)
            sums[f.name] = fr.Agg(f.monoid, fr.fresh("sum"))
        grouped = af.df.groupBy(*keys).agg(*(values or [F.count(F.lit(1)).alias(fr.fresh("n"))]))
        own = [cat.column(a).alias(n) for a, n in zip(cat.output(grouped)[: len(keys)], names, strict=True)]
        p = fr.fresh("prov")
        grouped = grouped.withColumns({p: ids("g", own) if keys else self.algebra.one(), **{sums[f.name].tensor: ids(f"t{i}", own) for i, f in enumerate(formals)}})
        return replace(af, df=grouped, factors=((p, Shape.DELTA if delta else Shape.SUM),), aggs={}), sums

    def results(self, grouped, calls, texts, sums):
        """An expression over several formal sums gets a gate over theirs."""
        aggs, extra = {}, {}
        for e, inside in calls:
            known = [sums[texts[x.resultId().id()]] for x in inside if x.resultId().id() in texts]
            if len(known) == 1:
                aggs[e.exprId().id()] = fr.Agg("sum", known[0])
            elif known:
                name = fr.fresh("sum")
                extra[name] = gate(F.lit("expression"), F.lit(e.name()), *[F.hex(F.col(k)) for k in known])
                aggs[e.exprId().id()] = fr.Agg("expression", name)
        return replace(grouped, df=grouped.df.withColumns(extra) if extra else grouped.df, aggs=aggs)

    def compared(self, af, c):
        """Filter by value; the factor refers to the gates of the formal sums."""
        af = af.with_df(af.df.where(cat.column(c)))
        tensors = [af.aggs[i].tensor for i in sorted(cat.references(c) & af.aggs.keys())]
        if not tensors:
            return af
        return af.with_factor(gate(F.lit("compare"), F.lit(c.sql()), *[F.hex(F.col(t)) for t in tensors]), Shape.CMP)


def circuit(engine, query, **options) -> tuple[DataFrame, Circuit]:
    """Annotated result with gate ids, and its circuit."""
    a = CircuitAnnotator(engine.policy, replace(engine.options, **options))
    af, out = a.run(engine.plain(query))
    af = af.one_factor()
    cols, sums, names = [], [], set()
    for x in out:
        cols.append(cat.column(x))
        names.add(x.name())
        if (agg := af.aggs.get(x.exprId().id())) is not None:
            sums.append(F.col(agg.tensor).alias(x.name() + "_agg"))
    return af.df.select(*cols, *sums, F.col(af.factors[0][0]).alias("prov")), a.circuit
