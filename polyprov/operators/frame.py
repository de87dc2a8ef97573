"""AnnotatedFrame: a DataFrame whose rows carry their annotation.

The annotation is kept as separate *factor* columns until an operator needs one
product: joins then stay plain joins of plain scans, which Catalyst can reorder
and prune.  Aggregated columns are known by the expression id of their attribute,
so they are followed through projections, joins and renamings without name rules.
"""

from __future__ import annotations

import itertools
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from polyprov.functions.algebra import ONE, TENSOR, TEXT, Algebra, Shape, bracketed, concatenated, shown, written
from polyprov.options import Options
from polyprov.plans import catalyst

_numbers = itertools.count()


def fresh(kind: str) -> str:
    """A column name that no user column has."""
    return f"__{kind}_{next(_numbers)}"


@dataclass(frozen=True)
class Agg:
    """An aggregated column: its monoid and the column with its formal sum."""

    monoid: str
    tensor: str


@dataclass(frozen=True)
class AnnotatedFrame:
    df: DataFrame
    #: (column, shape) of each factor; none at all is the annotation 1.
    factors: tuple[tuple[str, Shape], ...] = ()
    #: Aggregated columns by attribute id.
    aggs: dict[int, Agg] = field(default_factory=dict)
    algebra: Algebra = TEXT
    options: Options = Options()
    caveats: tuple[str, ...] = ()

    def with_df(self, df: DataFrame) -> AnnotatedFrame:
        return replace(self, df=df)

    def noted(self, caveat: str) -> AnnotatedFrame:
        return replace(self, caveats=(*self.caveats, caveat))

    @property
    def hidden(self) -> list[str]:
        """Columns of ours: factors and formal sums."""
        return [c for c, _ in self.factors] + list(dict.fromkeys(a.tensor for a in self.aggs.values()))

    @property
    def columns(self) -> list[str]:
        hidden = set(self.hidden)
        return [c for c in self.df.columns if c not in hidden]

    def attribute(self, name: str) -> int:
        """Attribute id of a column by its name."""
        found = [a for a in catalyst.output(self.df) if a.name() == name]
        if len(found) != 1:
            raise KeyError(f"{name}: {len(found)} columns")
        return found[0].exprId().id()

    def agg(self, name: str) -> Agg | None:
        return self.aggs.get(self.attribute(name))

    def product(self) -> tuple[Column, Shape]:
        return self.algebra.times([(F.col(c), s) for c, s in self.factors])

    def one_factor(self) -> AnnotatedFrame:
        """The product of the factors as one column."""
        if len(self.factors) == 1:
            return self
        c, shape = self.product()
        name = fresh("prov")
        gone = [f for f, _ in self.factors]
        df = self.df.withColumn(name, c)
        if self.algebra.recorder is not None and gone:
            self.algebra.recorder.product(df, self.factors, name)
        return replace(self, df=df.drop(*gone), factors=((name, shape),))

    def with_factor(self, c: Column, shape: Shape) -> AnnotatedFrame:
        name = fresh("prov")
        return replace(self, df=self.df.withColumn(name, c), factors=(*self.factors, (name, shape)))

    def neutral(self) -> AnnotatedFrame:
        """Rows of a helper relation: their annotation is 1."""
        return replace(self, factors=(), aggs={})

    def delivered(self, output: list[Column] | None = None) -> DataFrame:
        """Result columns, formal sums (valued mode), then ``prov``.

        Names that a user column already has are counted up (``prov_1`` ...).
        """
        kept = catalyst.output(self.df)
        hidden = set(self.hidden)
        attrs = [a for a in kept if a.name() not in hidden] if output is None else output
        cols, sums, names = [], [], {a.name() for a in attrs}

        def free(name: str) -> str:
            n, i = name, 0
            while n in names:
                i += 1
                n = f"{name}_{i}"
            names.add(n)
            return n

        for a in attrs:
            agg = self.aggs.get(a.exprId().id())
            if agg is None or not self.algebra.symbolic:
                cols.append(catalyst.column(a))
            elif self.options.symbolic:
                cols.append(F.col(agg.tensor).alias(a.name()))
            else:
                cols.append(catalyst.column(a))
                sums.append(F.col(agg.tensor).alias(free(a.name() + self.options.suffix)))
        c, _ = self.product()
        return self.df.select(*cols, *sums, c.alias(free("prov")))


def value_text(df: DataFrame, c: Column, options: Options) -> Column:
    """A value as text, the same on every engine: doubles as decimals."""
    kind = df.select(c.alias("v")).schema[0].dataType.typeName()
    return shown((c.cast(f"decimal(18,{options.value_scale})") if kind in ("double", "float") else c).cast("string"))


def tensor(prov: Column, shape: Shape, value: Column) -> Column:
    """annotation ⊗ value; null where the value is null."""
    return concatenated(bracketed(prov, shape), written(TENSOR), value)


def constant(value: Column) -> Column:
    return concatenated(written(ONE + TENSOR), value)
