"""Annotation algebras: what a token, a product, a sum and a group become.

One rewriter serves all; only these expressions change.  Everything here is
built-in Spark, so annotated plans stay inside code generation (up to the string
aggregates, which Spark plans as partial and final object-hash aggregates).
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence
from contextlib import contextmanager
from contextvars import ContextVar
from dataclasses import dataclass
from enum import Enum

from pyspark.sql import Column
from pyspark.sql import functions as F

from polyprov.errors import UnsupportedForProvenance


class Shape(Enum):
    """Static form of an annotation: tells where brackets are needed."""

    ATOM = "atom"
    PROD = "product"
    SUM = "sum"
    DELTA = "delta"
    CMP = "comparison"


TIMES, PLUS, TENSOR = " · ", " + ", "⊗"
ZERO, ONE = "0", "1"


#: While it holds, texts are built as their numbers of characters (``measured``).
_MEASURED: ContextVar[bool] = ContextVar("measured", default=False)


@contextmanager
def measured() -> Iterator[None]:
    """Rewriting within gives, for every text, its length as BIGINT: what the text would
    have is known without building it.  Rows and values are the same."""
    token = _MEASURED.set(True)
    try:
        yield
    finally:
        _MEASURED.reset(token)


#: While it holds, lists are resolved as they are aggregated (``folded``): "sums", or "all".
_FOLDED: ContextVar[str | None] = ContextVar("folded", default=None)


@contextmanager
def folded(what: str = "all") -> Iterator[None]:
    """Rewriting within writes, for a list of any length, a short text that resolves to
    the same with all tokens there: ``1⊗value`` for a formal sum and, for ``all``, a
    numeral for a sum of annotations.  Each addend is still written and read as text."""
    token = _FOLDED.set(what)
    try:
        yield
    finally:
        _FOLDED.reset(token)


def written(text: str) -> Column:
    """A constant text."""
    return F.lit(len(text)).cast("bigint") if _MEASURED.get() else F.lit(text)


def shown(c: Column) -> Column:
    """A text column of the data."""
    return F.length(c).cast("bigint") if _MEASURED.get() else c


def concatenated(*parts: Column) -> Column:
    """Texts one after the other; null if one of them is."""
    if not _MEASURED.get():
        return F.concat(*parts)
    out = parts[0]
    for p in parts[1:]:
        out = out + p
    return out


def measuring() -> bool:
    return _MEASURED.get()


def text_only(what: str) -> None:
    if _MEASURED.get():
        raise UnsupportedForProvenance(f"the length of {what} is not known without its text")


def ordered_listagg(name: str, delimiter: str) -> Column:
    """Texts of a group in their own (binary) order; null texts are left out."""
    if _MEASURED.get():
        return (F.sum(f"`{name}`") + F.lit(len(delimiter)) * (F.count(f"`{name}`") - 1)).cast("bigint")
    if (what := _FOLDED.get()) is not None:
        from polyprov.functions import udfs

        if delimiter == PLUS and what == "all":
            return udfs.folded_annotations(name)
        if delimiter.strip()[1:] in udfs.FOLDING:
            return udfs.folded_terms(name, delimiter.strip()[1:])
    return F.expr(f"listagg(`{name}`, '{delimiter}') WITHIN GROUP (ORDER BY `{name}`)")


@dataclass(frozen=True)
class Algebra:
    """``symbolic`` algebras write formal sums for aggregates, and comparisons."""

    name: str
    token: Callable[[Column], Column]
    one: Callable[[], Column]
    product: Callable[[Sequence[Column]], Column]
    #: Aggregate over the column of this name.
    plus: Callable[[str], Column]
    delta: Callable[[Column], Column]
    symbolic: bool = False
    #: Takes note of products and groups (circuits); gives the grouping itself.
    recorder: object | None = None

    def times(self, factors: Sequence[tuple[Column, Shape]]) -> tuple[Column, Shape]:
        if not factors:
            return self.one(), Shape.ATOM
        if len(factors) == 1:
            return factors[0]
        if not self.symbolic:
            return self.product([c for c, _ in factors]), Shape.PROD
        return self.product([bracketed(c, s) for c, s in factors]), Shape.PROD


def bracketed(c: Column, shape: Shape) -> Column:
    return concatenated(written("("), c, written(")")) if shape is Shape.SUM else c


def _joined(parts: Sequence[Column]) -> Column:
    out = [parts[0]]
    for p in parts[1:]:
        out += [written(TIMES), p]
    return concatenated(*out)


def _fold(f: Callable[[Column, Column], Column]) -> Callable[[Sequence[Column]], Column]:
    def run(parts: Sequence[Column]) -> Column:
        out = parts[0]
        for p in parts[1:]:
            out = f(out, p)
        return out

    return run


def _merge_witnesses(a: Column, b: Column) -> Column:
    pairs = F.flatten(F.transform(a, lambda x: F.transform(b, lambda y: F.array_sort(F.array_union(x, y)))))
    return _set(pairs)


def _merge_monomials(a: Column, b: Column) -> Column:
    pair = lambda x, y: F.struct((x["coef"] * y["coef"]).alias("coef"), F.array_sort(F.concat(x["toks"], y["toks"])).alias("toks"))
    return F.flatten(F.transform(a, lambda x: F.transform(b, lambda y: pair(x, y))))


def _bound(c: Column, f: Callable[[Column], Column]) -> Column:
    """``f`` of an expression that is evaluated once, however often ``f`` reads it."""
    return F.element_at(F.transform(F.array(c), f), 1)


def _set(c: Column) -> Column:
    """Sorted, without repetitions: neighbours are compared (array_distinct compares
    nested values pair by pair)."""
    return _bound(F.sort_array(c), lambda s: F.filter(s, lambda x, i: (i == 0) | (x != F.get(s, i - 1))))


def collected(monomials: Column) -> Column:
    """Monomials with equal tokens as one, in the order of their tokens: runs of the sorted list."""
    swapped = F.sort_array(F.transform(monomials, lambda m: F.struct(m["toks"].alias("toks"), m["coef"].alias("coef"))))

    def runs(s: Column) -> Column:
        starts = F.filter(F.transform(s, lambda x, i: F.when((i == 0) | (x["toks"] != F.get(s, i - 1)["toks"]), i)), lambda i: i.isNotNull())
        end = lambda p, j: F.coalesce(F.get(p, j + 1), F.size(s))
        total = lambda p, i, j: F.aggregate(F.slice(s, i + 1, end(p, j) - i), F.lit(0).cast("bigint"), lambda acc, m: acc + m["coef"])
        return _bound(starts, lambda p: F.transform(p, lambda i, j: F.struct(total(p, i, j).alias("coef"), F.get(s, i)["toks"].alias("toks"))))

    return _bound(swapped, runs)


def _level(token: Column, n: int) -> Column:
    return F.conv(F.substring(F.md5(token), 1, 6), 16, 10).cast("bigint") % F.lit(n)


def _grouped(c: Column) -> Column:
    """δ of a group's sum; resolved as well, where that is."""
    if _FOLDED.get() == "all" and not _MEASURED.get():
        return F.when(c == ZERO, ZERO).when(c.isNotNull(), ONE)
    return concatenated(written("δ("), c, written(")"))


TEXT = Algebra("text", shown, lambda: written(ONE), _joined, lambda n: ordered_listagg(n, PLUS), _grouped, symbolic=True)
NAT = Algebra("nat", lambda t: F.lit(1).cast("bigint"), lambda: F.lit(1).cast("bigint"), _fold(lambda a, b: a * b), lambda n: F.sum(f"`{n}`").cast("bigint"), lambda c: F.least(c, F.lit(1).cast("bigint")))
#: Bag counts through duplicate elimination: as NAT, but groups add up.
BAG = Algebra("bag", NAT.token, NAT.one, NAT.product, NAT.plus, lambda c: c)
BOOL = Algebra("bool", lambda t: F.lit(True), lambda: F.lit(True), _fold(lambda a, b: a & b), lambda n: F.bool_or(f"`{n}`"), lambda c: c)
LINEAGE = Algebra(
    "lineage", lambda t: F.array(t), lambda: F.array().cast("array<string>"), lambda p: F.array_sort(F.array_distinct(F.concat(*p))),
    lambda n: F.array_sort(F.array_distinct(F.flatten(F.collect_list(f"`{n}`")))), lambda c: c,
)
WHY = Algebra(
    "why", lambda t: F.array(F.array(t)), lambda: F.array(F.array().cast("array<string>")), _fold(_merge_witnesses),
    lambda n: _set(F.flatten(F.collect_list(f"`{n}`"))), lambda c: c,
)
NORMAL_FORM = Algebra(
    "normal_form",
    lambda t: F.array(F.struct(F.lit(1).cast("bigint").alias("coef"), F.array(t).alias("toks"))),
    lambda: F.array(F.struct(F.lit(1).cast("bigint").alias("coef"), F.array().cast("array<string>").alias("toks"))),
    lambda p: collected(_fold(_merge_monomials)(p)),
    lambda n: collected(F.flatten(F.collect_list(f"`{n}`"))),
    lambda c: c,
)
# Sample valuations of tokens: a cost of 1 to 9, a trust of 0.1 to 0.9, a clearance of 0 to 3.
COST = Algebra("cost", lambda t: (_level(t, 9) + 1).cast("double"), lambda: F.lit(0.0), _fold(lambda a, b: a + b), lambda n: F.min(f"`{n}`"), lambda c: c)
TRUST = Algebra("trust", lambda t: (_level(t, 9) + 1) / 10.0, lambda: F.lit(1.0), _fold(lambda a, b: a * b), lambda n: F.max(f"`{n}`"), lambda c: c)
CLEARANCE = Algebra("clearance", lambda t: _level(t, 4).cast("int"), lambda: F.lit(0), lambda p: F.greatest(*p) if len(p) > 1 else p[0], lambda n: F.min(f"`{n}`"), lambda c: c)

#: Characters of the text annotation, without building it (comparisons not counted).
LENGTH = Algebra(
    "length", lambda t: F.length(t).cast("bigint"), lambda: F.lit(1).cast("bigint"), lambda p: sum(p[1:], p[0]) + F.lit(len(TIMES) * (len(p) - 1)).cast("bigint"),
    lambda n: (F.sum(f"`{n}`") + F.lit(len(PLUS)) * (F.count(f"`{n}`") - 1)).cast("bigint"), lambda c: c + F.lit(3).cast("bigint"),
)

ALGEBRAS = {a.name: a for a in (TEXT, NAT, BAG, BOOL, LINEAGE, WHY, NORMAL_FORM, COST, TRUST, CLEARANCE, LENGTH)}


def valued(name: str, base: Algebra, valuation: Callable[[Column], Column]) -> Algebra:
    """``base`` with tokens valued by an expression over the token text."""
    return Algebra(name, valuation, base.one, base.product, base.plus, base.delta)
