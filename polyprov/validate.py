"""Validator of annotated results.

* result: without its annotations, the annotated result is the original one.
* aggregates: with all tokens there, symbolic rows of non-zero annotation are the
  original rows, and their formal sums resolve to the original values.
* products (sound): each monomial of a row lies within one of the row's witnesses.
* complete: each witness of a row contains one of its monomials.

Witnesses come from the un-aggregated token-witness join, which knows nothing of
annotations.  All comparisons are joins and aggregations; nothing is gathered.

A group's list can pass what a cell holds.  So lists are resolved as they are
aggregated, from the text of each addend, and monomials are compared a row each.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from polyprov.baselines import WitnessAnnotator
from polyprov.engine import Engine
from polyprov.functions import evaluate as ev
from polyprov.functions.algebra import folded
from polyprov.functions.grammar import parse, parse_value
from polyprov.functions.udfs import ATOMS, eval_n, eval_value
from polyprov.plans import catalyst as cat
from polyprov.plans.annotate import Annotator

SCALE = 4


@dataclass(frozen=True)
class Report:
    check: str
    rows: int
    missing: int
    extra: int

    @property
    def ok(self) -> bool:
        return not self.missing and not self.extra


def rounded(df: DataFrame, scale: int = SCALE) -> DataFrame:
    """Doubles as decimals, so that the order of summation does not show."""
    return df.select(*[F.col(f"`{f.name}`").cast(f"decimal(30,{scale})").alias(f.name) if f.dataType.typeName() in ("double", "float", "decimal") else F.col(f"`{f.name}`") for f in df.schema])


def compare(check: str, one: DataFrame, two: DataFrame) -> Report:
    """Bag comparison by counts per row: one aggregation over both."""
    both = one.withColumn("_side", F.lit(1)).union(two.withColumn("_side", F.lit(-1)))
    counts = both.groupBy(*[f"`{c}`" for c in one.columns]).agg(F.sum("_side").alias("_d"), F.count(F.when(F.col("_side") == 1, 1)).alias("_n"))
    r = counts.agg(F.sum("_n").alias("n"), F.sum(F.when(F.col("_d") > 0, F.col("_d"))).alias("missing"), F.sum(F.when(F.col("_d") < 0, -F.col("_d"))).alias("extra")).first()
    return Report(check, r["n"] or 0, r["missing"] or 0, r["extra"] or 0)


def check_result(engine: Engine, query: str, **options) -> Report:
    original = engine.plain(query)
    annotated = engine.rewrite(query, mode="valued", **options).select(*[f"`{c}`" for c in original.columns])
    return compare_within("result", original, annotated, 1e-9)


def check_aggregates(engine: Engine, query: str, mode: str = "symbolic", **options) -> Report:
    """In valued mode the formal sums beside the values are resolved instead (for
    queries whose symbolic result repeats a large sum in every row)."""
    original = engine.plain(query)
    with folded():
        af, output = engine.frame(query, mode=mode, **options)
        df = af.delivered(output)
    df = df.where(eval_n(F.col("prov")) > 0)
    cols = []
    for a, f in zip(output, original.schema, strict=True):
        c = F.col(f"`{a.name()}`" if mode == "symbolic" or a.exprId().id() not in af.aggs else f"`{a.name()}{af.options.suffix}`")
        cols.append(eval_value(c).cast(f.dataType).alias(f.name) if a.exprId().id() in af.aggs else c.alias(f.name))
    return compare_within("aggregates", original, df.select(*cols))


def compare_within(check: str, one: DataFrame, two: DataFrame, tolerance: float = 1e-4) -> Report:
    """Bag comparison in which numbers with fractions may differ by a share of
    ``tolerance`` (formal sums hold values of a fixed scale)."""
    loose = [f.name for f in one.schema if f.dataType.typeName() in ("double", "float", "decimal")]
    exact = [c for c in one.columns if c not in loose]

    def side(df: DataFrame, name: str) -> DataFrame:
        values = F.struct(*[F.col(f"`{c}`").cast("double").alias(f"v{i}") for i, c in enumerate(loose)], F.lit(0).alias("z"))
        key = F.to_json(F.struct(*[F.col(f"`{c}`") for c in exact], F.lit(0).alias("_z")))
        return df.groupBy(key.alias("key")).agg(F.sort_array(F.collect_list(values)).alias(name))

    near = lambda a, b: a.eqNullSafe(b) | (F.abs(a - b) <= tolerance * F.greatest(F.lit(1.0), F.abs(a)))
    pairs = F.zip_with("a", "b", lambda a, b: F.coalesce(F.forall(F.array(*[near(a[f"v{i}"], b[f"v{i}"]) for i in range(len(loose))], F.lit(True)), lambda x: x), F.lit(False)))
    same = (F.size("a") == F.size("b")) & F.forall(pairs, lambda x: x)
    both = side(one, "a").join(side(two, "b"), "key", "full").withColumn("same", F.coalesce(same, F.lit(False)))
    r = both.agg(F.sum(F.coalesce(F.size("a"), F.lit(0))).alias("n"), F.sum((~F.col("same") & F.col("a").isNotNull()).cast("int")).alias("missing"), F.sum((~F.col("same") & F.col("b").isNotNull()).cast("int")).alias("extra")).first()
    return Report(check, r["n"] or 0, r["missing"] or 0, r["extra"] or 0)


def _row_key(df: DataFrame, columns: list[str]) -> Column:
    parts = [F.coalesce(F.col(f"`{c}`").cast("decimal(30,2)") if df.schema[c].dataType.typeName() in ("double", "float", "decimal") else F.col(f"`{c}`"), F.lit("")).cast("string") for c in columns]
    return F.concat_ws("\x1f", *parts) if parts else F.lit("")


def _monomials(prov: Column, sums: list[Column]) -> Column:
    """Monomials of the annotation, or, where that is 1, of the formal sums' annotations."""

    @F.pandas_udf("array<array<string>>")
    def run(s: pd.Series, t: pd.Series) -> pd.Series:
        def one(x, y):
            out = ev.expand(parse(x))
            if set(out) == {()} and y is not None:
                out = {}
                todo = [parse_value(y)]
                while todo:
                    v = todo.pop()
                    if v[0] == "arith":
                        todo += [v[2], v[3]]
                    elif v[0] == "call":
                        todo += v[2]
                    elif v[0] == "terms":
                        for k in v[2]:
                            if k[0] == "nest":
                                todo.append(k[1])
                            else:
                                out |= ev.expand(k[1])
            return [list(m) for m in out]

        return pd.Series([None if x is None else one(x, y) for x, y in zip(s, t, strict=True)])

    return run(prov, F.coalesce(*sums) if sums else F.lit(None).cast("string"))


def _joined(tokens: Column) -> Column:
    return F.array_join(F.array_sort(tokens), " ")


def _addends(engine: Engine, query: str, original: DataFrame, **options) -> DataFrame:
    """key, m: a row per monomial of each result row."""
    if not cat.ends_in_groups(original):
        af, output = engine.frame(query, mode="valued", **options)
        df = af.delivered(output)
        prov, sums = F.col("prov"), [F.col(c) for c in df.columns if c.endswith("_agg")]
    else:
        # δ and sums do not change what the monomials are: the addends of a group have them.
        annotator = Annotator(engine.policy, replace(engine.options, mode="valued", **options))
        annotator.spread = True
        with folded("sums"):
            af, output = annotator.run(original)
            df = af.delivered(output)
        prov, sums = F.col("prov"), []
    easy = prov.rlike(ATOMS) & (prov != "1")
    plain = F.array(_joined(F.filter(F.split(prov, " · "), lambda t: t != "1")))
    found = F.when(easy, plain).otherwise(F.transform(_monomials(F.when(~easy, prov), [F.when(~easy, F.coalesce(*sums))] if sums else []), _joined))
    return df.select(_row_key(df, original.columns).alias("key"), F.explode(found).alias("m"))


def check_derivations(engine: Engine, query: str, **options) -> tuple[Report, Report]:
    """The sound and the complete check."""
    original = engine.plain(query)
    names = original.columns
    mine = _addends(engine, query, original, **options)
    witnesses = WitnessAnnotator(engine.policy, "token")
    witnesses.lone = False
    w = witnesses.result(original, uncorrelated=False)
    tokens = [F.col(f"`{c}`") for c in w.columns[len(names) :]]
    theirs = w.select(_row_key(w, names).alias("key"), _joined(F.array_compact(F.array(*tokens))).alias("m"))
    both = mine.withColumn("side", F.lit(1)).union(theirs.withColumn("side", F.lit(2))).groupBy("key", "m").agg(F.bit_or("side").alias("side"))
    # Most are equal; only the others are looked for within those of their row.
    keys = both.groupBy("key").agg(F.bit_or("side").alias("sides"), F.count_if(F.col("side") == 1).alias("m_left"), F.count_if(F.col("side") == 2).alias("w_left"))
    r = keys.agg(F.count("*").alias("n"), F.count_if(F.col("sides") != 3).alias("alone"), F.sum("m_left").alias("m_left"), F.sum("w_left").alias("w_left")).first()
    unsound = _outside(both, 1, 2) if r["m_left"] else 0
    unseen = _outside(both, 2, 1) if r["w_left"] else 0
    return Report("products", r["n"], 0, unsound + r["alone"]), Report("complete", r["n"], unseen + r["alone"], 0)


def _outside(both: DataFrame, side: int, other: int) -> int:
    """How many of one side's own lie within (contain, for witnesses) none of the other's.

    A monomial is looked for under one token of its own, the longest, which the fewest
    witnesses have."""
    rarest = lambda m: F.array_max(F.transform(F.split(m, " "), lambda t: F.struct(F.length(t).alias("n"), t.alias("t"))))["t"]
    left = both.where(F.col("side") == side).select(F.col("key").alias("k1"), F.col("m").alias("m1"))
    all_ = both.where(F.col("side").bitwiseAND(other) > 0).select(F.col("key").alias("k2"), F.col("m").alias("m2"))
    small, large = ("m1", "m2") if side == 1 else ("m2", "m1")
    left = left.withColumn("t1", rarest(F.col("m1")) if small == "m1" else F.explode(F.split("m1", " ")))
    all_ = all_.withColumn("t2", rarest(F.col("m2")) if small == "m2" else F.explode(F.split("m2", " ")))
    inside = F.size(F.array_except(F.split(small, " "), F.split(large, " "))) == 0
    found = left.join(all_, (F.col("k1") == F.col("k2")) & (F.col("t1") == F.col("t2")) & inside, "left_semi").select("k1", "m1").distinct()
    return left.select("k1", "m1").distinct().count() - found.count()


def validate(engine: Engine, query: str, mode: str = "symbolic", **options) -> list[Report]:
    return [check_result(engine, query, **options), check_aggregates(engine, query, mode, **options), *check_derivations(engine, query, **options)]


def validity(reports: dict[str, list[Report]]) -> float:
    """Share of queries that pass every check."""
    return sum(all(r.ok for r in rs) for rs in reports.values()) / len(reports) if reports else 1.0
