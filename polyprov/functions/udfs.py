"""Spark functions over annotation texts (Arrow-batched; never on the rule path)."""

from __future__ import annotations

from collections.abc import Iterable
from decimal import Decimal

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from polyprov.functions import evaluate as ev
from polyprov.functions.grammar import parse, parse_value


def eval_n(prov: Column, deleted: Iterable[str] = ()) -> Column:
    """Multiplicity of each row, with some tokens set to 0."""
    valuation = ev.without(deleted)

    @F.pandas_udf("long")
    def run(s: pd.Series) -> pd.Series:
        return s.map(lambda x: None if x is None else ev.evaluate(x, valuation))

    return run(prov)


def eval_value(tensor: Column, deleted: Iterable[str] = ()) -> Column:
    """Value of a formal sum as text, with some tokens set to 0; null for NULL."""
    valuation = ev.without(deleted)

    @F.pandas_udf("string")
    def run(s: pd.Series) -> pd.Series:
        def one(x):
            v = None if x is None else ev.evaluate_value(x, valuation)
            return None if v is None else str(v)

        return s.map(one)

    return run(tensor)


#: An atom other than 0.  Most addends are products of those, which Spark reads itself.
_ATOM = r"(?!0(?: |⊗|$))[^\s()\[\]⊗,]+"
ATOMS = rf"^{_ATOM}(?: · {_ATOM})*$"
_TERM = rf"^{_ATOM}(?: · {_ATOM})*⊗-?[0-9]+(?:\.[0-9]+)?$"

#: Monoids whose formal sums can be resolved part by part.
FOLDING = ("sum", "count", "min", "max", "avg")


def _numeral(n: Column) -> Column:
    """An annotation of multiplicity n, as long as its logarithm."""

    def written(x):
        bits = F.conv(x.cast("string"), 10, 2)
        rest = F.transform(F.sequence(F.lit(2), F.length(bits)), lambda i: F.substring(bits, i, F.lit(1)))
        return F.when(x < 2, x.cast("string")).otherwise(F.aggregate(rest, F.lit("1"), lambda a, b: F.concat(F.lit("(1 + 1) · ("), a, F.when(b == "1", F.lit(") + 1")).otherwise(F.lit(")")))))

    return F.element_at(F.transform(F.array(n), written), 1)


def folded_annotations(name: str) -> Column:
    """Aggregate: an annotation of the multiplicity that the sum of a group's has."""
    c = F.col(f"`{name}`")
    easy = c.rlike(ATOMS)

    @F.pandas_udf("long")
    def run(s: pd.Series) -> pd.Series:
        return pd.Series([None if x is None else ev.evaluate(x) for x in s], dtype="Int64")

    return _numeral(F.sum(F.when(easy, F.lit(1).cast("bigint")).otherwise(run(F.when(~easy, c)))))


def folded_terms(name: str, monoid: str) -> Column:
    """Aggregate: 1⊗value for a group's terms; null if nothing adds to it."""
    c = F.col(f"`{name}`")
    easy = c.rlike(_TERM)

    @F.pandas_udf("struct<n:bigint,v:string>")
    def run(s: pd.Series) -> pd.DataFrame:
        parts = [(0, None) if x is None else ev.folded(parse_value(x), monoid) for x in s]
        return pd.DataFrame({"n": [n for n, _ in parts], "v": pd.Series([None if v is None else format(v, "f") if isinstance(v, Decimal) else str(v) for _, v in parts], dtype=object)})

    other = run(F.when(~easy, c))
    v = F.when(easy, F.substring_index(c, "⊗", -1)).otherwise(other["v"])
    number = v.try_cast("decimal(38,10)")
    if monoid in ("min", "max"):
        by, of = (F.min_by, F.min) if monoid == "min" else (F.max_by, F.max)
        value = F.coalesce(by(v, number), of(v))
    elif monoid == "avg":
        value = F.sum(number) / F.sum(F.when(easy, F.lit(1).cast("bigint")).otherwise(other["n"]))
    else:
        value = F.sum(number)
    if monoid not in ("min", "max"):
        value = F.regexp_replace(F.regexp_replace(value.cast("string"), r"(\.\d*?)0+$", "$1"), r"\.$", "")
    return F.concat(F.lit("1⊗"), value)


def lineage_of(prov: Column) -> Column:
    @F.pandas_udf("array<string>")
    def run(s: pd.Series) -> pd.Series:
        return s.map(lambda x: None if x is None else sorted(ev.tokens(parse(x))))

    return run(prov)


def simplified(prov: Column) -> Column:
    from polyprov.functions.grammar import render

    @F.pandas_udf("string")
    def run(s: pd.Series) -> pd.Series:
        return s.map(lambda x: None if x is None else render(ev.simplify(parse(x))))

    return run(prov)


def monomials(df: DataFrame, prov: str = "prov", keys: list[str] | None = None) -> DataFrame:
    """keys, monomial (sorted tokens), coef: a row per monomial of each row."""
    keys = keys or []

    @F.pandas_udf("array<struct<coef:bigint,toks:array<string>>>")
    def run(s: pd.Series) -> pd.Series:
        return s.map(lambda x: [{"coef": n, "toks": list(m)} for m, n in sorted(ev.expand(parse(x)).items())])

    return df.select(*keys, F.explode(run(F.col(prov))).alias("m")).select(*keys, F.col("m.toks").alias("monomial"), F.col("m.coef").alias("coef"))


def tensors(df: DataFrame, column: str, keys: list[str] | None = None) -> DataFrame:
    """keys, k, m: a row per term of a formal sum."""
    from polyprov.functions.grammar import render

    keys = keys or []

    @F.pandas_udf("array<struct<k:string,m:string>>")
    def run(s: pd.Series) -> pd.Series:
        return s.map(lambda x: [{"k": render(t[1]), "m": t[2]} for t in parse_value(x)[2] if t[0] == "term"])

    return df.select(*keys, F.explode(run(F.col(column))).alias("t")).select(*keys, F.col("t.k").alias("k"), F.col("t.m").alias("m"))


def what_if(df: DataFrame, deleted: Iterable[str], columns: dict[str, str], prov: str = "prov") -> DataFrame:
    """Deletion propagation without running the query again.

    Rows whose annotation becomes 0 go; ``columns`` maps result columns to the columns
    with their formal sums (the same name in symbolic mode).  Exact for symbolic
    mode on monotone queries.
    """
    deleted = frozenset(deleted)
    out = df.where(eval_n(F.col(prov), deleted) > 0)
    return out.withColumns({c: eval_value(F.col(t), deleted) for c, t in columns.items()})


def what_if_joined(df: DataFrame, deleted: DataFrame, columns: dict[str, str], keys: list[str], prov: str = "prov") -> DataFrame:
    """``what_if`` for many deletions: ``deleted`` has a column ``token`` and stays distributed.

    ``keys`` tell the result's rows apart.  A row gets the deleted tokens that it holds, by a
    join on tokens, and is evaluated with these alone.
    """
    lists = [_tokens_in(F.col(prov), parse), *[_tokens_in(F.col(t), parse_value) for t in dict.fromkeys(columns.values())]]
    held = df.select(*keys, F.explode(F.array_distinct(F.flatten(F.array(*lists)))).alias("token"))
    gone = held.join(deleted.select("token").distinct(), "token").groupBy(*[F.col(k).alias(f"_key_{i}") for i, k in enumerate(keys)]).agg(F.collect_list("token").alias("_gone"))
    condition = F.lit(True)
    for i, k in enumerate(keys):
        condition = condition & F.col(k).eqNullSafe(F.col(f"_key_{i}"))
    joined = df.join(gone, condition, "left").drop(*[f"_key_{i}" for i in range(len(keys))])

    @F.pandas_udf("long")
    def count(s: pd.Series, gone: pd.Series) -> pd.Series:
        return pd.Series([0 if x is None else ev.evaluate(x, ev.without(() if g is None else g)) for x, g in zip(s, gone, strict=True)])

    @F.pandas_udf("string")
    def value(s: pd.Series, gone: pd.Series) -> pd.Series:
        values = [None if x is None else ev.evaluate_value(x, ev.without(() if g is None else g)) for x, g in zip(s, gone, strict=True)]
        return pd.Series([None if v is None else str(v) for v in values], dtype=object)

    out = joined.where(count(F.col(prov), F.col("_gone")) > 0)
    return out.withColumns({c: value(F.col(t), F.col("_gone")) for c, t in columns.items()}).drop("_gone")


def _tokens_in(text: Column, parser) -> Column:
    @F.pandas_udf("array<string>")
    def run(s: pd.Series) -> pd.Series:
        return pd.Series([[] if x is None else sorted(ev.tokens(parser(x))) for x in s], dtype=object)

    return run(text)


def truncated(prov: Column, n: int) -> Column:
    """Bounded display: the first n alternatives of a sum, and how many there are."""
    parts = F.split(prov, " \\+ ")
    return F.when(F.size(parts) > n, F.concat(F.array_join(F.slice(parts, 1, n), " + "), F.lit(" + … ("), F.size(parts).cast("string"), F.lit(")"))).otherwise(prov)


def approx_tokens(df: DataFrame, prov: str = "prov") -> DataFrame:
    """Approximate number of distinct tokens over a result."""
    return df.select(F.explode(F.regexp_extract_all(F.col(prov), F.lit(r"([A-Za-z0-9_#.]+:[^\s()\[\]⊗,]+)"), 1)).alias("t")).agg(F.approx_count_distinct("t").alias("approx_tokens"))
