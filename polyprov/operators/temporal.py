"""As-of and interval joins on annotated frames, without cross products."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import Column, Window
from pyspark.sql import functions as F

from polyprov.errors import UnsupportedForProvenance
from polyprov.operators.frame import AnnotatedFrame, fresh


def asof_join(left: AnnotatedFrame, right: AnnotatedFrame, keys: list[str], time: str, right_time: str, columns: list[str]) -> AnnotatedFrame:
    """Each left row with the latest right row of its keys at or before its time.

    Both sides are laid out in one order per key, and the last right row seen is
    carried along: one shuffle, no pairs.  The annotation is the product with the
    single row chosen; left rows without one go.  Right rows of equal time: any
    one of them (the greatest by its columns).
    """
    if left.aggs or right.aggs:
        raise UnsupportedForProvenance("as-of join of aggregated columns")
    left, right = left.one_factor(), right.one_factor()
    lp, ls = left.factors[0]
    rp, rs = right.factors[0]
    hit, when, side = fresh("hit"), fresh("time"), fresh("side")
    carried = F.struct(*[F.col(c) for c in columns], F.col(rp))
    r = right.df.select(*keys, F.col(right_time).alias(when), F.lit(0).alias(side), carried.alias(hit))
    own = fresh("row")
    l = left.df.select(*keys, F.col(time).alias(when), F.lit(1).alias(side), F.struct(*[F.col(f"`{c}`") for c in left.df.columns]).alias(own))
    both = l.unionByName(r, allowMissingColumns=True)
    w = Window.partitionBy(*keys).orderBy(when, side, F.col(hit)).rowsBetween(Window.unboundedPreceding, 0)
    chosen = both.withColumn(hit, F.last(hit, ignorenulls=True).over(w)).where((F.col(side) == 1) & F.col(hit).isNotNull())
    df = chosen.select(f"{own}.*", f"{hit}.*")
    return replace(left, df=df, factors=((lp, ls), (rp, rs)), caveats=left.caveats + right.caveats)


def interval_join(left: AnnotatedFrame, right: AnnotatedFrame, time: str, right_time: str, seconds: int, on: Column | None = None) -> AnnotatedFrame:
    """Pairs with right_time in [time, time + seconds]: an equi-join on time bins.

    A left row looks into the two bins that its interval can touch, so no row meets
    more than the rows of those bins.
    """
    bin_name, left_bin = fresh("bin"), fresh("bin")
    bin_of = lambda c: F.floor(F.unix_timestamp(F.col(c).cast("timestamp")) / F.lit(seconds))
    l = left.df.withColumn(left_bin, F.explode(F.array(bin_of(time), bin_of(time) + 1)))
    r = right.df.withColumn(bin_name, bin_of(right_time))
    start, end = F.col(time).cast("timestamp"), F.col(time).cast("timestamp") + F.make_interval(secs=F.lit(seconds))
    condition = (F.col(left_bin) == F.col(bin_name)) & F.col(right_time).cast("timestamp").between(start, end)
    df = l.join(r, condition if on is None else condition & on).drop(left_bin, bin_name)
    return replace(left, df=df, factors=left.factors + right.factors, aggs=left.aggs | right.aggs, caveats=left.caveats + right.caveats)
