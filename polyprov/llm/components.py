"""Connected components of an edge table, without gathering it anywhere.

Alternating star steps: each node is tied to the smallest node among its
neighbours, first by its larger neighbours, then by itself and its smaller
ones, until nothing changes.  Minima are combined before they are shuffled, so
a node with any number of links is no bottleneck; the joins are plain equi-joins
that Spark can split where one key dominates.  Each round is cut off by a
checkpoint in the shared folder.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polyprov.llm.common import cut


def _state(edges: DataFrame) -> tuple[int, int]:
    r = edges.agg(F.count("*").alias("n"), F.sum(F.pmod(F.xxhash64("a", "b"), F.lit(1 << 40))).alias("h")).first()
    return r["n"], r["h"] or 0


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(a, b) links -> (node, component), component = smallest node reachable.

    Only nodes that occur in a link to another node are returned; null ends and
    links of a node to itself are ignored.  No links give no rows.
    """
    e = cut(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    state = _state(e)
    for _ in range(max_rounds):
        if state[0] == 0:
            break
        both = e.union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"))
        large = both.where("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").union(low.select("a", F.col("m").alias("b"))).distinct()
        e = cut(small)
        before, state = state, _state(e)
        if state == before:
            return e.select(F.col("a").alias("node"), F.col("b").alias("component"))
    if state[0]:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return e.select(F.col("a").alias("node"), F.col("b").alias("component"))
