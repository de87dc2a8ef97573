"""Mixing sources to target weights (9), with Sainte-Lague quotas. JVM only.

Targets: sources in code-point order (null last) weigh 5, 2, 1, repeating; they
share 150 % of all words, no target above twice its source's words (the excess
is shared anew by weight).  Words are dealt in blocks of equal size: sources get
whole numbers of blocks by highest quotients t / (2k + 1), and each source's
blocks are dealt to its shards in the same way.  Within a shard, rows lie end to
end in a seeded order; a quota above the shard's blocks takes the whole shard
once and the rest in a second pass, and a seeded permutation of the block
numbers tells which blocks a pass takes.  A row's ``taken`` is the number of its
words in chosen blocks, so it is never above twice its size, and a rerun with
the same seed gives the same rows.

A highest-quotient allotment equals rounding every t / d to the nearest whole
number for a common divisor d, so the hand-out needs no loop: one divisor gives
all but a few blocks, and a ranking of the next quotients gives those.

Null and empty texts have size 0 and taken 0; repeated rows count each; ties in
the seeded order fall to doc_id and then to the size; a source of empty texts
has target 0; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from polyprov.llm.common import cut, word_count

WEIGHTS = (5, 2, 1)
SHARE = 1.5
MOST = 2
SEED = 20240901

#: Rows that a shard of a source is made for.
SHARD_ROWS = 5_000
#: Words of a block at most; smaller inputs have smaller blocks.
BLOCK_WORDS = 512

#: Sources that are broadcast at most (some 100 bytes each), and salts beyond that.
BROADCAST_SOURCES = 10_000
SALTS = 32

#: Multipliers of the seeded permutation: primes above any block number used.
_PRIMES = (2147483647, 2147483629, 2147483587, 2147483579)


def source_targets(sizes: DataFrame, weights=WEIGHTS, share: float = SHARE, most: int = MOST) -> DataFrame:
    """src_null, src, source_size, n_rows, weight, target: one row per source.

    Filling to caps: sources are taken by cap / weight; those whose cap lies
    below the common level get their cap, the others share the rest by weight.
    """
    per = sizes.groupBy("src_null", "src").agg(F.sum("size").alias("source_size"), F.count("*").alias("n_rows"))
    # A few partial tasks' sums meet here: one row per source.
    order = Window.orderBy("src_null", "src")
    by_level = Window.orderBy("level", "src_null", "src")
    pattern = F.array(*[F.lit(float(w)) for w in weights])
    ranked = (
        per.withColumn("weight", F.element_at(pattern, (F.pmod(F.row_number().over(order) - 1, F.lit(len(weights))) + 1).cast("int")))
        .withColumn("cap", F.col("source_size").cast("double") * most)
        .withColumn("level", F.col("cap") / F.col("weight"))
        .withColumn("wanted", F.sum("source_size").over(Window.partitionBy()) * F.lit(float(share)))
        .withColumn("cap_below", F.coalesce(F.sum("cap").over(by_level.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0)))
        .withColumn("weight_from", F.sum("weight").over(by_level.rowsBetween(0, Window.unboundedFollowing)))
        .withColumn("common", (F.col("wanted") - F.col("cap_below")) / F.col("weight_from"))
    )
    # The first source (by level) that stays below its cap fixes the level for all after it.
    open_level = F.min(F.when(F.col("level") > F.col("common"), F.struct("level", "common"))).over(Window.partitionBy())["common"]
    return ranked.withColumn("open", open_level).select(
        "src_null", "src", "source_size", "n_rows", "weight",
        F.when(F.col("open").isNull() | (F.col("level") <= F.col("open")), F.col("cap")).otherwise(F.col("weight") * F.col("open")).alias("target"),
    )


def highest_quotients(claims: DataFrame, claim: Column, blocks: Column, group: list[str], ties: list[str], cap: Column, name: str) -> DataFrame:
    """Adds integer ``name``: ``blocks`` (one value per group) dealt by Sainte-Lague.

    ``cap`` bounds what a claimant can hold; blocks beyond go to the next ones.
    """
    all_of = Window.partitionBy(*group)
    total = F.sum(claim).over(all_of)
    base = (
        claims.withColumn("_b", blocks.cast("long"))
        .withColumn("_q", F.when(total > 0, claim * F.col("_b") / total).otherwise(0.0))
        .withColumn("_cap", cap.cast("long"))
        .withColumn("_n", F.least(F.floor(F.col("_q") + 0.5).cast("long"), F.col("_cap")))
        .withColumn("_over", F.sum("_n").over(all_of) - F.col("_b"))
    )
    # Too many: the blocks with the smallest quotients go back; too few: the next highest are dealt.
    # Rounding errs by less than one block a claimant, so one change each settles it
    # unless caps bind; `_room` then lets a claimant take several.
    losing = F.when(F.col("_n") > 0, claim / (2 * F.col("_n") - 1))
    gaining = F.when(F.col("_n") < F.col("_cap"), claim / (2 * F.col("_n") + 1))
    back = F.row_number().over(all_of.orderBy(losing.asc_nulls_last(), *ties))
    room = F.col("_cap") - F.col("_n")
    before = F.sum(F.least(room, F.lit(1))).over(all_of.orderBy(gaining.desc_nulls_last(), *ties).rowsBetween(Window.unboundedPreceding, -1))
    slack = F.sum(F.greatest(room - 1, F.lit(0))).over(all_of.orderBy(gaining.desc_nulls_last(), *ties).rowsBetween(Window.unboundedPreceding, -1))
    ones = F.sum(F.least(room, F.lit(1))).over(all_of)
    return (
        base.withColumn("_back", back)
        .withColumn("_before", F.coalesce(before, F.lit(0)))
        .withColumn("_slack", F.coalesce(slack, F.lit(0)))
        .withColumn("_ones", ones)
        .withColumn(
            name,
            F.when(F.col("_over") > 0, F.col("_n") - F.when((F.col("_back") <= F.col("_over")) & (F.col("_n") > 0), 1).otherwise(0))
            .when(
                F.col("_over") < 0,
                F.col("_n")
                + F.when((room > 0) & (F.col("_before") < -F.col("_over")), 1).otherwise(0)
                + F.greatest(F.lit(0), F.least(room - 1, -F.col("_over") - F.col("_ones") - F.col("_slack"))),
            )
            .otherwise(F.col("_n"))
            .cast("long"),
        )
        .drop("_b", "_q", "_cap", "_n", "_over", "_back", "_before", "_slack", "_ones")
    )


def _with_source(rows: DataFrame, sources: DataFrame, key: list[str]) -> DataFrame:
    """Each row with its source's figures, whatever share of the rows a source has:
    few sources are broadcast (their number is checked), many are joined salted."""
    if sources.count() <= BROADCAST_SOURCES:
        return rows.join(F.broadcast(sources), key)
    spread = sources.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return rows.withColumn("_salt", F.pmod("draw", F.lit(SALTS)).cast("int")).join(spread, [*key, "_salt"]).drop("_salt")


def source_mix(docs: DataFrame, seed: int = SEED, weights=WEIGHTS, share: float = SHARE, most: int = MOST, block_words: int = BLOCK_WORDS, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """doc_id, size, source_size, target, taken, copies of each row.

    ``copies`` rounds taken / size to whole copies by a seeded draw per row, for
    users that repeat whole documents.
    """
    sizes = cut(
        docs.select(
            "doc_id",
            F.col("source").isNull().cast("int").alias("src_null"),
            F.coalesce("source", F.lit("")).alias("src"),
            word_count(F.col("text")).alias("size"),
            F.xxhash64(F.lit(seed), F.col("doc_id"), F.col("text")).alias("draw"),
        )
    )
    targets = source_targets(sizes, weights, share, most)
    one = Window.partitionBy()
    sources = cut(
        highest_quotients(
            targets.withColumn("n_shards", F.ceil(F.col("n_rows") / F.lit(shard_rows)).cast("int"))
            .withColumn("block", F.greatest(F.lit(1), F.least(F.lit(block_words), F.floor(F.sum("target").over(one) / (F.count("*").over(one) * 2000)))).cast("long")),
            F.col("target"),
            F.round(F.sum("target").over(one) / F.col("block")),
            [],
            ["src_null", "src"],
            F.floor(F.col("source_size") * most / F.col("block")) + F.col("n_shards") * most,
            "blocks",
        )
    )
    key = ["src_null", "src"]
    rows = _with_source(sizes, sources.drop("n_rows", "weight"), key).withColumn("shard", F.pmod(F.xxhash64(F.lit(seed + 1), "draw", "doc_id"), F.col("n_shards")).cast("int"))
    # Shards of a source: their words, and their blocks by highest quotients.
    shards = rows.groupBy(*key, "shard").agg(F.sum("size").alias("shard_size"), F.first("blocks").alias("blocks"), F.first("block").alias("block"))
    n_blocks = F.ceil(F.col("shard_size") / F.col("block"))
    quotas = (
        highest_quotients(shards, F.col("shard_size").cast("double"), F.col("blocks"), key, ["shard"], n_blocks * most, "quota")
        .withColumn("n_blocks", F.greatest(n_blocks.cast("long"), F.lit(1)))
        .withColumn("full", F.floor(F.col("quota") / F.col("n_blocks")))
        .withColumn("part", F.col("quota") - F.col("full") * F.col("n_blocks"))
        .withColumn("step", F.element_at(F.array(*map(F.lit, _PRIMES)), (F.pmod(F.xxhash64(F.lit(seed + 2), *key, "shard"), F.lit(len(_PRIMES))) + 1).cast("int")))
        .withColumn("shift", F.pmod(F.xxhash64(F.lit(seed + 3), *key, "shard"), F.col("n_blocks")))
        .select(*key, "shard", "n_blocks", "full", "part", "step", "shift")
    )
    line = Window.partitionBy(*key, "shard").orderBy("draw", "doc_id", "size")
    placed = rows.withColumn("stop", F.sum("size").over(line)).withColumn("start", F.col("stop") - F.col("size"))
    block = F.col("block")
    first, last = F.floor(F.col("start") / block), F.floor((F.col("stop") - 1) / block)
    chosen = lambda b: F.pmod(b * F.col("step") + F.col("shift"), F.col("n_blocks")) < F.col("part")
    overlap = lambda b: F.least(F.col("stop"), (b + 1) * block) - F.greatest(F.col("start"), b * block)
    inside = F.aggregate(F.sequence(first, last), F.lit(0).cast("long"), lambda acc, b: acc + F.when(chosen(b), overlap(b)).otherwise(F.lit(0).cast("long")))
    taken = F.when(F.col("size") == 0, 0).otherwise(F.col("full") * F.col("size") + F.when(F.col("part") == 0, 0).otherwise(inside)).cast("long")
    lot = F.pmod(F.xxhash64(F.lit(seed + 4), "draw", "doc_id"), F.lit(1 << 20)) / float(1 << 20)
    return (
        placed.join(quotas, [*key, "shard"])
        .withColumn("taken", taken)
        .select("doc_id", "size", "source_size", "target", "taken", F.when(F.col("size") == 0, 0).otherwise(F.floor(F.col("taken") / F.col("size") + lot)).cast("int").alias("copies"), "draw")
    )


def mixed_documents(docs: DataFrame, seed: int = SEED, **options) -> DataFrame:
    """The rows, with all their columns, as often as the mix has ``copies`` of them.

    Rows equal in doc_id and text share their copies evenly, rounded up.
    """
    # Names that no column of ``docs`` has.
    draw, n, same_id, same_draw = (f"_{x}_{uuid.uuid4().hex[:8]}" for x in ("draw", "copies", "id", "of"))
    plan = source_mix(docs, seed, **options).groupBy(F.col("doc_id").alias(same_id), F.col("draw").alias(same_draw)).agg(F.ceil(F.sum("copies") / F.count("*")).cast("int").alias(n)).where(F.col(n) > 0)
    rows = docs.withColumn(draw, F.xxhash64(F.lit(seed), "doc_id", "text"))
    return rows.join(plan, (F.col(draw) == F.col(same_draw)) & F.col("doc_id").eqNullSafe(F.col(same_id))).withColumn(n, F.explode(F.sequence(F.lit(1), F.col(n)))).select(docs.columns)
