"""URL filters (3): a tree of path templates per host. JVM only.

Listed rules decide the urls they fit.  For the rest, the urls that a rule
decided serve as labels (block = bad) of the tree their host has.  Level by level,
as deep as the longest path:

* a path segment below (host, template so far) turns into ``*`` if it is digits
  (an extension may follow), or if its place holds many values for its rows (more
  than ``kids_kept``, and their square above the number of rows);
* sibling branches of ``least_rows`` rows or more are similar if the distributions
  of what lies below them (the next segment and the depth that remains, in ``BINS``
  hashed bins) differ no more than chance and ``slack`` allow.  Similar branches with
  ``least_labels`` labels pool if their labelled rates do not differ by ``z_limit``
  standard errors; similar ones with fewer labels join them where they all pool, as
  ``{name}`` of the first, else they keep to themselves;
* a template is rejected if its smoothed purity reaches ``reject_at``: (bad + s * prior)
  / (labelled + s), s being ``strength`` and ``dilution`` for each row without label, so
  that a few labels do not decide for many rows.

Places with no more rows than ``kids_kept`` can hold neither many values nor similar
branches; once all are so small, the rest of the paths is written out in one step.

A null url, or one without ``://``, has an empty host and path, no rule and the
verdict of the empty host's (empty) template.  An empty path is the template of
its host's root.  Repeated rows count each and get equal verdicts; an empty table
gives no rows; other columns are ignored.  A host may hold any share of the rows:
all counts are combined before they are shuffled, and the joins that carry counts
back are salted.
"""

from __future__ import annotations

import string
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from polyprov.llm.common import cut

#: (rule, verdict): host up to the first slash, then the start of the path.
RULES = (("com/en/", "block"), ("example.com/en/7", "allow"), ("net/de/", "allow"), ("example.net/de/8", "block"), ("org/es/", "block"))
SALTS = 16
BINS = 64
NUMBER = r"^[0-9]+(\.[A-Za-z0-9]+)?$"


def host_and_path(url: Column) -> tuple[Column, Column]:
    at = F.instr(url, "://")
    rest = F.when(at > 0, F.substr(url, at + 3)).otherwise(F.lit(""))
    host = F.translate(F.regexp_extract(rest, "^([^/?#]*)", 1), string.ascii_uppercase, string.ascii_lowercase)
    return F.coalesce(host, F.lit("")), F.coalesce(F.regexp_extract(rest, "^[^/?#]*([^?#]*)", 1), F.lit(""))


def rule_of(host: Column, path: Column, rules: Sequence[tuple[str, str]]) -> Column:
    """struct(rule, verdict) of the longest rule that fits, else null."""
    found = F.lit(None).cast("struct<rule:string,verdict:string>")
    # Shortest first: each longer rule is asked before those already in `found`.
    for rule, verdict in sorted(rules, key=lambda r: (len(r[0]), r[1] == "block", r[0])):
        domain, slash, start = rule.partition("/")
        fits = ((host == domain) | host.endswith("." + domain)) & path.startswith(slash + start)
        found = F.when(fits, F.struct(F.lit(rule).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(found)
    return found


def _salted(rows: DataFrame, small: DataFrame, on: list[str], by: list[str], how: str = "left") -> DataFrame:
    """Join on keys of which one may hold a third of ``rows``."""
    spread = small.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    return rows.withColumn("_salt", F.pmod(F.xxhash64(*by), F.lit(SALTS)).cast("int")).join(spread, [*on, "_salt"], how).drop("_salt")


def _shown(segment: Column) -> Column:
    return F.when(segment.rlike(NUMBER), F.lit("*")).otherwise(segment)


def _classes(rows: DataFrame, level: int, variable: DataFrame, least_rows: int, slack: float, least_labels: int, z_limit: float) -> DataFrame:
    """(host, template, segment, class_name) of the branches that merge with others."""
    place = ["host", "template"]
    below = F.get("segments", F.lit(level))
    # The extension of a number stays: what differs in kind only is told apart.
    kind = F.coalesce(F.regexp_replace(below, r"^[0-9]+", "*"), F.lit("/"))
    hashed = F.pmod(F.xxhash64(kind, F.size("segments") - level), F.lit(BINS)).cast("int")
    counted = rows.where(~F.col("segment").rlike(NUMBER)).groupBy(*place, "segment", hashed.alias("bin")).agg(F.count("*").alias("c"), F.sum("labelled").alias("labelled"), F.sum("bad").alias("bad"))
    of_place = Window.partitionBy(*place).orderBy("main", "share", "segment")
    branches = (
        _salted(counted, variable, place, ["segment"], "left_anti")
        .groupBy(*place, "segment")
        .agg(
            F.sum("c").alias("n"), F.sum("labelled").alias("labelled"), F.sum("bad").alias("bad"),
            F.map_from_entries(F.collect_list(F.struct("bin", "c"))).alias("h"), F.max(F.struct("c", "bin")).alias("top"),
        )
        .where(F.col("n") >= least_rows)
        .withColumn("main", F.col("top.bin"))
        .withColumn("share", F.col("top.c") / F.col("n"))
        .withColumn("h0", F.lag("h").over(of_place))
        .withColumn("n0", F.lag("n").over(of_place))
    )
    share = lambda h, n, b: F.coalesce(F.try_element_at(F.col(h), b), F.lit(0)) / F.col(n)
    apart = F.aggregate(F.sequence(F.lit(0), F.lit(BINS - 1)), F.lit(0.0), lambda x, b: x + F.abs(share("h", "n", b) - share("h0", "n0", b))) / 2
    used = F.size(F.array_union(F.map_keys("h"), F.map_keys("h0")))
    chance = F.sqrt(used * (1 / F.col("n") + 1 / F.col("n0"))) / 2
    similar = branches.withColumn("kind", F.sum(F.coalesce(apart > chance + F.lit(slack), F.lit(True)).cast("int")).over(of_place)).drop("h", "h0", "n0", "top")
    known = similar.withColumn("known", F.col("labelled") >= least_labels).withColumn("rate", F.when(F.col("known"), F.col("bad") / F.col("labelled")))
    rated = Window.partitionBy(*place, "kind", "known").orderBy("rate", "segment")
    bad0, labelled0 = F.lag("bad").over(rated), F.lag("labelled").over(rated)
    # Of branches without labels all this is null: each starts a pool, which is not used.
    pooled = F.try_divide(F.col("bad") + F.col("bad0"), F.col("labelled") + F.col("labelled0"))
    error = F.sqrt(pooled * (1 - pooled) * (F.try_divide(F.lit(1), "labelled") + F.try_divide(F.lit(1), "labelled0")))
    differs = F.coalesce(F.col("rate") - F.try_divide("bad0", "labelled0") > z_limit * error, F.lit(True))
    of_kind = Window.partitionBy(*place, "kind")
    pools = (
        known.withColumn("bad0", bad0)
        .withColumn("labelled0", labelled0)
        .withColumn("pool", F.when(F.col("known"), F.sum(differs.cast("int")).over(rated)).otherwise(0))
        .withColumn("n_pools", F.max("pool").over(of_kind))
        .withColumn("pool", F.when(~F.col("known") & (F.col("n_pools") == 1), 1).otherwise(F.col("pool")))
    )
    of_pool = Window.partitionBy(*place, "kind", "pool")
    named = pools.withColumn("members", F.count("*").over(of_pool)).withColumn("first", F.min("segment").over(of_pool))
    return named.where("members > 1").select(*place, "segment", F.concat(F.lit("{"), "first", F.lit("}")).alias("class_name"))


def url_filter(
    pages: DataFrame,
    rules: Sequence[tuple[str, str]] = RULES,
    kids_kept: int = 8,
    least_rows: int = 10,
    slack: float = 0.1,
    least_labels: int = 5,
    z_limit: float = 1.96,
    prior: float = 0.1,
    strength: float = 4.0,
    dilution: float = 0.25,
    reject_at: float = 0.8,
) -> DataFrame:
    """page_id, host, path, rule, verdict, template, purity of each row."""
    if least_rows <= kids_kept:
        raise ValueError("least_rows must exceed kids_kept: small places are written out at once")
    host, path = host_and_path(F.col("url"))
    base = pages.select("page_id", host.alias("host"), path.alias("path"))
    active = cut(
        base.withColumn("hit", rule_of(F.col("host"), F.col("path"), rules))
        .withColumn("labelled", F.col("hit").isNotNull().cast("int"))
        .withColumn("bad", F.coalesce((F.col("hit.verdict") == "block").cast("int"), F.lit(0)))
        .withColumn("segments", F.filter(F.split("path", "/"), lambda s: s != ""))
        .withColumn("template", F.lit(""))
    )
    place, level, done = ["host", "template"], 0, []
    while True:
        done.append(active.where(F.size("segments") <= level))
        active = active.where(F.size("segments") > level).withColumn("segment", F.get("segments", F.lit(level)))
        places = cut(active.groupBy(*place, "segment").agg(F.count("*").alias("n")).groupBy(*place).agg(F.count("*").alias("kids"), F.sum("n").alias("n")))
        most = places.agg(F.max("n")).first()[0]
        if most is None:
            break
        if most <= kids_kept:
            rest = F.array_join(F.transform(F.slice("segments", level + 1, F.size("segments")), _shown), "/")
            done.append(active.withColumn("template", F.concat("template", F.lit("/"), rest)).drop("segment"))
            break
        level += 1
        variable = places.where((F.col("kids") > kids_kept) & (F.col("kids") * F.col("kids") > F.col("n"))).select(*place)
        classes = _classes(active, level, variable, least_rows, slack, least_labels, z_limit)
        marked = _salted(active, variable.withColumn("variable", F.lit(True)), place, ["page_id", "path"])
        marked = _salted(marked, classes, [*place, "segment"], ["page_id", "path"])
        shown = F.when(F.col("variable"), F.lit("*")).otherwise(F.coalesce("class_name", _shown(F.col("segment"))))
        active = cut(marked.withColumn("template", F.concat("template", F.lit("/"), shown)).drop("variable", "class_name", "segment"))
    rows = done[0]
    for d in done[1:]:
        rows = rows.unionByName(d)
    weight = F.lit(strength) + F.lit(dilution) * (F.col("n") - F.col("labelled"))
    judged = rows.groupBy(*place).agg(F.count("*").alias("n"), F.sum("labelled").alias("labelled"), F.sum("bad").alias("bad")).select(*place, ((F.col("bad") + weight * prior) / (F.col("labelled") + weight)).alias("purity"))
    return (
        _salted(rows, judged, place, ["page_id", "path"])
        .withColumn("verdict", F.coalesce(F.col("hit.verdict"), F.when(F.col("purity") >= reject_at, F.lit("block")).otherwise(F.lit("allow"))))
        .select("page_id", "host", "path", F.col("hit.rule").alias("rule"), "verdict", "template", "purity")
    )
