"""Cost measures of the experiments."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polyprov.errors import ProvenanceTooLarge, UnsupportedForBaseline, UnsupportedForProvenance

FAILURES = ("out of memory", "text limit", "time-out", "rewriting error", "unsupported", "empty result", "error")


@dataclass(frozen=True)
class Timing:
    seconds: float | None
    failure: str | None = None
    runs: tuple[float, ...] = ()


def failure_class(error: BaseException) -> str:
    text = f"{type(error).__name__} {error}"
    if isinstance(error, ProvenanceTooLarge):
        return "text limit"
    if isinstance(error, UnsupportedForBaseline | UnsupportedForProvenance):
        return "unsupported"
    if "OutOfMemory" in text or "MemoryError" in text or "Requested array size exceeds" in text:
        return "out of memory"
    if "cancelled" in text or "Timeout" in text:
        return "time-out"
    if "AnalysisException" in text or "ParseException" in text:
        return "rewriting error"
    return "error"


def time_query(make: Callable[[], DataFrame], runs: int = 3, timeout: float = 600.0) -> Timing:
    """Mean seconds of ``runs`` fresh runs into a no-op sink, caches cleared before each.

    ``make`` parses or rewrites; as in the experiments this is timed apart (see
    ``time_rewrite``).  A run past ``timeout`` is cancelled.
    """
    import threading

    took = []
    for _ in range(runs):
        try:
            df = make()
            spark = df.sparkSession
            spark.catalog.clearCache()
            began = time.perf_counter()
            group = f"timed-{began}"
            spark.sparkContext.setJobGroup(group, "timed query", interruptOnCancel=True)
            alarm = threading.Timer(max(0.1, timeout - (time.perf_counter() - began)), lambda g=group, sc=spark.sparkContext: sc.cancelJobGroup(g))
            alarm.start()
            try:
                df.write.format("noop").mode("overwrite").save()
            finally:
                alarm.cancel()
                spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
            took.append(time.perf_counter() - began)
        except Exception as e:
            return Timing(None, failure_class(e), tuple(took))
    return Timing(sum(took) / len(took), None, tuple(took))


def time_rewrite(make: Callable[[], DataFrame], runs: int = 3) -> float:
    """Mean seconds until the annotated plan stands (nothing is run)."""
    began = time.perf_counter()
    for _ in range(runs):
        make()
    return (time.perf_counter() - began) / runs


def overhead(annotated: float, plain: float) -> float:
    """Percent above the plain figure."""
    return 100.0 * (annotated - plain) / plain


def characters(df: DataFrame) -> DataFrame:
    """One row: characters of all values of a result, printed."""
    return df.agg(F.coalesce(F.sum(sum((F.coalesce(F.length(F.col(f"`{c}`").cast("string")), F.lit(0)) for c in df.columns), F.lit(0))), F.lit(0)).alias("characters"))


def size_of(df: DataFrame) -> int:
    return characters(df).first()["characters"]


def total(measured: DataFrame, columns: list[str]) -> int:
    """Characters of the texts in these columns of a result that was rewritten for their lengths."""
    return measured.agg(F.coalesce(F.sum(sum((F.coalesce(F.col(f"`{c}`"), F.lit(0)) for c in columns), F.lit(0))), F.lit(0)).alias("n")).first()["n"]


def prov_size_kb(annotated: DataFrame, plain: DataFrame) -> float:
    """Characters that the annotations add, in KB."""
    return (size_of(annotated) - size_of(plain)) / 1024.0


def size_overhead(annotated: DataFrame, plain: DataFrame) -> float:
    base = size_of(plain)
    return overhead(size_of(annotated), base) if base else 0.0


def coverage(results: dict[str, dict[str, Timing]]) -> dict[str, int]:
    """Per system: queries that ran (results: system -> query -> timing)."""
    return {s: sum(t.failure is None for t in q.values()) for s, q in results.items()}


def wins(results: dict[str, dict[str, float | None]]) -> dict[str, int]:
    """Per system: queries on which its figure is the smallest."""
    out = dict.fromkeys(results, 0)
    for q in {q for r in results.values() for q in r}:
        there = {s: r[q] for s, r in results.items() if r.get(q) is not None}
        if there:
            out[min(there, key=lambda s: there[s])] += 1
    return out


def group_average(values: dict[str, float | None], group: Iterable[str]) -> float | None:
    """Average over a group of queries, only where all of it ran."""
    found = [values.get(q) for q in group]
    return None if not found or any(v is None for v in found) else sum(found) / len(found)


def plan_figures(df: DataFrame) -> dict[str, int]:
    """Exchanges, joins and Python nodes of the physical plan."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {k: text.count(k) for k in ("Exchange", "BroadcastHashJoin", "SortMergeJoin", "CartesianProduct", "BroadcastNestedLoopJoin", "ArrowEvalPython", "BatchEvalPython")}


SYSTEMS = ("method", "full witness", "token witness", "function circuit")

#: What is reported for each system.
SUPPORT = {
    "select-project-join": SYSTEMS,
    "grouping and aggregates": SYSTEMS,
    "ORDER BY on an aggregate": ("method", "full witness", "token witness"),
    "HAVING with a subquery": ("method", "full witness"),
    "subquery in WHERE": ("method", "full witness"),
    "grouping by an aggregate": ("method", "full witness"),
    "polynomials": ("method", "function circuit"),
    "formal sums of aggregates": ("method", "function circuit"),
}

#: A query that needs each feature, and what its result must hold.
PROBES = {
    "select-project-join": ("SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'ASIA'", None),
    "grouping and aggregates": ("SELECT n_regionkey, COUNT(*) AS n FROM nation GROUP BY n_regionkey", None),
    "ORDER BY on an aggregate": ("SELECT n_regionkey, SUM(n_nationkey) AS v FROM nation GROUP BY n_regionkey ORDER BY v DESC", None),
    "HAVING with a subquery": ("SELECT n_regionkey, SUM(n_nationkey) AS v FROM nation GROUP BY n_regionkey HAVING SUM(n_nationkey) > (SELECT AVG(r_regionkey) FROM region)", None),
    "subquery in WHERE": ("SELECT r_name FROM region WHERE EXISTS (SELECT * FROM nation WHERE n_regionkey = r_regionkey)", None),
    "grouping by an aggregate": ("SELECT c, COUNT(*) AS n FROM (SELECT n_regionkey, COUNT(*) AS c FROM nation GROUP BY n_regionkey) AS g GROUP BY c", None),
    "polynomials": ("SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'ASIA'", "·"),
    "formal sums of aggregates": ("SELECT n_regionkey, SUM(n_nationkey) AS v FROM nation GROUP BY n_regionkey", "⊗"),
}


def run_system(engine, system: str, query: str, **options) -> DataFrame:
    """A query under one of ``SYSTEMS``, or plain."""
    from polyprov import baselines

    if system == "plain":
        return engine.plain(query)
    if system == "method":
        return engine.rewrite(query, **options)
    return {"full witness": baselines.full_witness, "token witness": baselines.token_witness, "function circuit": baselines.function_circuit}[system](engine, query)


def supports(engine, system: str, feature: str) -> bool:
    query, sign = PROBES[feature]
    try:
        rows = run_system(engine, system, query).collect()
    except (UnsupportedForBaseline, UnsupportedForProvenance):
        return False
    return bool(rows) and (sign is None or any(sign in v for r in rows for v in r if isinstance(v, str)))


def support_matrix(engine) -> DataFrame:
    """feature, system, supported: each system tried on a query that needs the feature."""
    return engine.spark.createDataFrame([(k, s, supports(engine, s, k)) for k in PROBES for s in SYSTEMS], "feature string, system string, supported boolean")
