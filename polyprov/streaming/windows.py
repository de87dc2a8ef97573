"""Annotated windows over streams.

Base annotation, selection, projection and bag union are stateless and work on a
stream as they are.  Windows keep their tokens in state until the watermark
passes: long windows over wide streams should carry gate ids instead (`edges`).
Late rows are dropped by the watermark and never enter an annotation;
``write_with_late`` keeps them, with their tokens, beside the others.
``running`` is a stateful operator whose annotations are chains of gates: its state
is a count and a sum per key, however many rows have been seen.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState

from polyprov.functions.algebra import ordered_listagg
from polyprov.functions.circuit import gate, token_gate
from polyprov.sources.tokens import TokenPolicy


def annotated(stream: DataFrame, policy: TokenPolicy) -> DataFrame:
    return stream.withColumn("prov", policy.column(stream.columns))


def windowed(stream: DataFrame, time: str, size: str, keys: list[str], value: str, watermark: str = "1 hour", slide: str | None = None, session: bool = False, scale: int = 4) -> DataFrame:
    """window_start, window_end, keys, n, total, total_agg, prov per window.

    ``stream`` is annotated; ``time`` is a timestamp with zone (cast beforehand).
    Tumbling windows, sliding ones with ``slide``, or sessions with gap ``size``.
    """
    w = F.session_window(F.col(time), size) if session else F.window(F.col(time), size, slide) if slide else F.window(F.col(time), size)
    terms = stream.withColumn("_term", F.concat("prov", F.lit("⊗"), F.col(value).cast(f"decimal(18,{scale})").cast("string")))
    grouped = terms.withWatermark(time, watermark).groupBy(w.alias("w"), *keys)
    out = grouped.agg(F.count("*").alias("n"), F.sum(value).alias("total"), ordered_listagg("_term", " +sum ").alias("total_agg"), ordered_listagg("prov", " + ").alias("prov"))
    return out.select(F.col("w.start").alias("window_start"), F.col("w.end").alias("window_end"), *keys, "n", "total", "total_agg", F.concat(F.lit("δ("), "prov", F.lit(")")).alias("prov"))


def edges(stream: DataFrame, time: str, size: str, keys: list[str], value: str, policy: TokenPolicy) -> DataFrame:
    """Stateless edges of a windowed sum: parent gate (window and keys), token gate, value."""
    w = F.window(F.col(time), size)
    keyed = stream.withColumn("_w", w)
    parent = gate(F.lit("window"), F.to_json(F.struct(F.col("_w.start"), *keys)))
    return keyed.select(parent.alias("parent"), token_gate(policy.column(stream.columns)).alias("child"), F.lit(0).alias("ord"), F.col(value).cast("string").alias("value"))


def join_static(stream: DataFrame, static: DataFrame, on: list[str]) -> DataFrame:
    """Stream-static join: annotations multiply (the static side has ``prov_static``)."""
    return stream.join(static, on).withColumn("prov", F.concat("prov", F.lit(" · "), "prov_static")).drop("prov_static")


def join_streams(left: DataFrame, right: DataFrame, time: str, right_time: str, on, gap: str, watermark: str = "1 hour") -> DataFrame:
    """Stream-stream join of rows with right_time within ``gap`` after time; both sides
    forget rows past their watermarks.  The right annotation comes as ``prov_right``."""
    l, r = left.withWatermark(time, watermark), right.withWatermark(right_time, watermark)
    condition = on & F.col(right_time).between(F.col(time), F.col(time) + F.expr(f"INTERVAL {gap}"))
    return l.join(r, condition).withColumn("prov", F.concat("prov", F.lit(" · "), "prov_right")).drop("prov_right")


def first_seen(stream: DataFrame, time: str, keys: list[str], watermark: str = "1 hour") -> DataFrame:
    """Deduplication: the first row's token stands for all (the others are lost)."""
    return stream.withWatermark(time, watermark).dropDuplicatesWithinWatermark(keys)


def write_batches(stream: DataFrame, path: str, checkpoint: str):
    """Append each micro-batch once: a batch that is run again overwrites its own folder."""

    def write(batch: DataFrame, epoch: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/epoch={epoch}")

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint)


def write_with_late(stream: DataFrame, time: str, delay: str, path: str, checkpoint: str):
    """Each micro-batch to ``path/rows``, its late rows to ``path/late``.

    A row is late if its time lies more than ``delay`` (such as ``1 hour``) before the latest time of all
    *former* batches.  That time is kept per batch in ``path/latest``: a batch that is
    run again reads the same one and overwrites its own folders.  Rows without a time are not late.
    """
    kind = stream.schema[time].dataType

    def write(batch: DataFrame, epoch: int) -> None:
        spark = batch.sparkSession
        latest = f"{path}/latest"
        schema = f"at {kind.simpleString()}"
        former = spark.read.schema(schema).parquet(f"{latest}/batch={epoch - 1}").select("at") if epoch else spark.createDataFrame([], schema)
        # One row: a global aggregate.
        bound = former.agg((F.max("at") - F.expr(f"INTERVAL {delay}")).alias("_bound"))
        marked = batch.join(F.broadcast(bound)).withColumn("_late", F.coalesce(F.col(time) < F.col("_bound"), F.lit(False))).drop("_bound").persist()
        try:
            marked.where(~F.col("_late")).drop("_late").write.mode("overwrite").parquet(f"{path}/rows/epoch={epoch}")
            marked.where("_late").drop("_late").write.mode("overwrite").parquet(f"{path}/late/epoch={epoch}")
            former.unionAll(marked.select(F.col(time).alias("at"))).agg(F.max("at").alias("at")).write.mode("overwrite").parquet(f"{latest}/batch={epoch}")
        finally:
            marked.unpersist()

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint)


def running(stream: DataFrame, keys: list[str], time: str, value: str, scale: int = 4) -> DataFrame:
    """keys, n, total, token, value: the running count and sum after each row of its key.

    ``stream`` is annotated.  The rows of a micro-batch come in order of time and token; batches in theirs.
    A null value counts as a row and adds nothing.  ``running_edges`` gives the annotations.
    """
    unit = F.lit(10**scale)
    ready = stream.select(*keys, F.col(time).alias("_time"), F.col("prov").alias("token"), (F.col(value).cast(f"decimal(18,{scale})") * unit).cast("long").alias("units"))
    head = ready.select(*keys).schema

    def advance(key: tuple, parts: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, units = state.get if state.exists else (0, 0)
        rows = pd.concat(list(parts)).sort_values(["_time", "token"], kind="stable")
        steps = [0 if pd.isna(x) else int(x) for x in rows["units"]]
        totals = []
        for step in steps:
            units += step
            totals.append(units)
        out = rows[[*keys, "token", "units"]].assign(n=range(n + 1, n + len(rows) + 1), total=totals)
        state.update((n + len(rows), units))
        yield out[[*keys, "n", "total", "token", "units"]]

    kept = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in head)
    out = ready.groupBy(*keys).applyInPandasWithState(advance, f"{kept}, n long, total long, token string, units long", "n long, units long", "append", "NoTimeout")
    exact = f"decimal(38,{scale})"
    return out.select(*keys, "n", (F.col("total").cast("decimal(28,0)") / unit).cast(exact).alias("total"), "token", (F.col("units").cast("decimal(28,0)") / unit).cast(exact).alias("value"))


def running_edges(rows: DataFrame, keys: list[str]) -> DataFrame:
    """Edges of running sums: each total's gate leads to the gate before it and to its row's token."""
    name = F.to_json(F.struct(*keys))
    own, before = gate(F.lit("running"), name, F.col("n")), gate(F.lit("running"), name, F.col("n") - 1)
    children = F.array(
        F.struct(F.when(F.col("n") > 1, before).alias("child"), F.lit(0).alias("ord"), F.lit(None).cast("string").alias("value")),
        F.struct(token_gate(F.col("token")).alias("child"), F.lit(1).alias("ord"), F.col("value").cast("string").alias("value")),
    )
    edge = F.explode(F.filter(children, lambda c: c["child"].isNotNull()))
    return rows.select(own.alias("parent"), edge.alias("edge")).select("parent", "edge.child", "edge.ord", "edge.value")
