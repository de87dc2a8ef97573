"""Streams: windows equal the batch result, edges need no state, joins multiply."""

from conftest import SF
from pyspark.sql import functions as F

from polyprov.sources.tokens import GIVEN
from polyprov.streaming import windows as w


def source(spark, types):
    schema = spark.read.parquet(f"{SF}/events.parquet").schema
    s = spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(SF)
    return s.where(F.col("event_type").isin(types)).withColumn("ts", F.col("ts").cast("timestamp"))


def batch(spark, types):
    return spark.read.parquet(f"{SF}/events.parquet").where(F.col("event_type").isin(types)).withColumn("ts", F.col("ts").cast("timestamp"))


def run(stream, name, mode="append"):
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return q


def test_windows_equal_batch(spark):
    for name, options in (("tumbling", {}), ("sliding", {"slide": "12 hours"}), ("session", {"session": True})):
        size = "6 hours" if name == "session" else "1 day"
        rows = w.windowed(w.annotated(source(spark, ["click"]), GIVEN["events"]), "ts", size, ["event_type"], "value", **options)
        run(rows, name)
        want = {tuple(r) for r in w.windowed(w.annotated(batch(spark, ["click"]), GIVEN["events"]), "ts", size, ["event_type"], "value", **options).drop("total").collect()}
        got = {tuple(r) for r in spark.table(name).drop("total").collect()}
        assert got and got <= want and len(got) >= len(want) - 4  # the last windows are still open


def test_edges_are_stateless(spark):
    e = w.edges(source(spark, ["error"]), "ts", "1 day", ["event_type"], "value", GIVEN["events"])
    run(e, "edges")
    assert spark.table("edges").count() == batch(spark, ["error"]).count()
    assert spark.table("edges").select("parent").distinct().count() == batch(spark, ["error"]).select(F.to_date("ts")).distinct().count()


def test_joins(spark):
    static = spark.createDataFrame([("error", "k:1")], "event_type string, prov_static string")
    run(w.join_static(w.annotated(source(spark, ["error", "view"]), GIVEN["events"]), static, ["event_type"]), "with_static")
    assert spark.table("with_static").count() == batch(spark, ["error"]).count()
    assert all(r.prov.endswith(" · k:1") for r in spark.table("with_static").collect())
    left = w.annotated(source(spark, ["signup"]), GIVEN["events"]).select(F.col("user_id").alias("u"), "ts", "prov")
    right = w.annotated(source(spark, ["error"]), GIVEN["events"]).select("user_id", F.col("ts").alias("at"), F.col("prov").alias("prov_right"))
    run(w.join_streams(left, right, "ts", "at", F.col("u") == F.col("user_id"), "2 days"), "both")
    want = batch(spark, ["signup"]).alias("a").join(batch(spark, ["error"]).alias("b"), F.expr("a.user_id = b.user_id AND b.ts BETWEEN a.ts AND a.ts + INTERVAL 2 days")).count()
    assert spark.table("both").count() == want


def test_first_seen(spark):
    run(w.first_seen(source(spark, ["view"]).select("user_id", "ts"), "ts", ["user_id"], "40 days"), "first")
    assert spark.table("first").count() == batch(spark, ["view"]).select("user_id").distinct().count()


def parts(spark, folder, frames):
    """A stream that reads one of the frames in each micro-batch."""
    import os

    for i, f in enumerate(frames):
        f.coalesce(1).write.parquet(f"{folder}/made/{i}")
        os.makedirs(f"{folder}/in", exist_ok=True)
        name = next(n for n in os.listdir(f"{folder}/made/{i}") if n.endswith(".parquet"))
        os.utime(f"{folder}/made/{i}/{name}", (1_000_000 + i, 1_000_000 + i))
        os.rename(f"{folder}/made/{i}/{name}", f"{folder}/in/{i}.parquet")
    return spark.readStream.schema(frames[0].schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in")


def test_late_rows_are_kept_beside(spark, tmp_path):
    make = lambda rows: spark.createDataFrame(rows, "prov string, at string").withColumn("ts", F.to_timestamp("at")).drop("at")
    frames = [make([("e:1", "2024-01-01 10:00:00"), ("e:2", "2024-01-01 03:00:00")]), make([("e:3", "2024-01-01 08:59:59"), ("e:4", "2024-01-01 09:00:00"), ("e:5", "2024-01-01 20:00:00"), ("e:6", None)]), make([("e:7", "2024-01-01 10:00:00")])]
    w.write_with_late(parts(spark, tmp_path, frames), "ts", "1 hour", f"{tmp_path}/out", f"{tmp_path}/check").trigger(availableNow=True).start().awaitTermination()
    read = lambda kind: {r.prov for r in spark.read.schema("prov string, ts timestamp").parquet(f"{tmp_path}/out/{kind}").collect()}
    assert read("late") == {"e:3", "e:7"} and read("rows") == {"e:1", "e:2", "e:4", "e:5", "e:6"}


def test_running_sums_as_chains(spark, tmp_path):
    rows = batch(spark, ["click"]).withColumn("value", F.when(F.col("event_id") % 9 > 0, F.col("value")))
    frames = [rows.where(F.col("event_id") % 3 == i) for i in range(3)]
    run(w.running(w.annotated(parts(spark, tmp_path, frames), GIVEN["events"]), ["user_id"], "ts", "value"), "running")
    got = spark.table("running")
    want = {r.user_id: (r.n, r.total) for r in rows.groupBy("user_id").agg(F.count("*").alias("n"), F.sum(F.col("value").cast("decimal(18,4)")).alias("total")).collect()}
    last = {r.user_id: (r.n, r.total) for r in got.groupBy("user_id").agg(F.max("n").alias("n"), F.max_by("total", "n").alias("total")).collect()}
    assert {k: (n, t or 0) for k, (n, t) in want.items()} == last
    assert got.groupBy("user_id", "n").count().where("count > 1").isEmpty()
    edges = w.running_edges(got, ["user_id"]).collect()
    of = {}
    for e in edges:
        of.setdefault(bytes(e.parent), []).append(e)
    tops = set(of) - {bytes(e.child) for e in edges}
    assert len(tops) == len(want)
    lengths = []
    for top in tops:
        n, at = 0, top
        while at:
            n += 1
            at = next((bytes(e.child) for e in of[at] if e.ord == 0), None)
        lengths.append(n)
    assert sorted(lengths) == sorted(n for n, _ in want.values())
