"""Registered queries of the tools, baselines, measures and remaining tables."""

from __future__ import annotations

import uuid
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from polyprov import baselines, metrics, validate
from polyprov.engine import Engine
from polyprov.functions import udfs
from polyprov.functions.algebra import ALGEBRAS, measured
from polyprov.functions.circuit import circuit
from polyprov.operators.temporal import asof_join, interval_join
from polyprov.options import Options
from polyprov.sources.storage import shared_folder
from polyprov.sources.tokens import GIVEN, TokenPolicy
from polyprov.workloads import oracle as o
from polyprov.workloads import tpch
from polyprov.workloads.catalogue import AGGREGATED, _BY_SEGMENT, benchmark_oracle, delivered, engine_query, register, sql

N, R, S, C, O, E = (o.TOKEN[t] for t in ("nation", "region", "supplier", "customer", "orders", "events"))

# ---------------------------------------------------------------- tools


@engine_query("circuit_expand", _BY_SEGMENT[1])
def _circuit_expand(engine: Engine, sf_dir: str) -> DataFrame:
    """The circuit of a grouped sum, expanded to text, equals the text annotation."""
    df, c = circuit(engine, _BY_SEGMENT[0])
    texts = c.expand(df.select(F.col("prov").alias("gate")).union(df.select("v_agg")))
    a, b = texts.select(F.col("gate").alias("prov"), F.col("x").alias("p")), texts.select(F.col("gate").alias("v_agg"), F.col("x").alias("t"))
    return df.join(a, "prov").join(b, "v_agg").select("c_mktsegment", "v", F.col("t").alias("v_agg"), F.col("p").alias("prov"))


@engine_query("circuit_count", "SELECT o_orderkey, CAST(count(*) AS BIGINT) AS n FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_quantity > 45 AND o_orderstatus = 'P' GROUP BY 1")
def _circuit_count(engine: Engine, sf_dir: str) -> DataFrame:
    """Multiplicities from a circuit: alternatives of each order's sum of products."""
    df, c = circuit(engine, "SELECT o_orderkey, count(*) AS m FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE l_quantity > 45 AND o_orderstatus = 'P' GROUP BY o_orderkey")
    n = c.count(wanted=df.select(F.col("m_agg").alias("gate")))
    return df.join(n, df["m_agg"] == n["gate"]).select("o_orderkey", F.col("x").alias("n"))


@engine_query("circuit_edges", f"SELECT count(*) AS edges, count(DISTINCT c_mktsegment) AS parents FROM customer")
def _circuit_edges(engine: Engine, sf_dir: str) -> DataFrame:
    _, c = circuit(engine, "SELECT c_mktsegment FROM customer GROUP BY c_mktsegment")
    edges, _ = c.tables()
    return edges.agg(F.count("*").alias("edges"), F.countDistinct("parent").alias("parents"))


_DROPPED = "c_custkey % 10 = 3"


@engine_query("what_if_delete", f"SELECT c_mktsegment, count(*) AS n, {o.number('sum(c_acctbal)')} AS v FROM customer WHERE NOT {_DROPPED} GROUP BY 1")
def _what_if(engine: Engine, sf_dir: str) -> DataFrame:
    """Deletion on the annotated result against the query over the reduced table."""
    gone = engine.plain("SELECT c_custkey FROM customer").where(_DROPPED).select(F.concat(F.lit("c:"), "c_custkey").alias("token"))
    df = engine.rewrite("SELECT c_mktsegment, count(*) AS n, sum(c_acctbal) AS v FROM customer GROUP BY c_mktsegment", mode="symbolic")
    out = udfs.what_if_joined(df, gone, {"n": "n", "v": "v"}, ["c_mktsegment"])
    return out.select("c_mktsegment", F.col("n").cast("bigint").alias("n"), F.col("v").cast("double").alias("v"))


@engine_query("what_if_having", f"SELECT user_id FROM events WHERE event_id % 7 <> 0 GROUP BY 1 HAVING sum(value) <= 6000")
def _what_if_having(engine: Engine, sf_dir: str) -> DataFrame:
    """A row that a valued run has dropped can come back: symbolic mode has it."""
    gone = engine.plain("SELECT event_id FROM events").where("event_id % 7 = 0").select(F.concat(F.lit("e:"), "event_id").alias("token"))
    df = engine.rewrite("SELECT user_id, sum(value) AS v FROM events GROUP BY user_id HAVING sum(value) <= CAST(6000 AS DOUBLE)", mode="symbolic")
    return udfs.what_if_joined(df, gone, {}, ["user_id"]).select("user_id")


@engine_query("monomials", f"SELECT n_regionkey AS k, 'n:' || n_nationkey || ',s:' || s_suppkey AS monomial, CAST(1 AS BIGINT) AS coef FROM nation JOIN supplier ON n_nationkey = s_nationkey")
def _monomials(engine: Engine, sf_dir: str) -> DataFrame:
    df = engine.rewrite("SELECT n_regionkey AS k FROM nation JOIN supplier ON n_nationkey = s_nationkey GROUP BY n_regionkey")
    return udfs.monomials(df, "prov", ["k"]).withColumn("monomial", F.array_join("monomial", ","))


@engine_query("tensor_terms", f"SELECT c_mktsegment, {C} AS k, {o.text('c_acctbal')} AS m FROM customer")
def _tensor_terms(engine: Engine, sf_dir: str) -> DataFrame:
    return udfs.tensors(engine.rewrite(_BY_SEGMENT[0]), "v_agg", ["c_mktsegment"])


@engine_query("qualified_tokens", "SELECT n_name, 'warehouse#main#nation:n:' || n_nationkey || ' · archive#main#region:r:' || r_regionkey AS prov FROM nation JOIN region ON n_regionkey = r_regionkey")
def _qualified(engine: Engine, sf_dir: str) -> DataFrame:
    """Two sources of different folders and formats in one query, tokens telling them apart."""
    spark = engine.spark
    folder = f"{shared_folder(spark)}/federated-{uuid.uuid4().hex}"
    spark.read.parquet(f"{sf_dir}/nation.parquet").write.orc(f"{folder}/warehouse")
    regions = spark.read.parquet(f"{sf_dir}/region.parquet")
    regions.write.json(f"{folder}/archive")
    engine.register("nation", spark.read.orc(f"{folder}/warehouse"), GIVEN["nation"].qualified("warehouse", "main", "nation"))
    engine.register("region", spark.read.schema(regions.schema).json(f"{folder}/archive"), GIVEN["region"].qualified("archive", "main", "region"))
    return engine.rewrite("SELECT n_name FROM nation JOIN region ON n_regionkey = r_regionkey")


@engine_query("token_content_hash", "SELECT count(*) AS n, count(*) AS tokens FROM lineitem")
def _content_hash(engine: Engine, sf_dir: str) -> DataFrame:
    policy = TokenPolicy("l", kind="content_hash")
    df = engine.spark.read.parquet(f"{sf_dir}/lineitem.parquet")
    return df.select(policy.column(df.columns).alias("t")).agg(F.count("*").alias("n"), F.countDistinct("t").alias("tokens"))


@engine_query("text_length", f"SELECT c_mktsegment, CAST(length({o.delta(C)}) AS BIGINT) AS prov FROM customer GROUP BY 1")
def _length(engine: Engine, sf_dir: str) -> DataFrame:
    """Size of annotations without building them: what decides between text and circuit."""
    return engine.provenance("SELECT c_mktsegment FROM customer GROUP BY c_mktsegment", ALGEBRAS["length"]).df


_FANIN = " UNION ALL ".join(f"SELECT {k} AS fan_in, CAST(length({o.delta(_T)}) AS BIGINT) AS characters FROM (SELECT * FROM lineitem ORDER BY l_orderkey, l_partkey, l_suppkey, l_linenumber LIMIT {k})" for _T in (o.TOKEN["lineitem"],) for k in (1, 10, 1000))


@engine_query("fan_in", _FANIN)
def _fan_in(engine: Engine, sf_dir: str) -> DataFrame:
    """Text grows with the fan-in; a gate id has 16 bytes."""
    out = None
    for k in (1, 10, 1000):
        q = f"SELECT x FROM (SELECT 1 AS x FROM lineitem ORDER BY l_orderkey, l_partkey, l_suppkey, l_linenumber LIMIT {k}) GROUP BY x"
        part = engine.provenance(q, ALGEBRAS["length"]).df.select(F.lit(k).alias("fan_in"), F.col("prov").alias("characters"))
        out = part if out is None else out.union(part)
    return out


@engine_query("provenance_of", f"SELECT c_mktsegment, count(*) AS n, {o.delta(C)} AS prov FROM customer WHERE c_mktsegment = 'BUILDING' GROUP BY 1")
def _of(engine: Engine, sf_dir: str) -> DataFrame:
    return engine.provenance_of("SELECT c_mktsegment, count(*) AS n FROM customer GROUP BY c_mktsegment", "c_mktsegment = 'BUILDING'").select("c_mktsegment", "n", "prov")


@engine_query("asof_join", f"""SELECT e.event_id, p.event_id AS before_id, {o.token('events', 'e')} || ' · ' || {o.token('events', 'p')} AS prov FROM (SELECT * FROM events WHERE event_type = 'purchase') e
    ASOF JOIN (SELECT * FROM events WHERE event_type = 'view') p ON e.user_id = p.user_id AND e.ts >= p.ts""")
def _asof(engine: Engine, sf_dir: str) -> DataFrame:
    """Each purchase with the user's latest view before it."""
    left, _ = engine.frame("SELECT event_id, user_id, ts FROM events WHERE event_type = 'purchase'")
    right, _ = engine.frame("SELECT event_id AS before_id, user_id, ts AS seen FROM events WHERE event_type = 'view'")
    out = asof_join(left, right, ["user_id"], "ts", "seen", ["before_id"])
    return out.df.select("event_id", "before_id", out.product()[0].alias("prov"))


@engine_query("interval_join", f"""SELECT e.event_id, p.event_id AS after_id, {o.token('events', 'e')} || ' · ' || {o.token('events', 'p')} AS prov FROM (SELECT * FROM events WHERE event_type = 'signup') e
    JOIN (SELECT * FROM events WHERE event_type = 'error') p ON p.ts BETWEEN e.ts AND e.ts + INTERVAL 120 SECOND""")
def _interval(engine: Engine, sf_dir: str) -> DataFrame:
    """Errors within two minutes after a signup."""
    left, _ = engine.frame("SELECT event_id, ts FROM events WHERE event_type = 'signup'")
    right, _ = engine.frame("SELECT event_id AS after_id, ts AS at FROM events WHERE event_type = 'error'")
    out = interval_join(left, right, "ts", "at", 120)
    return out.df.select("event_id", "after_id", out.product()[0].alias("prov"))


# ---------------------------------------------------------------- baselines

_SPJ = "SELECT c_mktsegment, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY c_mktsegment"
_ROWS = "SELECT *, count(*) OVER (PARTITION BY c_mktsegment) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey"
engine_query("witness_token", f"SELECT c_mktsegment, n, {C} AS prov_customer, {N} AS prov_nation FROM ({_ROWS})")(lambda e, d: baselines.token_witness(e, _SPJ))
engine_query(
    "witness_full",
    f"""SELECT c_mktsegment, n, c_custkey AS prov_customer_c_custkey, c_name AS prov_customer_c_name, CAST(c_nationkey AS BIGINT) AS prov_customer_c_nationkey, {o.number('c_acctbal')} AS prov_customer_c_acctbal,
    c_mktsegment AS prov_customer_c_mktsegment, CAST(n_nationkey AS BIGINT) AS prov_nation_n_nationkey, n_name AS prov_nation_n_name, CAST(n_regionkey AS BIGINT) AS prov_nation_n_regionkey FROM ({_ROWS})""",
)(lambda e, d: baselines.full_witness(e, _SPJ))
engine_query("witness_sublink", f"SELECT n_name, {N} AS prov_nation, {S} AS prov_supplier FROM nation JOIN supplier ON s_nationkey = n_nationkey WHERE s_acctbal < 0")(
    lambda e, d: baselines.token_witness(e, "SELECT n_name FROM nation WHERE n_nationkey IN (SELECT s_nationkey FROM supplier WHERE s_acctbal < 0)", strict=False)
)
engine_query("circuit_fn", o.grouped([("c_mktsegment", "c_mktsegment")], [("n", "count(*)", "'1'", "count")], "customer JOIN nation ON c_nationkey = n_nationkey", o.times(C, N)).replace("+count", "+").replace("n_agg", "agg_1"))(
    lambda e, d: baselines.function_circuit(e, _SPJ)
)

# ---------------------------------------------------------------- measures


@engine_query("size_measure", f"SELECT CAST(sum(length(c_mktsegment) + length(p)) AS BIGINT) AS characters FROM (SELECT c_mktsegment, {o.delta(C)} AS p FROM customer GROUP BY 1)")
def _size(engine: Engine, sf_dir: str) -> DataFrame:
    return metrics.characters(engine.rewrite("SELECT c_mktsegment FROM customer GROUP BY c_mktsegment"))


@engine_query("support_matrix", "SELECT * FROM (VALUES " + ", ".join(f"('{k}', '{x}', {str(x in v).lower()})" for k, v in metrics.SUPPORT.items() for x in metrics.SYSTEMS) + ") AS m(feature, system, supported)")
def _support(engine: Engine, sf_dir: str) -> DataFrame:
    """What each system accepts, found by trying it, against what is reported for it."""
    return metrics.support_matrix(engine)


def _validated(names: tuple[str, ...]):
    def run(engine: Engine, sf_dir: str) -> DataFrame:
        rows = [(n, r.check, r.rows > 0 or r.ok, r.ok) for n in names for r in validate.validate(engine, tpch.text(n, sf_dir), "valued" if n in ("t11", "t15") else "symbolic")]
        return engine.spark.createDataFrame(rows, "query string, check string, ran boolean, passed boolean")

    return run


_CHECKS = ("result", "aggregates", "products", "complete")
for _n in tpch.QUERIES:
    engine_query(f"validate_{_n}", f"SELECT '{_n}' AS query, c AS \"check\", true AS ran, true AS passed FROM (SELECT unnest({list(_CHECKS)}) AS c)")(_validated((_n,)))


@engine_query("validate_distinct_unrewritten", "SELECT true AS differs")
def _unrewritten(engine: Engine, sf_dir: str) -> DataFrame:
    """Without its rewriting, COUNT(DISTINCT) resolves to wrong values, as reported."""
    r = validate.check_aggregates(engine, tpch.text("t16", sf_dir), rewrite_distinct=False)
    return engine.spark.createDataFrame([(not r.ok,)], "differs boolean")


# ---------------------------------------------------------------- the remaining tables

_D, _L, _B, _P, _X, _V = (o.TOKEN[t] for t in ("documents", "labels", "benchmark", "pages", "embeddings", "conversations"))
_dl = f"documents JOIN labels ON documents.doc_id = labels.doc_id"
_dp = o.times(o.token("documents", "documents"), o.token("labels", "labels"))
sql("docs_quality", "SELECT source, avg(quality) AS q, count(*) AS n FROM documents JOIN labels ON documents.doc_id = labels.doc_id GROUP BY source",
    o.grouped([("source", "source")], [("q", o.number("avg(quality)"), "CAST(quality AS VARCHAR)", "avg"), ("n", "count(*)", "'1'", "count")], _dl, _dp))
sql("docs_benchmark", "SELECT documents.doc_id FROM documents WHERE EXISTS (SELECT * FROM benchmark WHERE contains(documents.text, benchmark.text))",
    f"SELECT doc_id, {_D} || ' · ' || p AS prov FROM documents JOIN (SELECT d.text AS t, {o.delta('b.p0')} AS p FROM (SELECT DISTINCT text FROM documents) d JOIN (SELECT text, {_B} AS p0 FROM benchmark) b ON contains(d.text, b.text) GROUP BY 1) ON t = text")
sql("docs_copies", "SELECT md5(text) AS h, count(*) AS n FROM documents GROUP BY md5(text) HAVING count(*) > 1",
    f"SELECT h, n, t AS n_agg, p || ' · [' || t || ' > 1⊗1]' AS prov FROM (SELECT md5(text) AS h, count(*) AS n, {o.formal(_D, chr(39) + '1' + chr(39), 'count')} AS t, {o.delta(_D)} AS p FROM documents GROUP BY 1) WHERE n > 1")
sql("conv_system", "SELECT conv_id, turn FROM conversations WHERE conv_id IN (SELECT conv_id FROM conversations WHERE role = 'system')",
    f"SELECT conv_id, turn, {_V} || ' · ' || p AS prov FROM conversations JOIN (SELECT conv_id AS k, {o.delta(_V)} AS p FROM conversations WHERE role = 'system' GROUP BY 1) ON k = conv_id")
sql("conv_long", "SELECT conv_id, turn FROM conversations c WHERE length(text) > (SELECT avg(length(d.text)) FROM conversations d WHERE d.conv_id = c.conv_id)",
    f"SELECT conv_id, turn, {_V} || ' · ' || p || ' · [1⊗' || {o.text('length(text)')} || ' > ' || t || ']' AS prov FROM conversations JOIN (SELECT conv_id AS k, avg(length(text)) AS v, {o.formal(_V, 'CAST(length(text) AS VARCHAR)', 'avg')} AS t, {o.delta(_V)} AS p FROM conversations GROUP BY 1) ON k = conv_id WHERE length(text) > v")
sql("pages_host", "SELECT regexp_extract(url, '://([^/?#]*)', 1) AS host FROM pages GROUP BY regexp_extract(url, '://([^/?#]*)', 1)", f"SELECT regexp_extract(url, '://([^/?#]*)', 1) AS host, {o.delta(_P)} AS prov FROM pages GROUP BY 1")
sql("emb_label", "SELECT label, count(*) AS n, max(embedding[0]) AS top FROM embeddings GROUP BY label",
    o.grouped([(o.whole("label"), "label")], [("n", "count(*)", "'1'", "count"), ("top", o.number("max(embedding[1])"), o.text("embedding[1]"), "max")], "embeddings", _X))
sql("events_type", "SELECT event_type, count(*) AS n FROM events WHERE CAST(get_json_object(props, '$.k') AS INT) > 50 GROUP BY event_type",
    o.grouped([("event_type", "event_type")], [("n", "count(*)", "'1'", "count")], "events WHERE CAST(json_extract(props, '$.k') AS INT) > 50", E))
sql("events_user_sum", "SELECT user_id, sum(value) AS total FROM events GROUP BY user_id", o.grouped([("user_id", "user_id")], [("total", o.number("sum(value)"), o.text("value"), "sum")], "events", E), mode="valued")


def _stream_window(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily windows over the event stream: what the append mode has closed."""
    from polyprov.streaming.windows import annotated, windowed, write_batches

    source = spark.read.parquet(f"{sf_dir}/events.parquet")
    stream = spark.readStream.schema(source.schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    rows = annotated(stream, GIVEN["events"]).withColumn("ts", F.col("ts").cast("timestamp"))
    out = windowed(rows, "ts", "1 day", ["event_type"], "value")
    folder = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    query = write_batches(out, f"{folder}/rows", f"{folder}/checkpoint").trigger(availableNow=True).start()
    query.awaitTermination()
    return delivered(spark.read.parquet(f"{folder}/rows").drop("epoch").withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("window_start", "window_end")}))


register(
    "stream_window",
    _stream_window,
    f"""SELECT d AS window_start, d + INTERVAL 1 DAY AS window_end, event_type, n, total, total_agg, prov FROM (SELECT date_trunc('day', ts)::TIMESTAMP AS d, event_type, count(*) AS n, {o.number('sum(value)')} AS total, {o.formal(E, o.text('value'), 'sum')} AS total_agg, {o.delta(E)} AS prov
    FROM events GROUP BY 1, 2) WHERE d + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)""",
)


def options_table(spark: SparkSession) -> DataFrame:
    """Options and their defaults."""
    return spark.createDataFrame([(k, str(v)) for k, v in Options().__dict__.items()], "option string, value string")


# ---------------------------------------------------------------- sizes of provenance, all queries


def _length_of(columns) -> str:
    return " + ".join(f"coalesce(length({c}), 0)" for c in columns)


def _sizes_oracle(mode: str) -> str:
    parts = []
    for n in tpch.QUERIES:
        texts = (["prov"] + [f"{c}_agg" for c in AGGREGATED.get(n, ())]) if mode == "valued" else ["prov", *AGGREGATED.get(n, ())]
        parts.append(f"SELECT '{n}' AS query, CAST(coalesce(sum({_length_of(texts)}), 0) AS BIGINT) AS characters FROM ({benchmark_oracle(n, mode)})")
    return " UNION ALL ".join(parts)


def _sizes(mode: str):
    def run(engine: Engine, sf_dir: str) -> DataFrame:
        rows = []
        for n in tpch.QUERIES:
            with measured():
                df = engine.rewrite(tpch.text(n, sf_dir), mode=mode)
            texts = ["prov"] + [c if mode == "symbolic" else f"{c}_agg" for c in AGGREGATED.get(n, ())]
            rows.append((n, metrics.total(df, texts)))
        return engine.spark.createDataFrame(rows, "query string, characters long")

    return run


for _mode in ("valued", "symbolic"):
    engine_query(f"experiment_sizes_{_mode}", _sizes_oracle(_mode))(_sizes(_mode))
