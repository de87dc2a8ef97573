"""Aggregates, measures and baselines that no registered query covers."""

import pytest
from conftest import SF
from pyspark.sql import functions as F

from polyprov.baselines import full_witness, token_witness
from polyprov.functions import evaluate as ev
from polyprov.functions import udfs


@pytest.fixture(scope="module")
def engine(spark):
    from polyprov.engine import Engine

    return Engine(spark).register_folder(SF)


@pytest.mark.parametrize("call", ["stddev_samp", "var_samp", "stddev_pop", "var_pop"])
def test_spread_of_values(spark, engine, call):
    q = f"SELECT c_mktsegment, {call}(c_acctbal) AS v FROM customer GROUP BY c_mktsegment"
    want = {r[0]: r.v for r in spark.sql(q).collect()}
    got = engine.rewrite(q).collect()
    assert len(got) == len(want)
    for r in got:
        assert r.v == pytest.approx(want[r[0]]) and len(ev.tokens(ev.parse_value(r.v_agg))) == spark.table("customer").where(F.col("c_mktsegment") == r[0]).count()


def test_sampled_rows_keep_their_tokens(spark, engine):
    got = engine.rewrite("SELECT c_custkey FROM customer TABLESAMPLE (40 PERCENT) REPEATABLE (3)").collect()
    assert got and all(r.prov == f"c:{r.c_custkey}" for r in got)


def test_pivot(spark, engine):
    q = "SELECT * FROM (SELECT o_orderstatus, o_orderpriority, o_totalprice FROM orders) PIVOT (count(o_totalprice) FOR o_orderstatus IN ('F', 'O'))"
    got = engine.rewrite(q)
    assert {tuple(r) for r in got.select("o_orderpriority", "F", "O").collect()} == {tuple(r) for r in spark.sql(q).collect()}


def test_semi_join(spark, engine):
    q = "SELECT n_name FROM nation LEFT SEMI JOIN supplier ON n_nationkey = s_nationkey"
    assert {r.n_name for r in engine.rewrite(q).collect()} == {r.n_name for r in spark.sql(q).collect()}


def test_lag_and_lead(spark, engine):
    q = "SELECT event_id, lag(value) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS a, lead(value) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM events"
    got = engine.rewrite(q)
    assert {tuple(r) for r in got.select("event_id", "a", "b").collect()} == {tuple(r) for r in spark.sql(q).collect()}


def test_both_strategies_of_the_full_witness_baseline(spark, engine):
    q = "SELECT n_name FROM nation WHERE n_nationkey IN (SELECT s_nationkey FROM supplier)"
    left, domain = (sorted(map(str, full_witness(engine, q, s).collect())) for s in ("left", "domain"))
    assert left == domain and len(left) == spark.table("supplier").count()


def test_token_witness_with_all_columns(spark, engine):
    q = "SELECT c_name FROM customer JOIN orders ON c_custkey = o_custkey WHERE o_orderstatus = 'P'"
    tokens, everything = token_witness(engine, q), token_witness(engine, q, columns="all")
    assert tokens.count() == everything.count() > 0 and len(everything.columns) > len(tokens.columns)


def test_bounded_display_and_number_of_tokens(spark, engine):
    df = spark.createDataFrame([("a + b + c",), ("a",), ("c:1 · o:2",)], "prov string")
    assert [r[0] for r in df.select(udfs.truncated(F.col("prov"), 2)).collect()] == ["a + b + … (3)", "a", "c:1 · o:2"]
    orders = engine.rewrite("SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey")
    n = spark.table("orders").count()
    assert abs(udfs.approx_tokens(orders).first()[0] - n) < 0.15 * n


def test_joined_deletions_equal_listed_ones(spark, engine):
    q = "SELECT user_id, sum(value) AS v, count(*) AS n FROM events GROUP BY user_id HAVING sum(value) <= 2000"
    df = engine.rewrite(q, mode="symbolic")
    tokens = [f"e:{i}" for i in range(0, 1000, 3)]
    deleted = spark.createDataFrame([(t,) for t in [*tokens, tokens[0]]], "token string")
    listed = udfs.what_if(df, tokens, {"v": "v", "n": "n"}).select("user_id", "v", "n")
    joined = udfs.what_if_joined(df, deleted, {"v": "v", "n": "n"}, ["user_id"]).select("user_id", "v", "n")
    assert {tuple(r) for r in joined.collect()} == {tuple(r) for r in listed.collect()} != set()
