"""Worked examples, algebras, text tools and edge cases of the rules."""

import pytest
from conftest import SF

from polyprov.errors import NonUniqueTokens, UnsupportedForBaseline, UnsupportedForProvenance
from polyprov.functions import evaluate as ev
from polyprov.functions.grammar import ParseError, parse, parse_value, render
from polyprov.operators import basic as b
from polyprov.operators import extended as x
from polyprov.operators import unnest as u
from polyprov.options import Options
from polyprov.sources.tokens import TokenPolicy

OWN = TokenPolicy("", ("t",))


def relation(spark, rows, columns, mode="symbolic", **options):
    df = spark.createDataFrame(rows, ["t", *columns] if isinstance(columns, list) else f"t string, {columns}")
    names = columns if isinstance(columns, list) else [c.split()[0] for c in columns.split(", ")]
    return b.project_bag(b.annotate_base(df, OWN, Options(mode=mode, **options)), names)


def log_a(spark, mode="symbolic", **o):
    return relation(spark, [("t1", "sn123", 100), ("t2", "sn234", 150), ("t3", "sn345", 220), ("t4", "sn123", 100)], ["sn", "duration"], mode, **o)


def equipment(spark, mode="symbolic", **o):
    return relation(spark, [("t5", "sn1", "ModelA"), ("t6", "sn2", "ModelA"), ("t7", "sn345", "ModelB")], ["sn", "model"], mode, **o)


def log_b(spark, mode="symbolic", **o):
    return relation(spark, [("t8", "ModelB", 10), ("t9", "ModelB", 5), ("t10", "ModelA", 7)], ["model", "num_events"], mode, **o)


def rows(af):
    return sorted((tuple(r) for r in af.delivered().collect()), key=lambda r: tuple((c is None, str(c)) for c in r))


def test_join_and_selection(spark):
    assert rows(b.select_rows(b.join(log_a(spark), equipment(spark), ["sn"]), "model = 'ModelB'")) == [("sn345", 220, "ModelB", "t3 · t7")]


def test_unions(spark):
    one, two = b.project_bag(equipment(spark), ["model"]), b.project_bag(log_b(spark), ["model"])
    assert rows(b.union_set(one, two)) == [("ModelA", "t10 + t5 + t6"), ("ModelB", "t7 + t8 + t9")]
    assert len(rows(b.union_all(one, two))) == 6


def test_aggregates(spark):
    assert rows(b.aggregate(log_b(spark), [b.AggSpec("total", "sum", "num_events")])) == [("t10⊗7 +sum t8⊗10 +sum t9⊗5", "1")]
    assert rows(b.group_by(log_a(spark), ["sn"])) == [("sn123", "δ(t1 + t4)"), ("sn234", "δ(t2)"), ("sn345", "δ(t3)")]
    assert rows(b.project_set(log_a(spark), ["sn"])) == rows(b.group_by(log_a(spark), ["sn"]))
    total = b.group_agg(log_a(spark), ["sn"], [b.AggSpec("total", "sum", "duration")])
    assert rows(total)[0] == ("sn123", "t1⊗100 +sum t4⊗100", "δ(t1 + t4)")


@pytest.mark.parametrize(("mode", "want"), [
    ("symbolic", [("sn123", "t1⊗100 +sum t4⊗100", "δ(t1 + t4) · [t1⊗100 +sum t4⊗100 <= 1⊗200]"), ("sn234", "t2⊗150", "δ(t2) · [t2⊗150 <= 1⊗200]"), ("sn345", "t3⊗220", "δ(t3) · [t3⊗220 <= 1⊗200]")]),
    ("valued", [("sn123", 200, "t1⊗100 +sum t4⊗100", "δ(t1 + t4) · [t1⊗100 +sum t4⊗100 <= 1⊗200]"), ("sn234", 150, "t2⊗150", "δ(t2) · [t2⊗150 <= 1⊗200]")]),
])
def test_selection_on_an_aggregate(spark, mode, want):
    af = x.select_agg(b.group_agg(log_a(spark, mode), ["sn"], [b.AggSpec("total", "sum", "duration")]), "total", "<=", 200)
    assert rows(af) == want
    if mode == "symbolic":
        assert [ev.evaluate(r[-1]) for r in want] == [1, 1, 0]


def test_exists_with_inequality(spark):
    e, m = equipment(spark), x.renamed(log_b(spark), {"model": "m"})
    out = b.group_by(u.exists(e, m, [("model", "<>", "m")]), ["model"])
    assert rows(out) == [("ModelA", "δ(t5 · δ(t8 + t9) + t6 · δ(t8 + t9))"), ("ModelB", "δ(t7 · δ(t10))")]


def test_reaggregation_styles(spark):
    for style, want in (("printed", "(t1⊗100 +sum t4⊗100) +max (t2⊗150) +max (t3⊗220)"), ("evaluable", "δ(t1 + t4) *max (t1⊗100 +sum t4⊗100) +max δ(t2) *max (t2⊗150) +max δ(t3) *max (t3⊗220)")):
        g = b.group_agg(log_a(spark, reagg_style=style), ["sn"], [b.AggSpec("total", "sum", "duration")])
        (m, p), = rows(x.reaggregate(g, [], [b.AggSpec("m", "max", "total")]))
        assert m == want and p.startswith("δ(t1 + t4) *max (")
        assert ev.evaluate_value(m) == 220
    # Only the evaluable style feels a deletion in the outer annotation as well.
    assert ev.evaluate_value(want, ev.without(["t3"])) == 200


def test_empty_inputs(spark):
    none = b.select_rows(log_a(spark, "valued"), "false")
    assert rows(b.aggregate(none, [b.AggSpec("s", "sum", "duration"), b.AggSpec("n", "count")])) == [(None, 0, "0", "1⊗0", "1")]
    assert rows(b.group_agg(none, ["sn"], [b.AggSpec("s", "sum", "duration")])) == []
    assert ev.evaluate_value("0") is None and ev.evaluate_value("1⊗0") == 0


def nulls(spark, mode="valued"):
    r = relation(spark, [("r1", 1, 5), ("r2", 2, None), ("r3", None, 7)], "k int, a int", mode)
    v = relation(spark, [("v1", 1, 3), ("v2", 1, 4), ("v3", 2, None)], "j int, c int", mode)
    return r, v


def test_nulls_in_subqueries(spark):
    r, v = nulls(spark)
    assert rows(u.exists(r, v, [("k", "=", "j")]))[0][-1] == "r1 · δ(v1 + v2)"
    assert {t[0] for t in rows(u.in_(r, v, ["k"], ["j"]))} == {1, 2}
    assert rows(u.all_(r, v, "a", ">", "c")) == []  # a null among the inner values: unknown
    assert len(rows(u.all_(r, b.select_rows(v, "c is not null"), "a", ">", "c"))) == 2
    assert len(rows(u.all_(r, b.select_rows(v, "false"), "a", ">", "c"))) == 3  # true over nothing
    assert {t[0] for t in rows(u.all_(r, v, "a", ">", "c", [("k", "=", "j")]))} == {1, None}
    assert rows(u.not_in(r, v, ["k"], ["c"])) == []
    assert {t[0] for t in rows(u.not_exists(r, v, [("k", "=", "c")]))} == {1, 2, None}
    assert len(rows(u.scalar(r, v, "k", ">", b.AggSpec("n", "count", "c"), [("k", "=", "j")]))) == 1
    assert len(rows(u.any_(r, v, "a", ">", "c"))) == 2
    assert rows(u.prefix_exists(r, v, "a", ">", "c"))[0][-1].startswith("r")


def test_negation_options(spark):
    r, v = (nulls(spark)[0], nulls(spark)[1])
    from dataclasses import replace

    with pytest.raises(UnsupportedForProvenance):
        u.not_exists(replace(r, options=Options(negation="reject")), v, [("k", "=", "j")])
    m = {t[0]: t[-1] for t in rows(u.not_exists(replace(r, options=Options(negation="monus")), v, [("k", "=", "j")]))}
    assert m[1] == "(r1 ⊖ δ(v1 + v2))" and ev.evaluate(m[1]) == 0 and ev.evaluate(m[1], ev.without(["v1", "v2"])) == 1 and m[None] == "r3"


def test_sets(spark):
    r, v = nulls(spark)
    one, two = b.project_bag(r, ["k"]), x.renamed(b.project_bag(v, ["j"]), {"j": "k"})
    assert rows(u.intersect(one, two))[0] == (1, "δ(r1) · δ(v1 + v2)")
    assert rows(u.except_(one, two)) == [(None, "δ(r3)")]
    assert len(rows(b.drop_duplicates(two, ["k"]))) == 2


def test_outer_joins(spark):
    r, v = nulls(spark)
    assert sorted(t[-1] for t in rows(b.join(r, v, r.df.k == v.df.j, "left"))) == ["r1 · v1", "r1 · v2", "r2 · v3", "r3 · 1"]
    assert b.join(r, v, r.df.k == v.df.j, "full").caveats


def test_reserved_names_are_counted_up(spark):
    af = relation(spark, [("t1", 1, 2)], ["prov", "total_agg"], "valued")
    assert af.delivered().columns == ["prov", "total_agg", "prov_1"]


def test_tokens(spark):
    from polyprov.sources.tokens import GIVEN, assert_unique_tokens, content_hash

    lines = spark.read.parquet(f"{SF}/lineitem.parquet")
    with pytest.raises(NonUniqueTokens):
        assert_unique_tokens(lines, GIVEN["lineitem"])
    from dataclasses import replace

    assert_unique_tokens(lines, replace(GIVEN["lineitem"], strict=True))
    df = spark.createDataFrame([(None, 1), (1, None)], "a int, b int")
    assert df.select(content_hash(["a", "b"]).alias("h")).distinct().count() == 2
    files = spark.read.parquet(f"{SF}/nation.parquet")
    assert files.select(TokenPolicy("n", kind="row_index").column(files.columns).alias("t")).distinct().count() == 25


def test_grammar_round_trip_and_errors():
    for t in ("a", "(a + b) · c", "δ(a · δ(b + c))", "a · [x⊗1 +sum y⊗2 <= 1⊗3]", "[(a⊗1) / (b⊗2) > (0.5) * (c⊗4)]", "a *max (b⊗1) + c *max (d⊗2)", "a · [(x⊗1 <= 1⊗2) or (x⊗1 > 1⊗8)]", "a · [not (x⊗1 = 1⊗2)]"):
        assert render(parse(t)) == t
    for t in ("a +", "(a", "a)", "[a]", ""):
        with pytest.raises(ParseError):
            parse(t)
    assert "\\delta(" in render(parse("δ(a)"), "latex") and render(parse("w#main#nation:n:1"), "short") == "n:1"


def test_laws_and_images():
    assert render(ev.simplify(parse("δ(δ(a + 0)) · 1"))) == "δ(a)" and ev.simplify(parse("a · 0 + 0")) == ("const", 0)
    t = "δ(a · b + a · c)"
    assert ev.specialise(t, "nat") == 1 and ev.specialise(t, "lineage") == ["a", "b", "c"] and ev.specialise(t, "why") == [["a", "b"], ["a", "c"]]
    cost = {"a": 1.0, "b": 5.0, "c": 2.0}.get
    assert ev.specialise(t, "cost", cost) == 3.0 and ev.specialise(t, "trust", {"a": 0.5, "b": 0.5, "c": 1.0}.get) == 0.5
    assert ev.degree(parse(t)) == 2 and ev.n_monomials(parse(t)) == 2 and ev.tokens(parse("a · [b⊗1 > 1⊗0]")) == {"a", "b"}
    assert ev.value_of(parse_value("a⊗2 +min b⊗1")) == 1 and ev.value_of(parse_value("a⊗2 +avg b⊗1"), ev.without(["b"])) == 2


def test_specialised_texts_equal_runs_in_the_algebra(spark):
    from polyprov.engine import Engine
    from polyprov.functions.algebra import ALGEBRAS

    e = Engine(spark).register_folder(SF, ["customer", "orders"])
    q = "SELECT c_nationkey FROM customer JOIN orders ON c_custkey = o_custkey WHERE o_orderstatus = 'P' GROUP BY c_nationkey"
    texts = {r[0]: r.prov for r in e.rewrite(q).collect()}
    for name in ("nat", "bool", "lineage", "why"):
        for r in e.provenance(q, ALGEBRAS[name]).df.collect():
            assert ev.specialise(texts[r[0]], name) == ([list(w) for w in r.prov] if name == "why" else r.prov)
    for r in e.provenance(q, ALGEBRAS["normal_form"]).df.collect():
        assert ev.specialise(texts[r[0]], "normal_form") == [(m.coef, list(m.toks)) for m in r.prov]


def test_refusals(spark):
    from polyprov.baselines import function_circuit, token_witness
    from polyprov.engine import Engine

    e = Engine(spark).register_folder(SF, ["nation", "supplier"])
    nested = "SELECT n_name FROM nation WHERE n_nationkey IN (SELECT s_nationkey FROM supplier)"
    for f in (token_witness, function_circuit):
        with pytest.raises(UnsupportedForBaseline):
            f(e, nested)
    with pytest.raises(UnsupportedForProvenance):
        e.rewrite("SELECT n_nationkey FROM nation INTERSECT ALL SELECT s_nationkey FROM supplier")
    with pytest.raises(UnsupportedForProvenance):
        e.rewrite("SELECT n_name FROM nation WHERE n_nationkey NOT IN (SELECT s_nationkey FROM supplier)", negation="reject")
    spark.range(3).createOrReplaceTempView("stranger")
    with pytest.raises(UnsupportedForProvenance):
        e.rewrite("SELECT * FROM stranger")
    assert e.provenance("SELECT n_name FROM nation WHERE n_nationkey NOT IN (SELECT s_nationkey FROM supplier)").caveats


def test_measures(spark):
    from polyprov import metrics

    df = spark.createDataFrame([("ab", 12), ("c", None), (None, 345)], "a string, b int")
    assert metrics.size_of(df) == 8 and metrics.overhead(3.0, 2.0) == 50.0
    assert metrics.wins({"a": {"q": 1.0, "r": None}, "b": {"q": 2.0, "r": 3.0}}) == {"a": 1, "b": 1}
    t = metrics.time_query(lambda: df, 2)
    assert t.failure is None and len(t.runs) == 2
    assert metrics.time_query(lambda: spark.sql("select nope"), 1).failure == "rewriting error"
    assert metrics.group_average({"q": 1.0}, ["q", "r"]) is None
