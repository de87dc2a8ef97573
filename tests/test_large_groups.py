"""Rules whose cost or result depends on the size of a group, and on ties in it."""

import time

from pyspark.sql import functions as F

from polyprov.functions.algebra import ALGEBRAS


def _summed(spark, algebra, n: int, repeat: int = 1):
    """One group of n tokens, each ``repeat`` times, in the algebra."""
    a = ALGEBRAS[algebra]
    token = F.concat(F.lit("t:"), (F.col("id") % n).cast("string"))
    return spark.range(n * repeat).select(a.token(token).alias("p")).agg(a.plus("p").alias("p"))


def test_normal_form_counts_repeated_monomials_in_time(spark):
    small = _summed(spark, "normal_form", 3, 4).first().p
    assert [(m.coef, m.toks) for m in small] == [(4, ["t:0"]), (4, ["t:1"]), (4, ["t:2"])]
    began = time.perf_counter()
    r = _summed(spark, "normal_form", 40_000, 2).select(F.size("p").alias("n"), F.forall("p", lambda m: m["coef"] == 2).alias("twice")).first()
    assert (r.n, r.twice) == (40_000, True) and time.perf_counter() - began < 15


def test_why_sets_are_sorted_and_distinct_in_time(spark):
    assert _summed(spark, "why", 3, 4).first().p == [["t:0"], ["t:1"], ["t:2"]]
    began = time.perf_counter()
    assert _summed(spark, "why", 40_000, 2).select(F.size("p").alias("n")).first().n == 40_000
    assert time.perf_counter() - began < 15


def _frames(spark, outer, inner):
    from polyprov.operators.basic import annotate_base
    from polyprov.sources.tokens import TokenPolicy

    left = annotate_base(spark.createDataFrame(outer, "x int, a double"), TokenPolicy("r", ("x",)))
    right = annotate_base(spark.createDataFrame(inner, "y int, c double"), TokenPolicy("s", ("y",)))
    return left, right


def _texts(af):
    return sorted((r.x, r.prov) for r in af.df.select("x", af.product()[0].alias("prov")).collect())


def test_prefix_lists_rows_of_tied_values_in_one_order(spark):
    from polyprov.operators import unnest as u

    left, right = _frames(spark, [(1, 5.0), (2, 0.5), (3, None), (4, 9.0)], [(1, 1.0), (2, 2.0), (3, 1.0), (4, 9.0), (5, None)])
    got = _texts(u.prefix_exists(left, right, "a", ">", "c"))
    assert got == [(1, "r:1 · δ(s:1 + s:2 + s:3)"), (4, "r:4 · δ(s:1 + s:2 + s:3)")]
    assert got == _texts(u.exists_domain(left, right, [F.col("a")], F.col("a") > F.col("c")))


def _plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_any_by_order_makes_no_pairs_of_rows(spark):
    from polyprov.operators import unnest as u

    left, right = _frames(spark, [(1, 5.0)], [(1, 1.0)])
    out = u.any_(left, right, "a", ">", "c")
    assert "string_agg" not in _plan(out.df) and "CartesianProduct" in _plan(out.df) and "Join BuildRight, LeftOuter" not in _plan(out.df) and _texts(out) == [(1, "r:1 · δ(s:1)")]


def test_all_of_a_whole_relation_takes_its_row_beside_each(spark):
    """An outer nested loop join copied the row with the whole relation's text for all outer rows at once."""
    from polyprov.operators import unnest as u

    for op, a, agg in ((">", 5.0, "max"), ("<", 0.5, "min")):
        left, right = _frames(spark, [(1, a)], [(1, 1.0), (2, 2.0)])
        out = u.all_(left, right, "a", op, "c")
        assert "CartesianProduct" in _plan(out.df) and out.df.rdd.getNumPartitions() > 1
        assert _texts(out) == [(1, f"r:1 · δ(s:1 + s:2) · [1⊗{a:.4f} {op} s:1⊗1.0000 +{agg} s:2⊗2.0000]")]
        assert _texts(u.all_(left, right.with_df(right.df.where("false")), "a", op, "c")) == [(1, "r:1 · 1 · 1")]


def test_uncorrelated_scalar_takes_its_row_beside_each(spark):
    from conftest import SF

    from polyprov.engine import Engine

    df = Engine(spark).register_folder(SF).rewrite("SELECT s_name FROM supplier WHERE s_acctbal > (SELECT avg(x.s_acctbal) FROM supplier x)")
    assert "CartesianProduct" in _plan(df) and df.rdd.getNumPartitions() > 1


def test_wide_rows_do_not_pile_up_in_a_parquet_writer(spark, tmp_path):
    """After many short rows the writer looked at its size only thousands of rows later."""
    from polyprov.engine import Engine

    Engine(spark)
    wide = F.when(F.col("id") < 5000, F.lit("1")).otherwise(F.concat(F.col("id").cast("string"), F.expr("repeat('c:12 + ', 300000)")))
    spark.range(0, 5300, 1, 1).select(wide.alias("prov")).write.option("parquet.block.size", 8 << 20).option("compression", "none").parquet(f"{tmp_path}/w")
    file = next(tmp_path.glob("w/*.parquet"))
    import pyarrow.parquet as pq

    meta = pq.ParquetFile(file).metadata
    assert meta.num_rows == 5300 and max(meta.row_group(i).total_byte_size for i in range(meta.num_row_groups)) < 64 << 20


def test_wide_rows_have_small_row_groups_and_pages_of_one_row(spark, tmp_path):
    """A page had four rows, a row group some 128 MB: compressors and readers of whole batches held them at once."""
    from polyprov.engine import Engine

    Engine(spark)
    spark.range(0, 24, 1, 1).select(F.concat(F.col("id").cast("string"), F.expr("repeat('c:12 + ', 600000)")).alias("prov")).write.option("compression", "none").parquet(f"{tmp_path}/w")
    jvm, file = spark._jvm, next(tmp_path.glob("w/*.parquet"))
    parquet = jvm.org.apache.parquet.hadoop
    reader = parquet.ParquetFileReader.open(parquet.util.HadoopInputFile.fromPath(jvm.org.apache.hadoop.fs.Path(str(file)), spark._jsc.hadoopConfiguration()))
    column, rows, pages = reader.getFooter().getFileMetaData().getSchema().getColumns().get(0), [], []
    while (group := reader.readNextRowGroup()) is not None:
        rows.append(group.getRowCount())
        found = group.getPageReader(column)
        while (page := found.readPage()) is not None:
            pages.append(page.getValueCount())
    reader.close()
    assert pages == [1] * 24 and sum(rows) == 24 and max(rows) * 4.2 <= 40


def test_annotated_rows_take_less_disk_as_parquet(spark, tmp_path):
    """Rows that repeat a table-wide sum filled the disk; a session's own codec stays."""
    from polyprov.engine import Engine

    ours, own = spark.newSession(), spark.newSession()
    own.conf.set("spark.sql.parquet.compression.codec", "snappy")
    sizes = []
    for s, codec in ((ours, "zstd"), (own, "snappy")):
        Engine(s)
        rows = s.range(20_000).select(F.concat(F.lit("l:"), F.col("id") * 7 % 6007, F.lit(":"), F.col("id") * 11 % 2003, F.lit("⊗"), F.round(F.rand(1) * 1e5, 4)).alias("t"))
        rows.agg(F.expr("listagg(t, ' +sum ') WITHIN GROUP (ORDER BY t)").alias("prov")).write.parquet(f"{tmp_path}/{codec}")
        files = list((tmp_path / codec).glob("part-*.parquet"))
        assert all(f.name.endswith(f".{codec}.parquet") for f in files)
        sizes.append(sum(f.stat().st_size for f in files))
        assert s.read.parquet(f"{tmp_path}/{codec}").select(F.regexp_count("prov", F.lit("⊗")).alias("n")).first().n == 20_000
    assert sizes[0] < 0.7 * sizes[1], sizes


def test_no_annotations_are_held_until_a_parquet_file_ends(spark, tmp_path):
    """Two texts of megabytes a row group, as its statistics, filled the heap of a writer of many."""
    import pyarrow.parquet as pq
    from conftest import SF

    from polyprov.engine import Engine

    query = "SELECT s_name, count(*) AS n FROM supplier WHERE s_nationkey >= 0 GROUP BY s_name"
    for mode, texts in (("valued", {"prov", "n_agg"}), ("symbolic", {"prov", "n"})):
        Engine(spark).register_folder(SF).rewrite(query, mode=mode).write.parquet(f"{tmp_path}/{mode}")
        seen = 0
        for f in (tmp_path / mode).glob("part-*.parquet"):
            meta = pq.read_metadata(f)
            for g in range(meta.num_row_groups):
                columns = [meta.row_group(g).column(i) for i in range(meta.num_columns)]
                assert {c.path_in_schema for c in columns if c.statistics is None or not c.statistics.has_min_max} == texts
                seen += 1
        assert seen


def test_measured_lengths_are_those_of_the_texts(spark):
    from conftest import SF

    from polyprov.engine import Engine
    from polyprov.functions.algebra import measured
    from polyprov.workloads import tpch

    e = Engine(spark).register_folder(SF, tpch.TABLES)
    for n, mode in (("t1", "valued"), ("t2", "symbolic"), ("t8", "symbolic"), ("t13", "valued"), ("t15", "symbolic"), ("t18", "valued"), ("t22", "symbolic")):
        text = e.rewrite(tpch.text(n, SF), mode=mode)
        with measured():
            sizes = e.rewrite(tpch.text(n, SF), mode=mode)
        changed = [c for c in text.columns if (c in sizes.columns) and c == "prov" or dict(text.dtypes)[c] != dict(sizes.dtypes)[c] or c.endswith("_agg")]
        assert "prov" in changed and "listagg" not in _plan(sizes)
        want = text.select(*[c if c not in changed else F.length(c).cast("bigint").alias(c) for c in text.columns])
        assert sorted(map(str, sizes.collect())) == sorted(map(str, want.collect())), n


def test_sizes_are_measured_without_texts(spark, monkeypatch):
    """Texts of a table-wide sum in every row did not fit an executor."""
    from conftest import SF

    from polyprov import metrics
    from polyprov.workloads import catalogue

    seen = []
    total = metrics.total
    monkeypatch.setattr(metrics, "total", lambda df, columns: seen.append(_plan(df)) or total(df, columns))
    assert len(catalogue.queries()["experiment_sizes_symbolic"](spark, SF).collect()) == len(seen) == 22
    assert not any("listagg" in p or "string_agg" in p for p in seen)


def test_equal_sums_are_equal_in_any_order_of_their_rows(spark):
    """A sum was added in the order of arrival, apart for each side of the equality: tied groups were lost."""
    from polyprov.engine import Engine
    from polyprov.sources.tokens import TokenPolicy

    e = Engine(spark)
    rows = [(k, i, v) for k, vs in (("a", (0.1, 0.2, 0.3)), ("b", (0.3, 0.2, 0.1)), ("c", (0.1,)), ("d", (None,))) for i, v in enumerate(vs)]
    e.register("sold", spark.createDataFrame(rows, "k string, i int, v double").coalesce(1), TokenPolicy("s", ("k", "i")))
    got = e.rewrite("WITH g AS (SELECT k, SUM(v) AS t FROM sold GROUP BY k) SELECT k, t FROM g WHERE t = (SELECT MAX(t) FROM g)").collect()
    assert sorted(r.k for r in got) == ["a", "b"] and len({r.t for r in got}) == 1
    assert all(r.t_agg == f"s:{r.k}.0⊗{x} +sum s:{r.k}.1⊗0.2000 +sum s:{r.k}.2⊗{y}" for r, x, y in zip(sorted(got), ("0.1000", "0.3000"), ("0.3000", "0.1000")))


def test_symbolic_equality_with_a_scalar_takes_its_row_beside_each(spark):
    from conftest import SF

    from polyprov.engine import Engine
    from polyprov.workloads import tpch

    df = Engine(spark).register_folder(SF, tpch.TABLES).rewrite(tpch.text("t15", SF), mode="symbolic")
    assert "CartesianProduct" in _plan(df) and df.rdd.getNumPartitions() > 1


def test_lists_are_resolved_as_they_are_aggregated(spark):
    """The validator listed a group's addends in one text, which can pass what a row holds."""
    from conftest import SF

    from polyprov.engine import Engine
    from polyprov.functions import evaluate as ev
    from polyprov.functions.algebra import folded
    from polyprov.workloads import tpch

    e = Engine(spark).register_folder(SF, tpch.TABLES)
    for n, mode, sums in (("t1", "symbolic", ("sum_qty", "avg_disc", "n")), ("t13", "symbolic", ("custdist",)), ("t11", "valued", ("value_agg",)), ("t17", "symbolic", ("avg_yearly",)), ("t22", "symbolic", ("numcust", "totacctbal"))):
        text = e.rewrite(tpch.text(n, SF), mode=mode)
        with folded():
            short = e.rewrite(tpch.text(n, SF), mode=mode)
        assert "listagg" in _plan(text) and "listagg" not in _plan(short)
        keys = [c for c in text.columns if c not in (*sums, "prov")]

        def read(df):
            rows = [(*[str(r[c]) for c in keys if c != "value"], ev.evaluate(r.prov), *[ev.evaluate_value(r[c]) for c in sums]) for r in df.collect() if ev.evaluate(r.prov)]
            return sorted(tuple(round(float(x), 6) if hasattr(x, "is_finite") else x for x in r) for r in rows)

        assert read(short) == read(text), n


def test_folded_annotations_have_the_multiplicity_of_their_list(spark):
    from polyprov.functions.evaluate import evaluate
    from polyprov.functions.udfs import folded_annotations

    rows = [(k, p) for k, n in (("a", 1), ("b", 6), ("c", 37)) for p in ["t:1"] * n] + [("d", "0"), ("d", "t:0 · 0"), ("e", "δ(t:1 + t:2)"), ("e", "(t:1 + t:2) · t:3"), ("f", None), ("f", "[t:1⊗2 > 1⊗3]")]
    got = spark.createDataFrame(rows, "k string, p string").groupBy("k").agg(folded_annotations("p").alias("p")).collect()
    assert {r.k: evaluate(r.p) for r in got} == {"a": 1, "b": 6, "c": 37, "d": 0, "e": 3, "f": 0}


def test_monomials_outside_of_all_witnesses_are_counted(spark):
    from polyprov.validate import _outside

    rows = [("x", "a:1 b:1", 3), ("x", "a:2", 1), ("x", "a:2 b:2", 2), ("x", "a:3", 1), ("x", "a:4 b:4", 2), ("y", "a:1", 1), ("y", "a:9", 3)]
    both = spark.createDataFrame(rows, "key string, m string, side int")
    assert (_outside(both, 1, 2), _outside(both, 2, 1)) == (2, 1)


def test_witnesses_of_an_uncorrelated_scalar_do_not_multiply_rows(spark):
    """Every outer row was paired with every inner row, though these witnesses are left out."""
    from conftest import SF

    from polyprov.baselines import WitnessAnnotator
    from polyprov.engine import Engine
    from polyprov.workloads import tpch

    e = Engine(spark).register_folder(SF, tpch.TABLES)
    w = WitnessAnnotator(e.policy, "token")
    w.lone = False
    df = w.result(e.plain(tpch.text("t22", SF)), uncorrelated=False)
    assert df.count() == df.distinct().count() == e.plain(tpch.text("t22", SF)).agg(F.sum("numcust")).first()[0]
