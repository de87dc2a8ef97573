"""The experiments' harness over a few queries and two folders."""

from polyprov.workloads import experiments as ex


def test_harness_gives_its_tables(spark):
    from polyprov.engine import Engine
    from polyprov.workloads import tpch

    found = []
    for sf in ("0.001", "0.01"):
        folder = f"/root/testdata/sf{sf}"
        found.append(ex.measure(Engine(spark).register_folder(folder, tpch.TABLES), folder, ("t4", "t6"), runs=1, limit=60))
    s = ex.summary(found[1])
    assert s["executed"] == {"method": 2, "symbolic": 2, "full witness": 2, "token witness": 1, "function circuit": 1}
    assert s["failures"] == {"token witness": {"t4": "unsupported"}, "function circuit": {"t4": "unsupported"}}
    assert sum(s["fastest"].values()) == 2 and sum(s["smallest"].values()) == 2
    assert s["size_kb"]["method"]["t4"] > 0 and s["plans"]["t6"]["ArrowEvalPython"] == 0
    small, large = (f.characters["method"]["t6"] for f in found)
    assert 5 < large / small < 20
    assert set(ex.growth(*found)["times"]) == {"plain", *ex.SYSTEMS}


def test_symbolic_sizes_are_measured_whatever_the_folder_is_called(spark, tmp_path, monkeypatch):
    """From sf0.1 on, symbolic texts of three queries were reported as too long without a run."""
    from polyprov.engine import Engine
    from polyprov.workloads import tpch

    given, large, names = "/root/testdata/sf0.001", tmp_path / "sf0.1", ("t11", "t15", "t22")
    large.mkdir()
    for t in tpch.TABLES:
        (large / f"{t}.parquet").symlink_to(f"{given}/{t}.parquet")
    monkeypatch.setattr(ex, "SYSTEMS", ("symbolic",))
    small, named = (ex.measure(Engine(spark).register_folder(f, tpch.TABLES), f, names, runs=1, limit=60) for f in (given, str(large)))
    assert named.failures == {} and set(named.seconds["symbolic"]) == set(names)
    assert named.characters == small.characters and named.characters["symbolic"]["t15"] > 0
