"""The experiments: every system over every query, at one size or several.

``python -m polyprov.workloads.experiments FOLDER [FOLDER ...] [--runs 3] [--limit 600]``
prints a JSON line per folder: for each system the queries that ran, failures by
class, wins by time and by size, average overheads of time and size per group of
queries and per mode, what the plans exchange and join; and a last line with the
growth of times and sizes per group between folders.  Every query of every system is
run once untimed before.
"""

from __future__ import annotations

import json
import sys
from dataclasses import dataclass, field

from polyprov import metrics
from polyprov.engine import Engine
from polyprov.workloads import tpch

SYSTEMS = ("method", "symbolic", *metrics.SYSTEMS[1:])


@dataclass
class Figures:
    """Seconds, characters and failures: system -> query -> figure."""

    seconds: dict[str, dict[str, float]] = field(default_factory=dict)
    characters: dict[str, dict[str, int]] = field(default_factory=dict)
    failures: dict[str, dict[str, str]] = field(default_factory=dict)
    plans: dict[str, dict[str, int]] = field(default_factory=dict)


def measure(engine: Engine, sf_dir: str, names=tuple(tpch.QUERIES), runs: int = 3, limit: float = 600.0) -> Figures:
    out = Figures()
    for system in ("plain", *SYSTEMS):
        for n in names:

            def make(system=system, n=n):
                if system == "symbolic":
                    return metrics.run_system(engine, "method", tpch.text(n, sf_dir), mode="symbolic")
                return metrics.run_system(engine, system, tpch.text(n, sf_dir))

            metrics.time_query(make, 1, limit)
            timing = metrics.time_query(make, runs, limit)
            if timing.failure is not None:
                out.failures.setdefault(system, {})[n] = timing.failure
                continue
            df = make()
            out.seconds.setdefault(system, {})[n] = timing.seconds
            out.characters.setdefault(system, {})[n] = metrics.size_of(df)
            if system == "method":
                out.plans[n] = metrics.plan_figures(df)
    return out


def summary(f: Figures) -> dict:
    """The tables of the experiments from the figures of one size."""
    others = [s for s in SYSTEMS if s != "symbolic"]

    def overheads(figures: dict[str, dict[str, float]]) -> dict:
        out = {}
        for s in SYSTEMS:
            per = {q: metrics.overhead(v, figures["plain"][q]) for q, v in figures.get(s, {}).items() if figures["plain"].get(q)}
            out[s] = {g: None if (x := metrics.group_average(per, names)) is None else round(x, 1) for g, names in tpch.GROUPS.items()}
            mode = [per[q] for q in tpch.MODE_GROUP if q in per]
            if s in ("method", "symbolic") and mode:
                out[s]["comparisons that ran"] = round(sum(mode) / len(mode), 1)
        return out

    return {
        "executed": {s: len(f.seconds.get(s, {})) for s in SYSTEMS},
        "failures": f.failures,
        "fastest": metrics.wins({s: f.seconds.get(s, {}) for s in others}),
        "smallest": metrics.wins({s: f.characters.get(s, {}) for s in others}),
        "time_overhead_pct": overheads(f.seconds),
        "size_overhead_pct": overheads(f.characters),
        "size_kb": {s: {q: round((c - f.characters["plain"][q]) / 1024, 1) for q, c in f.characters.get(s, {}).items()} for s in SYSTEMS},
        "plans": f.plans,
    }


def growth(small: Figures, large: Figures) -> dict:
    """Per system and group: the average of large / small, for times and sizes."""

    def ratios(a, b):
        return {s: {g: None if (x := metrics.group_average({q: b[s][q] / a[s][q] for q in a.get(s, {}) if a[s][q] and q in b.get(s, {})}, names)) is None else round(x, 2) for g, names in tpch.GROUPS.items()} for s in ("plain", *SYSTEMS)}

    return {"times": ratios(small.seconds, large.seconds), "sizes": ratios(small.characters, large.characters)}


def main(args: list[str]) -> None:
    from pyspark.sql import SparkSession

    options = {a: float(b) for a, b in zip(args, args[1:], strict=False) if a.startswith("--")}
    folders = [a for i, a in enumerate(args) if not a.startswith("--") and (i == 0 or not args[i - 1].startswith("--"))]
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("OFF")
    found = []
    for folder in folders:
        engine = Engine(spark).register_folder(folder, tpch.TABLES)
        found.append(measure(engine, folder, runs=int(options.get("--runs", 3)), limit=options.get("--limit", 600.0)))
        print(json.dumps({"folder": folder, **summary(found[-1])}), flush=True)
    print(json.dumps({"growth": [growth(a, b) for a, b in zip(found, found[1:], strict=False)]}))


if __name__ == "__main__":
    main(sys.argv[1:])
