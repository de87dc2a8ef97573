"""Sharding (10): size-tiered compaction under a versioned manifest.

A store is a folder with ``data/`` (immutable Parquet shards) and
``manifest-<version>.json`` files.  An arrival is written as small shards, which
form a run; when ``fanout`` runs are of similar size (within 0.5 and 1.5 of their
mean), they are merged into one run of target-sized files.  Each change is one new
manifest, put in place by a rename that fails if that version exists: a reader
sees a whole version or the one before, and of two writers one commits anew on
top of the other.  Groups that are due together are merged side by side.  ``vacuum`` removes older versions and the shards that only they name.

Rows are kept as they are, repeated ones and nulls included, with all their
columns whatever their names; texts of any length stay whole.  Ties in size fall to
the older run.  A null doc_id belongs to a fixed arrival.  An empty table gives a store with a manifest and no shard, whose rows are none.
"""

from __future__ import annotations

import json
import uuid
from concurrent.futures import ThreadPoolExecutor
from dataclasses import asdict, dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from polyprov.llm.common import fresh_folder

TARGET_BYTES = 128 << 20
FANOUT = 4
#: Arrivals: 16 or more, of some 64 MB, and not so many that their commits take the time.
ARRIVALS = 16
ARRIVAL_BYTES = 64 << 20
MOST_ARRIVALS = 1024
#: Merges that run side by side, and commits tried against other writers.
MERGES_AT_ONCE = 8
COMMITS_TRIED = 20
SEED = 23


class VersionTaken(RuntimeError):
    """Another writer has committed this version."""


@dataclass(frozen=True)
class Run:
    """Shards written together: their files (relative to data/), bytes and merges so far."""

    id: int
    files: tuple[str, ...]
    bytes: int
    tier: int


@dataclass(frozen=True)
class Manifest:
    version: int
    next_run: int
    runs: tuple[Run, ...]

    def to_json(self) -> str:
        return json.dumps(asdict(self))

    @staticmethod
    def from_json(text: str) -> Manifest:
        x = json.loads(text)
        return Manifest(x["version"], x["next_run"], tuple(Run(r["id"], tuple(r["files"]), r["bytes"], r["tier"]) for r in x["runs"]))


def all_due(runs: tuple[Run, ...], fanout: int, target: int) -> list[tuple[Run, ...]]:
    """Groups of similarly sized runs (by size, then age) that are large enough to merge.

    A run belongs to one group; groups hold at most twice ``fanout`` runs.  Runs whose
    files have all reached the target size are left alone.
    """
    open_runs = sorted((r for r in runs if r.bytes < target * max(1, len(r.files))), key=lambda r: (r.bytes, r.id))
    groups: list[list[Run]] = []
    for r in open_runs:
        mean = sum(x.bytes for x in groups[-1]) / len(groups[-1]) if groups else 0
        if not groups or len(groups[-1]) >= 2 * fanout or not 0.5 * mean <= r.bytes <= 1.5 * mean:
            groups.append([])
        groups[-1].append(r)
    return [tuple(part) for g in groups for part in _halves(g, fanout) if len(part) >= fanout]


def _halves(group: list[Run], fanout: int) -> list[list[Run]]:
    """A full group as two of ``fanout`` each, so that merges have one size."""
    return [group[:fanout], group[fanout:]] if len(group) == 2 * fanout else [group]


def due(runs: tuple[Run, ...], fanout: int, target: int) -> tuple[Run, ...]:
    """The first group of ``all_due``."""
    groups = all_due(runs, fanout, target)
    return groups[0] if groups else ()


class Store:
    def __init__(self, spark: SparkSession, folder: str, target_bytes: int = TARGET_BYTES, fanout: int = FANOUT):
        self.spark, self.folder, self.target, self.fanout = spark, folder.rstrip("/"), target_bytes, fanout
        self.jvm, self.conf = spark._jvm, spark._jsc.hadoopConfiguration()
        self.root = self.jvm.org.apache.hadoop.fs.Path(self.folder)
        self.fs = self.root.getFileSystem(self.conf)
        # Local folders: without checksum files, which do not move together with what they check.
        self.plain = self.fs.getRawFileSystem() if self.fs.getClass().getSimpleName() == "LocalFileSystem" else self.fs

    # ------------------------------------------------------------ manifests

    def _path(self, name: str):
        return self.jvm.org.apache.hadoop.fs.Path(f"{self.folder}/{name}")

    def versions(self) -> list[int]:
        if not self.fs.exists(self.root):
            return []
        names = [s.getPath().getName() for s in self.fs.listStatus(self.root)]
        return sorted(int(n[9:-5]) for n in names if n.startswith("manifest-") and n.endswith(".json"))

    def manifest(self, version: int | None = None) -> Manifest:
        versions = self.versions()
        if version is None and not versions:
            return Manifest(0, 0, ())
        stream = self.plain.open(self._path(f"manifest-{versions[-1] if version is None else version:010d}.json"))
        try:
            return Manifest.from_json(bytes(self.jvm.org.apache.commons.io.IOUtils.toByteArray(stream)).decode())
        finally:
            stream.close()

    def commit(self, manifest: Manifest) -> Manifest:
        temp, final = self._path(f".{uuid.uuid4().hex}.tmp"), self._path(f"manifest-{manifest.version:010d}.json")
        out = self.plain.create(temp, False)
        out.write(bytearray(manifest.to_json().encode()))
        out.close()
        options = self.spark.sparkContext._gateway.new_array(getattr(self.jvm.org.apache.hadoop.fs, "Options$Rename"), 0)
        try:
            self.jvm.org.apache.hadoop.fs.FileContext.getFileContext(self.root.toUri(), self.conf).rename(temp, final, options)
        except Exception as e:
            self.fs.delete(temp, False)
            if "FileAlreadyExists" in str(e) or self.fs.exists(final):
                raise VersionTaken(manifest.version) from e
            raise
        return manifest

    # ------------------------------------------------------------ runs

    def _files(self, below: str) -> list[tuple[str, int]]:
        path = self._path(f"data/{below}")
        if not self.fs.exists(path):
            return []
        found = [(s.getPath().getName(), s.getLen()) for s in self.fs.listStatus(path)]
        return sorted((f"{below}/{n}", size) for n, size in found if n.endswith(".parquet"))

    def _added(self, folder: str, tier: int, gone: tuple[Run, ...] = ()) -> Manifest:
        """Commit a folder's shards in place of ``gone``; anew where another writer was first.

        Where that writer has removed one of ``gone``, the rows are merged already: the
        folder goes, and its version stands.
        """
        files = self._files(folder)
        for _ in range(COMMITS_TRIED):
            now = self.manifest()
            if not set(gone) <= set(now.runs):
                self.fs.delete(self._path(f"data/{folder}"), True)
                return now
            kept = tuple(r for r in now.runs if r not in gone)
            new = (Run(now.next_run, tuple(f for f, _ in files), sum(s for _, s in files), tier),) if files else ()
            try:
                return self.commit(Manifest(now.version + 1, now.next_run + 1, kept + new))
            except VersionTaken:
                continue
        self.fs.delete(self._path(f"data/{folder}"), True)
        raise VersionTaken(now.version + 1)

    def append(self, rows: DataFrame) -> Manifest:
        """One arrival: small shards as they come, no shuffle."""
        folder = f"run-{uuid.uuid4().hex}"
        rows.write.parquet(f"{self.folder}/data/{folder}")
        return self._added(folder, 0)

    def append_all(self, rows: DataFrame, arrival, n: int):
        """Several arrivals in one pass over ``rows``; yields a manifest after each."""
        column, load = f"_arrival_{uuid.uuid4().hex[:8]}", f"load-{uuid.uuid4().hex}"
        rows.withColumn(column, arrival).write.partitionBy(column).parquet(f"{self.folder}/data/{load}")
        for i in range(n):
            yield self._added(f"{load}/{column}={i}", 0)

    def compact(self, vacuum: bool = False) -> Manifest:
        """Merge until no group of runs is due; groups that are due together are merged at once.

        ``vacuum`` lets go of merged runs between the rounds.
        """
        while groups := all_due(self.manifest().runs, self.fanout, self.target):
            with ThreadPoolExecutor(MERGES_AT_ONCE) as pool:
                folders = list(pool.map(self._merge, groups))
            for group, folder in zip(groups, folders, strict=True):
                self._added(folder, 1 + max(r.tier for r in group), group)
            if vacuum:
                self.vacuum()
        return self.manifest()

    def _merge(self, group: tuple[Run, ...]) -> str:
        folder = f"run-{uuid.uuid4().hex}"
        files = max(1, round(sum(r.bytes for r in group) / self.target))
        self._rows(group).coalesce(files).write.parquet(f"{self.folder}/data/{folder}")
        return folder

    def _rows(self, runs) -> DataFrame:
        # The folders' column=value names tell of arrivals only: each file is read by its own path.
        return self.spark.read.option("recursiveFileLookup", "true").parquet(*[f"{self.folder}/data/{f}" for r in runs for f in r.files])

    def read(self, version: int | None = None) -> DataFrame | None:
        """Rows of a version; None where it has no shard."""
        runs = self.manifest(version).runs
        return self._rows(runs) if runs else None

    def vacuum(self) -> int:
        """Remove older manifests and the shards that only they name.

        Shards that no manifest names may belong to a write under way; they stay.
        """
        now, dropped = self.manifest(), set()
        for v in self.versions():
            if v < now.version:
                dropped |= {f for r in self.manifest(v).runs for f in r.files}
                self.fs.delete(self._path(f"manifest-{v:010d}.json"), False)
        dropped -= {f for r in now.runs for f in r.files}
        for f in sorted(dropped):
            self.fs.delete(self._path(f"data/{f}"), False)
        return len(dropped)


def arrivals(doc_id, n: int = ARRIVALS, seed: int = SEED):
    return F.pmod(F.xxhash64(F.lit(seed), doc_id), F.lit(n)).cast("int")


def arrivals_for(docs: DataFrame) -> int:
    """So many arrivals that one holds about ``ARRIVAL_BYTES``, as far as the plan knows the size."""
    known = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    # Spark's figure where it knows nothing is near the largest long.
    return max(ARRIVALS, min(MOST_ARRIVALS, known // ARRIVAL_BYTES)) if known < 1 << 60 else ARRIVALS


def compacted(docs: DataFrame, folder: str | None = None, n_arrivals: int | None = None, target_bytes: int = TARGET_BYTES, fanout: int = FANOUT) -> Store:
    """Append ``docs`` as ``n_arrivals`` arrivals, then merge what is due."""
    spark = docs.sparkSession
    store = Store(spark, folder or fresh_folder(spark, "shards"), target_bytes, fanout)
    n = n_arrivals or arrivals_for(docs)
    for _ in store.append_all(docs, arrivals(F.col("doc_id"), n), n):
        pass
    store.compact(vacuum=True)
    store.vacuum()
    return store


def placement(store: Store, docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, text_hash, shard, shard_bytes, version: a row per stored row."""
    version, rows = store.manifest().version, store.read()
    rows = docs.limit(0).withColumns({"_shard": F.lit(""), "_bytes": F.lit(0)}) if rows is None else rows.withColumns({"_shard": F.col("_metadata.file_name"), "_bytes": F.col("_metadata.file_size")})
    return rows.select("doc_id", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long").alias("n_bytes"), F.xxhash64("text").alias("text_hash"), F.col("_shard").alias("shard"), F.col("_bytes").cast("long").alias("shard_bytes"), F.lit(version).cast("long").alias("version"))
