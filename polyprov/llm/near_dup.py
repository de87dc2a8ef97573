"""MinHash near-dedup (8): a chosen-path set similarity join.

Texts become sets of five-word shingles; rows with equal sets are taken together
first.  Each remaining set has ``POSITIONS`` minwise tokens.  In each of
``trees`` independent trees, a node of documents picks one or two positions (4/3
on average, the inverse of the similarity sought) by a hash of its own path, and
its documents branch by their tokens there.  Nodes of up to ``leaf`` documents
are compared exhaustively: first by one byte of each minwise token, which leaves
groups of likely partners, then on the full sets.  Inside a group, documents that
are already tied need no comparison, so a group of n copies costs about n
comparisons and gives n - 1 links.  Larger nodes branch again; what is still
large at ``levels`` is compared whole, in blocks of ``BLOCK_ROWS`` that are dealt over
tasks: first each block in itself, going on from the members tied last, so that a
hub ties all of its own in one pass; then each pair of blocks, but for members that
are tied by then.  A task holds two blocks' sketches (some 150 bytes a row) and reads
full sets from mapped files.

With similarity 0.75 a pair meets in a tree with probability 0.81 (leaves of
the first level) to 0.53 (of the fourth), so eight trees miss at most 0.3 % of such
links, and next to none in small nodes.

A link is confirmed on full sets: 100 * intersection >= 75 * union, on 64-bit
shingle hashes.  Texts of fewer than five words are one shingle; null or empty
texts have no shingle and link with nothing.  Rows of one doc_id count as one
document; a null doc_id links with nothing, its component is null and it is
kept.  An empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import hashlib
import io
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polyprov.llm.common import Shared, by_ids, cut, drop_folder, fresh_folder, mix64, shingle_sets, text_steps
from polyprov.llm.components import components

POSITIONS = 128
TREES = 8
LEAF = 1000
LEVELS = 4
SEED = 5

#: Equal sketch bytes of 128 that a pair needs to be looked at in full: a pair
#: of similarity 0.75 has 96 on average, with a standard deviation of 4.9.
SKETCH_LEAST = 75

_draw = np.random.default_rng(20240817)
_A = _draw.integers(0, 1 << 32, POSITIONS, dtype=np.uint32) | np.uint32(1)
_B = _draw.integers(0, 1 << 32, POSITIONS, dtype=np.uint32) | np.uint32(1)


def minwise(s: np.ndarray) -> np.ndarray:
    """The minwise tokens (uint32) of a set of 64-bit hashes."""
    best = np.full(POSITIONS, 0xFFFFFFFF, np.uint32)
    for i in range(0, len(s), 1024):
        part = s[i : i + 1024]
        low, high = part.astype(np.uint32), (part >> np.uint64(32)).astype(np.uint32)
        np.minimum(best, (low[:, None] * _A + high[:, None] * _B).min(axis=0), out=best)
    return best


def _sets(column: pa.Array) -> Iterator[np.ndarray]:
    for _, data, offsets in text_steps(column):
        yield from shingle_sets(data, offsets)


def _digest(s: np.ndarray) -> tuple[int, int]:
    d = hashlib.blake2b(s.tobytes(), digest_size=16).digest()
    return int.from_bytes(d[:8], "little", signed=True), int.from_bytes(d[8:], "little", signed=True)


def _sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sizes, prints, sigs, sketches = [], [], [], []
        for s in _sets(batch.column(1)):
            sizes.append(len(s))
            prints.append(_digest(s))
            m = minwise(s)
            sigs.append(m.tobytes())
            sketches.append(m.astype(np.uint8).tobytes())
        yield pa.RecordBatch.from_arrays(
            [batch.column(0), pa.array(sizes, pa.int64()), pa.array([p[0] for p in prints], pa.int64()), pa.array([p[1] for p in prints], pa.int64()), pa.array(sigs, pa.binary()), pa.array(sketches, pa.binary())],
            ["doc_id", "n_shingles", "fp1", "fp2", "sig", "sketch"],
        )


def _children(nodes: np.ndarray, sigs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(index of the member, key of the child) for members of nodes."""
    h = mix64(nodes ^ np.uint64(0x5851F42D4C957F2D))
    first = (h & np.uint64(0xFFFF)).astype(np.int64) % POSITIONS
    second = (first + 1 + ((h >> np.uint64(16)) & np.uint64(0xFFFF)).astype(np.int64) % (POSITIONS - 1)) % POSITIONS
    twice = ((h >> np.uint64(32)) % np.uint64(3)) == 0
    index = np.concatenate([np.arange(len(nodes)), np.flatnonzero(twice)])
    position = np.concatenate([first, second[twice]])
    token = sigs[index, position].astype(np.uint64) | (position.astype(np.uint64) << np.uint64(32))
    return index, mix64(mix64(token) + nodes[index] * np.uint64(0x9E3779B97F4A7C15))


def _matrix(column: pa.Array, dtype, width: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), dtype).reshape(-1, width)


def _grow(trees: int, seed: int):
    roots = mix64(np.arange(1, trees + 1, dtype=np.uint64) * np.uint64(0xD1342543DE82EF95) + np.uint64(seed))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            sigs, rows = _matrix(batch.column(1), np.uint32, POSITIONS), batch.column(0).to_numpy(zero_copy_only=False)
            with np.errstate(over="ignore"):
                if batch.num_columns == 3:
                    starts = [batch.column(2).to_numpy(zero_copy_only=False).view(np.uint64)]
                else:
                    starts = [np.full(len(rows), r, np.uint64) for r in roots]
                for nodes in starts:
                    index, keys = _children(nodes, sigs)
                    yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(rows[index])], ["key", "row"])

    return run


def _by_key(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """Runs of whole keys (column 0 sorted); what is held is a batch and a key."""
    held = None
    for batch in batches:
        if batch.num_rows == 0:
            continue
        part = pa.Table.from_batches([batch])
        part = part if held is None else pa.concat_tables([held, part])
        keys = part.column(0).to_numpy()
        last = int(np.searchsorted(keys, keys[-1], side="left"))
        if last:
            yield part.slice(0, last)
        held = part.slice(last)
    if held is not None and held.num_rows:
        yield held


def _bounds(keys: np.ndarray) -> np.ndarray:
    return np.concatenate([[0], np.flatnonzero(keys[1:] != keys[:-1]) + 1, [len(keys)]])


def _likely(sizes: np.ndarray, sketches: np.ndarray) -> list[np.ndarray]:
    """Groups of members that chains of likely partners tie together."""
    left, groups = np.arange(len(sizes)), []
    while len(left):
        group, reach = [left[:1]], left[:1]
        left = left[1:]
        while len(reach) and len(left):
            i, reach = reach[0], reach[1:]
            fit = (4 * np.minimum(sizes[i], sizes[left]) >= 3 * np.maximum(sizes[i], sizes[left])) & ((sketches[left] == sketches[i]).sum(axis=1) >= SKETCH_LEAST)
            if fit.any():
                group.append(left[fit])
                reach = np.concatenate([reach, left[fit]])
                left = left[~fit]
        whole = np.concatenate(group)
        if len(whole) > 1:
            groups.append(np.sort(whole))
    return groups


def _group(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Nodes (key, row, n_shingles, sketch) to groups (gid, rows)."""
    for part in _by_key(batches):
        keys, rows, sizes = (part.column(i).to_numpy() for i in range(3))
        sketches = _matrix(part.column(3), np.uint8, POSITIONS)
        at = _bounds(keys)
        out = []
        pairs = at[:-1][np.diff(at) == 2]
        fit = (4 * np.minimum(sizes[pairs], sizes[pairs + 1]) >= 3 * np.maximum(sizes[pairs], sizes[pairs + 1])) & ((sketches[pairs] == sketches[pairs + 1]).sum(axis=1) >= SKETCH_LEAST)
        out += [np.sort(rows[i : i + 2]) for i in pairs[fit]]
        for a, b in zip(at[:-1], at[1:], strict=True):
            if b - a > 2:
                out += [np.sort(rows[a:b][g]) for g in _likely(sizes[a:b], sketches[a:b])]
        ids = [int.from_bytes(hashlib.blake2b(g.tobytes(), digest_size=8).digest(), "little", signed=True) for g in out]
        yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array([g.tolist() for g in out], pa.list_(pa.int64()))], ["gid", "rows"])


def _common(pivot: np.ndarray, others: list[np.ndarray]) -> np.ndarray:
    whole = np.concatenate(others)
    at = np.minimum(np.searchsorted(pivot, whole), len(pivot) - 1)
    ends = np.cumsum([len(o) for o in others])
    total = np.concatenate([[0], np.cumsum(pivot[at] == whole)])
    return total[ends] - total[ends - [len(o) for o in others]]


def _confirm(similarity: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Groups (gid, doc_id, set) to links that tie all that belong together."""
        for part in _by_key(batches):
            keys, ids = part.column(0).to_numpy(), part.column(1).to_numpy()
            at, a, b = _bounds(keys), [], []
            for lo, hi in zip(at[:-1], at[1:], strict=True):
                sets = [np.frombuffer(x, np.uint64) for x in part.column(2).slice(lo, hi - lo).to_pylist()]
                sizes = np.array([len(s) for s in sets])
                tie = np.arange(hi - lo)
                for i in range(hi - lo - 1):
                    to = i + 1 + np.flatnonzero((tie[i + 1 :] != tie[i]) & (100 * np.minimum(sizes[i], sizes[i + 1 :]) >= similarity * np.maximum(sizes[i], sizes[i + 1 :])))
                    for k in range(0, len(to), 64):
                        js = to[k : k + 64]
                        js = js[tie[js] != tie[i]]
                        if not len(js):
                            continue
                        both = _common(sets[i], [sets[j] for j in js])
                        for j in js[100 * both >= similarity * (sizes[i] + sizes[js] - both)]:
                            if tie[j] != tie[i]:
                                a.append(ids[lo + i])
                                b.append(ids[lo + j])
                                tie[tie == tie[j]] = tie[i]
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    return run


def _leaves(reps: DataFrame, trees: int, leaf: int, levels: int, seed: int) -> tuple[DataFrame, DataFrame | None]:
    """(key, row) of the nodes of two rows up to ``leaf``, and of those still larger at the last level."""
    keys = reps.select("row", "sig").mapInArrow(_grow(trees, seed), "key long, row long")
    done, rest = [], None
    for level in range(1, levels + 1):
        keys = cut(keys)
        sizes = keys.groupBy("key").agg(F.count("*").alias("n")).where("n > 1")
        members = cut(keys.join(sizes, "key"))
        done.append(members.where(F.col("n") <= leaf).select("key", "row"))
        large = members.where(F.col("n") > leaf)
        if large.isEmpty():
            break
        if level < levels:
            keys = large.select("row", "key").join(reps.select("row", "sig"), "row").select("row", "sig", "key").mapInArrow(_grow(trees, seed), "key long, row long")
        else:
            rest = large.select("key", "row", "n").distinct()
    out = done[0]
    for d in done[1:]:
        out = out.union(d)
    return out, rest


#: Shingles of a file of sets, sketches compared at once, and files a task keeps mapped.
SET_FILE = 1 << 22
SKETCH_STEP = 1 << 16
MAPPED_FILES = 256
#: Rows of a block of a large node, and tasks for pairs of blocks at most.
BLOCK_ROWS = 4096
MOST_TASKS = 20_000


def _store(uri: str):
    """Texts to files of sets, and where each lies."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sets, held = [], 0

        def flush(sets):
            name = f"sets-{uuid.uuid4().hex}"
            Shared(uri).write(name, b"".join(s.tobytes() for s in sets))
            prints, starts = [_digest(s) for s in sets], np.cumsum([0] + [len(s) for s in sets])[:-1]
            return pa.RecordBatch.from_arrays([pa.array([p[0] for p in prints], pa.int64()), pa.array([p[1] for p in prints], pa.int64()), pa.array([name] * len(sets), pa.string()), pa.array(starts, pa.int64())], ["fp1", "fp2", "file", "start"])

        for batch in batches:
            for s in _sets(batch.column(1)):
                sets.append(s)
                held += len(s)
                if held > SET_FILE:
                    yield flush(sets)
                    sets, held = [], 0
        if sets:
            yield flush(sets)

    return run


def _tied(sizes: np.ndarray, sketches: np.ndarray, sets: Callable[[int], np.ndarray], similarity: int) -> Iterator[tuple[int, np.ndarray]]:
    """(member, members it ties) until all that belong together are tied."""
    left = np.arange(len(sizes))
    while len(left) > 1:
        reach, left = [int(left[0])], left[1:]
        while reach and len(left):
            i = reach.pop()
            near = []
            for k in range(0, len(left), SKETCH_STEP):
                part = left[k : k + SKETCH_STEP]
                fit = (100 * np.minimum(sizes[i], sizes[part]) >= similarity * np.maximum(sizes[i], sizes[part])) & (np.count_nonzero(sketches[part] == sketches[i], axis=1) >= SKETCH_LEAST)
                near.append(k + np.flatnonzero(fit))
            near, hits = np.concatenate(near), []
            for k in range(0, len(near), 64):
                js = near[k : k + 64]
                both = _common(sets(i), [sets(j) for j in left[js]])
                hits.append(js[100 * both >= similarity * (sizes[i] + sizes[left[js]] - both)])
            hit = np.concatenate(hits) if hits else near
            if len(hit):
                yield i, left[hit]
                reach += left[hit].tolist()
                left = np.delete(left, hit)


class _Sets:
    """Full sets of a block's members, from mapped files."""

    def __init__(self, shared: Shared):
        self.shared, self.maps = shared, {}

    def of(self, names: np.ndarray, which: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> Callable[[int], np.ndarray]:
        def one(i: int) -> np.ndarray:
            name = str(names[which[i]])
            if name not in self.maps:
                if len(self.maps) >= MAPPED_FILES:
                    self.maps.clear()
                self.maps[name] = np.asarray(self.shared.mapped(name, np.uint64))
            return self.maps[name][starts[i] : starts[i] + sizes[i]]

        return one


def _within_blocks(uri: str, similarity: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Blocks (part, key, block, doc_id, n_shingles, sketch, file, start) to links inside
        them, and a row (key, block) for each, which is left in the shared folder."""
        shared = Shared(uri)
        sets = _Sets(shared)
        for part in _by_key(batches):
            parts, keys, blocks, ids, sizes, starts = (part.column(i).to_numpy() for i in (0, 1, 2, 3, 4, 7))
            sketches, files = _matrix(part.column(5), np.uint8, POSITIONS), np.array(part.column(6).to_pylist())
            at = _bounds(parts)
            for lo, hi in zip(at[:-1], at[1:], strict=True):
                names, which = np.unique(files[lo:hi], return_inverse=True)
                label, a, b = np.arange(hi - lo), [], []
                for i, js in _tied(sizes[lo:hi], sketches[lo:hi], sets.of(names, which, starts[lo:hi], sizes[lo:hi]), similarity):
                    label[js] = label[i]
                    a.append(np.full(len(js), ids[lo + i]))
                    b.append(ids[lo:hi][js])
                held = io.BytesIO()
                np.savez(held, ids=ids[lo:hi], sizes=sizes[lo:hi], starts=starts[lo:hi], sketches=sketches[lo:hi], names=names, which=which, label=label)
                shared.write(f"block-{keys[lo]}-{blocks[lo]}", held.getvalue())
                n = sum(map(len, a))
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.concatenate([*a, [0]]).astype(np.int64)), pa.array(np.concatenate([*b, [0]]).astype(np.int64)), pa.array([None] * n + [int(keys[lo])], pa.int64()), pa.array([None] * n + [int(blocks[lo])], pa.int64())],
                    ["a", "b", "key", "block"],
                )
        shared.close()

    return run


def _between_blocks(uri: str, similarity: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Pairs of blocks (key, i, j) to links that tie what belongs together."""
        shared = Shared(uri)
        sets = _Sets(shared)
        for batch in batches:
            for key, i, j in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                with np.load(shared.path(f"block-{key}-{i}")) as x, np.load(shared.path(f"block-{key}-{j}")) as y:
                    one, two = ({k: z[k] for k in z.files} for z in (x, y))
                of_one, of_two = (sets.of(z["names"], z["which"], z["starts"], z["sizes"]) for z in (one, two))
                # Groups of the first block, then those of the second.
                mine, other, a, b = one["label"], two["label"] + len(one["label"]), [], []
                for p in range(len(mine)):
                    near = np.flatnonzero((other != mine[p]) & (100 * np.minimum(one["sizes"][p], two["sizes"]) >= similarity * np.maximum(one["sizes"][p], two["sizes"])))
                    near = near[np.count_nonzero(two["sketches"][near] == one["sketches"][p], axis=1) >= SKETCH_LEAST]
                    for k in range(0, len(near), 64):
                        qs = near[k : k + 64]
                        qs = qs[other[qs] != mine[p]]
                        if not len(qs):
                            continue
                        both = _common(of_one(p), [of_two(q) for q in qs])
                        for q in qs[100 * both >= similarity * (one["sizes"][p] + two["sizes"][qs] - both)]:
                            if other[q] != mine[p]:
                                a.append(one["ids"][p])
                                b.append(two["ids"][q])
                                old, new = other[q], mine[p]
                                mine[mine == old], other[other == old] = new, new
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])
        shared.close()

    return run


def _large_links(docs: DataFrame, reps: DataFrame, large: DataFrame, similarity: int, block_rows: int) -> DataFrame:
    """(a, b) doc_ids: confirmed links inside nodes of any size."""
    spark = docs.sparkSession
    uri = fresh_folder(spark, "near-sets")
    rows = cut(large.select("row").distinct().join(reps.select("row", "doc_id", "n_shingles", "fp1", "fp2", "sketch"), "row"))
    wanted = cut(rows.select("doc_id").distinct())
    stored = cut(by_ids(docs.select("doc_id", "text"), wanted, "left_semi").mapInArrow(_store(uri), "fp1 long, fp2 long, file string, start long"))
    places = stored.groupBy("fp1", "fp2").agg(F.min(F.struct("file", "start")).alias("at"))
    placed = rows.join(places, ["fp1", "fp2"]).select("row", "doc_id", "n_shingles", "sketch", "at.file", "at.start")
    block = F.pmod(F.xxhash64("row"), F.ceil(F.col("n") / block_rows))
    dealt = large.withColumn("block", block).withColumn("part", F.xxhash64("key", "block")).join(placed, "row").select("part", "key", "block", "doc_id", "n_shingles", "sketch", "file", "start")
    first = cut(dealt.repartition("part").sortWithinPartitions("part", "doc_id").mapInArrow(_within_blocks(uri, similarity), "a long, b long, key long, block long"))
    blocks = first.where("key is not null").select("key", "block")
    pairs = blocks.where("block > 0").select("key", F.col("block").alias("j"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("block") - 1)).alias("i"))
    jobs = cut(pairs.join(blocks.withColumnRenamed("block", "i"), ["key", "i"]).select("key", "i", "j"))
    out = first.where("key is null").select("a", "b")
    n = jobs.count()
    if n:
        out = out.union(cut(jobs.repartition(min(n, MOST_TASKS)).mapInArrow(_between_blocks(uri, similarity), "a long, b long")))
    drop_folder(spark, uri)
    return out


def links(docs: DataFrame, base: DataFrame, trees: int = TREES, leaf: int = LEAF, levels: int = LEVELS, similarity: int = 75, seed: int = SEED, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """(a, b) doc_ids: confirmed links that tie every group of near copies."""
    firsts = base.where("n_shingles > 0 and doc_id is not null").groupBy("fp1", "fp2").agg(F.min_by("row", "doc_id").alias("row"))
    reps = cut(base.join(firsts.select("row"), "row").select("row", "doc_id", "n_shingles", "fp1", "fp2", "sig", "sketch"))
    small, large = _leaves(reps, trees, leaf, levels, seed)
    nodes = small.join(reps.select("row", "n_shingles", "sketch"), "row")
    groups = (
        nodes.select("key", "row", "n_shingles", "sketch").repartition("key").sortWithinPartitions("key").mapInArrow(_group, "gid long, rows array<long>")
        .groupBy("gid").agg(F.first("rows").alias("rows"))
    )
    members = cut(groups.select("gid", F.explode("rows").alias("row")).join(reps.select("row", "doc_id", "fp1", "fp2"), "row"))
    wanted = cut(members.select("doc_id").distinct())
    sets = by_ids(docs.select("doc_id", "text"), wanted, "left_semi").mapInArrow(_with_sets, "fp1 long, fp2 long, shingles binary").groupBy("fp1", "fp2").agg(F.first("shingles").alias("shingles"))
    confirmed = (
        members.join(sets, ["fp1", "fp2"]).select("gid", "doc_id", "shingles").repartition("gid").sortWithinPartitions("gid", "doc_id")
        .mapInArrow(_confirm(similarity), "a long, b long")
    )
    return confirmed if large is None else confirmed.union(_large_links(docs, reps, large, similarity, block_rows))


def _with_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        sets, held = [], 0

        def flush(sets):
            prints = [_digest(s) for s in sets]
            return pa.RecordBatch.from_arrays([pa.array([p[0] for p in prints], pa.int64()), pa.array([p[1] for p in prints], pa.int64()), pa.array([s.tobytes() for s in sets], pa.binary())], ["fp1", "fp2", "shingles"])

        for s in _sets(batch.column(1)):
            sets.append(s)
            held += len(s)
            if held > 1 << 20:
                yield flush(sets)
                sets, held = [], 0
        yield flush(sets)


def near_duplicates(docs: DataFrame, trees: int = TREES, leaf: int = LEAF, levels: int = LEVELS, similarity: int = 75, seed: int = SEED, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """doc_id, n_shingles, component_id, kept of each row.

    The filters before the confirmation are made for a ``similarity`` of 75 %;
    a lower one is refused, as pairs would be lost.
    """
    if similarity < 75:
        raise ValueError("the similarity is 75 or more")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    base = cut(docs.mapInArrow(_sign, "doc_id long, n_shingles long, fp1 long, fp2 long, sig binary, sketch binary").withColumn("row", F.monotonically_increasing_id()))
    confirmed = links(docs, base, trees, leaf, levels, similarity, seed, block_rows)
    slim = base.select("doc_id", "n_shingles", "fp1", "fp2", "row")
    twins = slim.where("n_shingles > 0 and doc_id is not null")
    firsts = twins.groupBy("fp1", "fp2").agg(F.min("doc_id").alias("first"), F.max("doc_id").alias("last")).where("first < last").select("fp1", "fp2", "first")
    copies = twins.join(firsts, ["fp1", "fp2"]).select(F.col("doc_id").alias("a"), F.col("first").alias("b"))
    tied = components(confirmed.union(copies))
    return (
        slim.join(tied, F.col("doc_id") == F.col("node"), "left")
        .withColumn("component_id", F.coalesce("component", "doc_id"))
        .select("doc_id", "n_shingles", "component_id", F.coalesce(F.col("doc_id") == F.col("component_id"), F.lit(True)).alias("kept"))
    )


def one_of_each(docs: DataFrame, **options) -> DataFrame:
    """The rows, with all their columns, of one document of each group of copies.

    The smallest doc_id of a group stays, as one row even if its id repeats;
    rows with a null doc_id stay.
    """
    judged = cut(near_duplicates(docs, **options).select("doc_id", "kept"))
    rows = by_ids(docs, cut(judged.where("not kept").select("doc_id").distinct()), "left_anti")
    repeated = judged.where("kept and doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1").select("doc_id")
    if repeated.isEmpty():
        return rows
    return rows.join(repeated, "doc_id", "left_anti").select(docs.columns).union(rows.join(repeated, "doc_id", "left_semi").select(docs.columns).dropDuplicates(["doc_id"]))
