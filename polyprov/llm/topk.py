"""Exact top-k search (6): ball trees with branch and bound, one per shard.

Components become floor(1024 * x).  Vectors are dealt into shards; a task builds
the ball tree of its shard once and runs all query blocks through it.  A block
walks the tree best first: the node with the highest inner-product bound,
q . centre + |q| * radius, comes next, with those queries whose bound reaches
their k-th score so far.  A pilot shard is searched first; its k-th scores are
put in the shared folder, and every other shard starts from them.

Scores are exact integers: in float64 while they fit 53 bits, else with whole
numbers of any size, held to the range of a long.  Ties go to the smaller
vec_id.  Vectors that are null or hold null or non-finite components, and rows
with a null vec_id, take no part; shorter vectors are continued by zeros; rows
that repeat a vec_id are candidates of their own, and each is a query.  An empty
table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from polyprov.llm.common import Shared, cut, fresh_folder
from polyprov.llm.vectors import matrix, packed, read_block, write_blocks

K = 10
EVERY = 100
SHARD_ROWS = 12_000
LEAF = 96
BLOCK = 256
NONE = np.iinfo(np.int64).min + 1


class BallTree:
    """Nodes as arrays: centre, radius, children or a range of the ordered rows."""

    def __init__(self, x: np.ndarray, leaf: int = LEAF):
        self.order = np.arange(len(x))
        self.centre, self.radius, self.kids, self.span = [], [], [], []
        todo = [(0, len(x), -1)]
        while todo:
            a, b, parent = todo.pop()
            rows = x[self.order[a:b]]
            c = rows.mean(axis=0)
            far = rows - c
            dist = np.sqrt((far * far).sum(axis=1))
            node = len(self.centre)
            self.centre.append(c)
            self.radius.append(dist.max())
            self.kids.append([])
            self.span.append((a, b))
            if parent >= 0:
                self.kids[parent].append(node)
            if b - a > leaf and dist.max() > 0:
                # Split between two far rows: the farthest from the centre, and the farthest from it.
                one = rows[dist.argmax()]
                two = rows[((rows - one) ** 2).sum(axis=1).argmax()]
                side = rows @ (two - one)
                half = (b - a) // 2
                self.order[a:b] = self.order[a:b][np.argpartition(side, half)]
                todo += [(a, a + half, node), (a + half, b, node)]
        self.centre, self.radius = np.array(self.centre), np.array(self.radius)


def _exact(q: np.ndarray, x: np.ndarray, small: bool) -> np.ndarray:
    if small:
        return (q @ x.T).astype(np.int64)
    whole = np.array([[int(c) for c in v] for v in q], object) @ np.array([[int(c) for c in v] for v in x], object).T
    return np.clip(whole, NONE + 1, np.iinfo(np.int64).max).astype(np.int64)


def search(x: np.ndarray, ids: np.ndarray, rows: np.ndarray, tree: BallTree, q: np.ndarray, q_rows: np.ndarray, floor: np.ndarray, k: int, small: bool) -> tuple[np.ndarray, np.ndarray]:
    """(scores, ids), each (queries, k): the best of this shard not below ``floor``.

    Places without a candidate have score ``NONE``.
    """
    best = np.full((len(q), k), NONE, np.int64)
    which = np.full((len(q), k), np.iinfo(np.int64).max, np.int64)
    norm = np.sqrt((q * q).sum(axis=1))
    kth = floor.astype(np.float64)
    scale = np.sqrt((tree.centre**2).sum(axis=1)) + tree.radius

    def bound(node: int, active: np.ndarray) -> np.ndarray:
        return q[active] @ tree.centre[node] + norm[active] * tree.radius[node] + 1 + 1e-9 * norm[active] * scale[node]

    everyone = np.arange(len(q))
    first = bound(0, everyone)
    heap = [(-first.max(), 0, everyone, first)]
    while heap:
        _, node, active, limit = heapq.heappop(heap)
        active = active[limit >= kth[active]]
        if not len(active):
            continue
        if tree.kids[node]:
            for kid in tree.kids[node]:
                limit = bound(kid, active)
                fit = limit >= kth[active]
                if fit.any():
                    heapq.heappush(heap, (-limit[fit].max(), kid, active[fit], limit[fit]))
            continue
        members = tree.order[slice(*tree.span[node])]
        for start in range(0, len(members), 4 * LEAF):
            part = members[start : start + 4 * LEAF]
            scores = _exact(q[active], x[part], small)
            scores[q_rows[active][:, None] == rows[part][None, :]] = NONE
            better = (scores >= kth[active][:, None]).any(axis=1)
            a = active[better]
            if not len(a):
                continue
            both = np.concatenate([best[a], scores[better]], axis=1)
            names = np.concatenate([which[a], np.broadcast_to(ids[part], (len(a), len(part)))], axis=1)
            order = np.lexsort((names, -both), axis=1)[:, :k]
            best[a] = np.take_along_axis(both, order, axis=1)
            which[a] = np.take_along_axis(names, order, axis=1)
            kth[a] = np.maximum(kth[a], best[a, -1].astype(np.float64))
    return best, which


def _floor(shared: Shared, name: str, n: int) -> np.ndarray:
    """The pilot's k-th scores; none where the pilot shard has no rows."""
    try:
        return np.asarray(shared.mapped(f"{name}.kth", np.float64))
    except FileNotFoundError:
        return np.full(n, float(NONE))


def _search_shard(uri: str, names: list[str], dims: int, k: int, small: bool, pilot: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = [b for b in batches if b.num_rows]
        if not held:
            return
        part = pa.Table.from_batches(held).combine_chunks()
        ids, rows = part.column(0).to_numpy(), part.column(1).to_numpy()
        x = matrix(part.column(2).combine_chunks(), dims)
        tree, shared = BallTree(x), Shared(uri)
        for name in names:
            q_rows, q = read_block(shared, name, dims)
            floor = np.full(len(q), float(NONE)) if pilot else _floor(shared, name, len(q))
            best, which = search(x, ids, rows, tree, q, q_rows, floor, k, small)
            if pilot:
                shared.write(f"{name}.kth", best[:, -1].astype(np.float64).tobytes())
            at, place = np.nonzero((best != NONE) & (best.astype(np.float64) >= floor[:, None]))
            yield pa.RecordBatch.from_arrays([pa.array(q_rows[at]), pa.array(which[at, place]), pa.array(best[at, place])], ["q", "vec_id", "score"])

    return run


def top_k(embeddings: DataFrame, k: int = K, every: int = EVERY, shard_rows: int = SHARD_ROWS, factor: float = 1024.0) -> DataFrame:
    """query_id, rank, vec_id, score: the k best candidates of each query row."""
    vectors = packed(embeddings, lambda v: np.floor(factor * v)).where("v is not null and vec_id is not null").select("vec_id", "row", "dims", "v")
    spark = embeddings.sparkSession

    def peaks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        top = max((float(np.abs(np.frombuffer(x, np.float64)).max(initial=0)) for b in batches for x in b.column(0).to_pylist()), default=0.0)
        yield pa.RecordBatch.from_arrays([pa.array([top])], ["top"])

    size = vectors.agg(F.count("*").alias("n"), F.max("dims").alias("dims")).first()
    n, dims = size["n"], size["dims"] or 0
    schema = "q long, vec_id long, score long"
    nothing = spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    if not n:
        return nothing
    dims = max(dims, 1)  # a table of empty vectors: all scores are 0
    top = vectors.select("v").mapInArrow(peaks, "top double").agg(F.max("top")).first()[0]
    small = top * top * dims < 2**53
    uri = fresh_folder(spark, "topk")
    names = [name for name, _ in write_blocks(vectors.where(F.col("vec_id") % every == 0), uri, dims, BLOCK)]
    shards = max(1, -(-n // shard_rows))
    lot = F.pmod(F.xxhash64("row"), F.lit(shards))
    if not names:
        return nothing
    found = cut(vectors.where(lot == 0).select("vec_id", "row", "v").repartition(1).mapInArrow(_search_shard(uri, names, dims, k, small, True), schema))
    if shards > 1:
        rest = vectors.where(lot != 0).select("vec_id", "row", "v").repartition(shards - 1, "row")
        found = found.union(rest.mapInArrow(_search_shard(uri, names, dims, k, small, False), schema))
    best = Window.partitionBy("q").orderBy(F.desc("score"), "vec_id")
    return (
        found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k)
        .join(vectors.where(F.col("vec_id") % every == 0).select(F.col("row").alias("q"), F.col("vec_id").alias("query_id")), "q")
        .select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
    )
