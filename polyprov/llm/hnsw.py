"""Embedding near-dedup (7): navigable small-world graphs, one per shard.

Equal vectors are taken together first.  The others are dealt into shards as
large as ``SHARD_BYTES`` allows; one task builds the layered graph of its shard
and puts it in the shared folder, where search tasks map it.  A pair of shards
meets once: slices of the one's vectors run through the other's graph, and a link
counts for both ends; a shard's own vectors run through its own graph.  Insertion
and search work on many vectors at once: each step expands the best unexpanded
members of every beam.  A new vector keeps neighbours of which none is nearer to
another kept one than to itself, then fills up with the nearest, so that dense
groups stay tied to the rest and within themselves.

Where a vector's links fill its beam, its search goes on from every link (and
every vector within ``margin`` of one) until none is new, so no cap cuts a large
group.  Before a shard answers, an audit compares links with brute force, for
vectors of the shard and for some of the whole table, a vector's link to itself
left out: beam and margin are widened until the mean share found per vector
reaches ``RECALL`` (in the end the beam is the shard).  Links are confirmed by
cosine in double precision.  A search task sends a count per vector and, for
components, one tie per vector, however large a group is: it unites as links are
found and holds none.

Vectors that are null, zero or hold null or non-finite components link with
nothing, as do rows with a null vec_id (component null, kept); shorter vectors
are continued by zeros.  Rows that repeat a vec_id are vectors of their own that
share the component.  An empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polyprov.llm.common import Shared, cut, drop_folder, fresh_folder
from polyprov.llm.components import components
from polyprov.llm.vectors import matrix, packed, read_block, write_blocks

COSINE = 0.95
#: Bytes of a shard's vectors in double precision: what a task holds, with as much again for its graph and marks.
SHARD_BYTES = 48 << 20
#: Vectors of a search task, and marks (vectors met, by query) that a step keeps.
SLICE = 4096
MARKS = 1 << 24
WIDTH = 32
KEPT = 16
PRUNED = 20
BUILD_BEAM = 32
BEAM = 24
EXPANDED = 4
BLOCK = 512
AUDITED = 4096
AUDITED_LINKED = 256
RECALL = 0.99
LAYER_SHARE = 16
TINY = 256
SEED = 3
#: Single precision ranks; double decides.
SLACK = 1e-4

Report = Callable[[np.ndarray, np.ndarray], None]


def _dots(a: np.ndarray, i: np.ndarray, b: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Products of rows a[i] and b[j], in steps whose copies stay in the cache."""
    out, step = np.empty(len(i), a.dtype), min(len(i), 2048)
    one, two = np.empty((step, a.shape[1]), a.dtype), np.empty((step, a.shape[1]), b.dtype)
    for k in range(0, len(i), max(1, step)):
        n = min(step, len(i) - k)
        np.take(a, i[k : k + n], axis=0, out=one[:n], mode="clip")
        np.take(b, j[k : k + n], axis=0, out=two[:n], mode="clip")
        np.einsum("ad,ad->a", one[:n], two[:n], out=out[k : k + n])
    return out


class Marks:
    """Which (query, vector) pairs of a step were met: numbers given out in turn."""

    def __init__(self):
        self.slots, self.next = np.empty(0, np.int32), 1

    def begin(self, n: int) -> None:
        if len(self.slots) < n or self.next > 1 << 30:
            self.slots, self.next = np.zeros(max(n, len(self.slots)), np.int32), 1
        self.base = self.next

    def first(self, keys: np.ndarray) -> np.ndarray:
        """Places of the keys met for the first time, one for each."""
        places = np.flatnonzero(self.slots[keys] < self.base)
        keys = keys[places]
        numbers = np.arange(self.next, self.next + len(keys), dtype=np.int32)
        self.next += len(keys)
        self.slots[keys] = numbers
        return places[self.slots[keys] == numbers]


class Layer:
    """Graph over some rows: ``links`` holds up to ``WIDTH`` places, -1 unused."""

    def __init__(self, x: np.ndarray, marks: Marks, links: np.ndarray | None = None):
        self.x, self.marks = x, marks
        self.links = np.full((len(x), WIDTH), -1, np.int32) if links is None else links
        self.degree = np.zeros(len(x), np.int64)

    def connect(self, new: np.ndarray, candidates: np.ndarray, sims: np.ndarray) -> None:
        """Tie new rows to candidates (-1 unused), both ways."""
        chosen = select(self.x, candidates, sims, KEPT)
        self.links[new, :KEPT] = chosen
        self.degree[new] = (chosen >= 0).sum(axis=1)
        a, b = np.repeat(new, KEPT), chosen.ravel()
        a, b = a[b >= 0], b[b >= 0]
        strange = (self.links[b] != a[:, None]).all(axis=1)
        a, b = a[strange], b[strange]
        order = np.argsort(b, kind="stable")
        a, b = a[order], b[order]
        targets, start, count = np.unique(b, return_index=True, return_counts=True)
        total = self.degree[targets] + count
        fits = np.repeat(total <= WIDTH, count)
        place = self.degree[b] + np.arange(len(b)) - np.repeat(start, count)
        self.links[b[fits], place[fits]] = a[fits]
        self.degree[targets[total <= WIDTH]] = total[total <= WIDTH]
        # A full list is chosen anew, and leaves room for the next ones.
        full = np.flatnonzero(total > WIDTH)
        for i in range(0, len(full), 256):
            t, s, c = targets[full[i : i + 256]], start[full[i : i + 256]], count[full[i : i + 256]]
            more = np.full((len(t), int(c.max())), -1, np.int32)
            more[np.arange(more.shape[1])[None, :] < c[:, None]] = a[np.concatenate([np.arange(x, x + y) for x, y in zip(s, c, strict=True)])]
            whole = np.concatenate([self.links[t], more], axis=1)
            near = np.where(whole >= 0, np.matmul(self.x[np.maximum(whole, 0)], self.x[t][:, :, None])[:, :, 0], -np.inf)
            kept = select(self.x, whole, near, PRUNED)
            self.links[t, :PRUNED], self.links[t, PRUNED:] = kept, -1
            self.degree[t] = (kept >= 0).sum(axis=1)

    def search(self, q: np.ndarray, entry: np.ndarray, beam: int, limit: int, least: float | None = None, margin: float = 0.0, report: Report | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Beams (ids, sims) over the first ``limit`` rows; and, with ``least``, a
        report of all (query, row) pairs met with a similarity of at least that."""
        n = len(q)
        self.marks.begin(n * limit)
        ids = np.full((n, beam), -1, np.int32)
        sims = np.full((n, beam), -np.inf, np.float32)
        open_ = np.zeros((n, beam), bool)
        worst = np.full(n, -np.inf, np.float32)
        near_enough, found = [], np.zeros(n, np.int64)
        step = min(EXPANDED, beam)

        def met(at: np.ndarray, new: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            first = self.marks.first(at * limit + new)
            at, new = at[first], new[first]
            near = _dots(q, at, self.x, new)
            if least is not None:
                hit = near >= least
                if hit.any():
                    report(at[hit], new[hit])
                    found[:] += np.bincount(at[hit], minlength=n)
                hit = near >= least - margin
                if hit.any():
                    near_enough.append((at[hit], new[hit]))
            return at, new, near

        def take(rows: np.ndarray, new: np.ndarray) -> None:
            at, place = np.nonzero(new >= 0)
            at, new, near = met(rows[at], new[at, place].astype(np.int64))
            good = near > worst[at]
            at, new, near = at[good], new[good], near[good]
            if not len(at):
                return
            touched, start, count = np.unique(at, return_index=True, return_counts=True)
            width = int(count.max())
            line, place = np.repeat(np.arange(len(touched)), count), np.arange(len(at)) - np.repeat(start, count)
            sims_, ids_, open__ = np.full((len(touched), beam + width), -np.inf, np.float32), np.full((len(touched), beam + width), -1, np.int32), np.zeros((len(touched), beam + width), bool)
            sims_[:, :beam], ids_[:, :beam], open__[:, :beam] = sims[touched], ids[touched], open_[touched]
            sims_[line, beam + place], ids_[line, beam + place], open__[line, beam + place] = near, new, True
            best = np.argpartition(-sims_, beam - 1, axis=1)[:, :beam]
            sims[touched], ids[touched], open_[touched] = np.take_along_axis(sims_, best, axis=1), np.take_along_axis(ids_, best, axis=1), np.take_along_axis(open__, best, axis=1)
            worst[touched] = sims[touched].min(axis=1)

        rows = np.arange(n)
        take(rows, entry)
        while True:
            rows = rows[open_[rows].any(axis=1)]
            if not len(rows):
                break
            waiting = np.where(open_[rows], sims[rows], -np.inf)
            best = np.argpartition(-waiting, step - 1, axis=1)[:, :step]
            valid = np.take_along_axis(open_[rows], best, axis=1)
            at = np.take_along_axis(ids[rows], best, axis=1)
            open_[rows[:, None], best] = False
            near = np.where(valid[:, :, None], self.links[np.maximum(at, 0)], -1)
            take(rows, near.reshape(len(rows), -1))
        # Links that fill a beam may have pushed others out of it unexpanded.
        if least is not None and len(near_enough):
            at, new = (np.concatenate(z) for z in zip(*near_enough, strict=True))
            wide = found >= (beam if margin == 0 else 1)
            at, new = at[wide[at]], new[wide[at]]
            while len(at):
                near_enough.clear()
                for i in range(0, len(at), 1 << 15):
                    a, b = at[i : i + (1 << 15)], self.links[new[i : i + (1 << 15)]]
                    line, place = np.nonzero(b >= 0)
                    met(a[line], b[line, place].astype(np.int64))
                at, new = (np.concatenate(z) for z in zip(*near_enough, strict=True)) if near_enough else (at[:0], new[:0])
        return ids, sims


def select(x: np.ndarray, candidates: np.ndarray, sims: np.ndarray, most: int) -> np.ndarray:
    """Up to ``most`` of each row's candidates: first those nearer to the row than
    to any chosen one, then the nearest of the rest."""
    width = min(candidates.shape[1], max(2 * KEPT, most))
    if width < candidates.shape[1]:
        part = np.argpartition(-sims, width - 1, axis=1)[:, :width]
        candidates, sims = np.take_along_axis(candidates, part, axis=1), np.take_along_axis(sims, part, axis=1)
    order = np.argsort(-sims, axis=1, kind="stable")
    c, s = np.take_along_axis(candidates, order, axis=1), np.take_along_axis(sims, order, axis=1)
    there = (c >= 0) & (s > -np.inf)
    v = x[np.maximum(c, 0)]
    between = np.matmul(v, v.transpose(0, 2, 1))
    chosen = np.zeros(c.shape, bool)
    closest = np.full(c.shape, -np.inf, np.float32)
    n = np.zeros(len(c), np.int64)
    for j in range(c.shape[1]):
        take = there[:, j] & (closest[:, j] < s[:, j]) & (n < most)
        chosen[:, j] = take
        n += take
        closest = np.maximum(closest, np.where(take[:, None], between[:, j, :], -np.inf))
    rank = np.where(chosen, 0, np.where(there, 1, 2)) * c.shape[1] + np.arange(c.shape[1])
    best = np.argsort(rank, axis=1, kind="stable")[:, :most]
    out = np.full((len(c), most), -1, np.int32)
    out[:, : best.shape[1]] = np.where(np.take_along_axis(there, best, axis=1), np.take_along_axis(c, best, axis=1), -1)
    return out


class Graph:
    """Layers over nested heads of the rows; the top layer is searched whole."""

    def __init__(self, x: np.ndarray, links: list[np.ndarray] | None = None):
        self.x, self.marks = np.ascontiguousarray(x, np.float32), Marks()
        sizes = [len(x)]
        while sizes[-1] > TINY:
            sizes.append(max(1, sizes[-1] // LAYER_SHARE))
        self.layers = [Layer(self.x[:n], self.marks, links[i] if links else None) for i, n in enumerate(sizes)]
        if links is None:
            for depth in range(len(sizes) - 1, -1, -1):
                self._build(depth)

    def _build(self, depth: int) -> None:
        layer, n = self.layers[depth], len(self.layers[depth].x)
        # The rows of the layer above come first, so that every entry from there is in place.
        done = min(n, max(TINY, len(self.layers[depth + 1].x) if depth + 1 < len(self.layers) else 0))
        for i in range(0, done if done > 1 else 0, BLOCK):
            part = np.arange(i, min(done, i + BLOCK))
            head = layer.x[part] @ layer.x[:done].T
            head[np.arange(len(part)), part] = -np.inf
            width = min(done, 2 * KEPT)
            near = np.argpartition(-head, width - 1, axis=1)[:, :width]
            layer.connect(part, near.astype(np.int32), np.take_along_axis(head, near, axis=1))
        while done < n:
            new = np.arange(done, min(n, done + min(BLOCK, done, max(1, MARKS // n))))
            q = layer.x[new]
            ids, sims = layer.search(q, self.entry(q, depth), BUILD_BEAM, done)
            # Rows of one batch have not met in the graph: they are compared with one another.
            mates = q @ q.T
            np.fill_diagonal(mates, -np.inf)
            width = min(KEPT, len(new))
            near = np.argpartition(-mates, width - 1, axis=1)[:, :width]
            layer.connect(new, np.concatenate([ids, new[near].astype(np.int32)], axis=1), np.concatenate([sims, np.take_along_axis(mates, near, axis=1)], axis=1))
            done = new[-1] + 1

    def entry(self, q: np.ndarray, depth: int) -> np.ndarray:
        """Where the search of a layer starts: the nearest of the layer above."""
        above = self.layers[depth + 1]
        n = len(above.x)
        if n <= TINY:
            return (q @ above.x.T).argmax(axis=1)[:, None].astype(np.int32)
        return above.search(q, self.entry(q, depth + 1), 4, n)[0]

    def within(self, q: np.ndarray, least: float, beam: int, margin: float, report: Report) -> None:
        """Reports (query, row) pairs found with similarity of ``least`` or more."""
        layer, n = self.layers[0], len(self.x)
        size = max(16, min(BLOCK, MARKS // n))
        for i in range(0, len(q), size):
            rows = q[i : i + size]
            if n <= TINY or beam * 4 >= n:
                for k in range(0, n, 1 << 14):
                    a, b = np.nonzero(rows @ self.x[k : k + (1 << 14)].T >= least)
                    report(a + i, b + k)
            else:
                layer.search(rows, self.entry(rows, 0), beam, n, least, margin, lambda a, b, i=i: report(a + i, b))


def shares_found(graph: Graph, q: np.ndarray, own: np.ndarray | None, least: float, beam: int, margin: float) -> tuple[np.ndarray, np.ndarray]:
    """Per vector of ``q``: its true links in the graph, and those found; ``own`` are its own places."""
    true, got = np.zeros(len(q), np.int64), np.zeros(len(q), np.int64)

    def report(a: np.ndarray, b: np.ndarray) -> None:
        other = slice(None) if own is None else own[a] != b
        got[:] += np.bincount(a[other], minlength=len(q))

    for i in range(0, len(q), 64):
        near = q[i : i + 64] @ graph.x.T >= least
        if own is not None:
            near[np.arange(len(near)), own[i : i + 64]] = False
        true[i : i + 64] = near.sum(axis=1)
    some = np.flatnonzero(true)
    if len(some):
        got_all, own_all = got, own
        got, own = np.zeros(len(some), np.int64), None if own_all is None else own_all[some]
        q = q[some]
        graph.within(q, least, beam, margin, report)
        got_all[some] = got
        got = got_all
    return true, got


def audited(graph: Graph, q: np.ndarray, own: np.ndarray | None, least: float, beam: int = BEAM, margin: float = 0.0, recall: float = RECALL) -> tuple[int, float, float, int]:
    """(beam, margin, recall, audited vectors with links): the first beam and margin,
    widened each time, with which a vector finds ``recall`` of its links on average."""
    linked = []
    for i in range(0, len(q), BLOCK):
        true, _ = shares_found(graph, q[i : i + BLOCK], None if own is None else own[i : i + BLOCK], least, 1 << 40, 0.0)
        linked += (i + np.flatnonzero(true)).tolist()
        if len(linked) >= AUDITED_LINKED:
            break
    if not linked:
        return beam, margin, 1.0, 0
    q, own = q[linked], None if own is None else own[linked]
    while True:
        true, got = shares_found(graph, q, own, least, beam, margin)
        share = float(np.minimum(got / true, 1.0).mean())
        if share >= recall or beam * 4 >= len(graph.x):
            return beam, margin, share, len(q)
        beam, margin = beam * 2, margin + 0.02


class Ties:
    """Unites places as links come; the smallest place stands for its group."""

    def __init__(self, n: int):
        self.label = np.arange(n)

    def unite(self, i: np.ndarray, j: np.ndarray) -> None:
        label = self.label
        while True:
            a, b = label[i], label[j]
            apart = a != b
            if not apart.any():
                return
            i, j, a, b = i[apart], j[apart], a[apart], b[apart]
            np.minimum.at(label, np.maximum(a, b), np.minimum(a, b))
            while (label[label] != label).any():
                label[:] = label[label]


# ------------------------------------------------------------ shards in the shared folder


def _save(shared: Shared, shard: int, rows: np.ndarray, weight: np.ndarray, x: np.ndarray, graph: Graph, settings: dict) -> None:
    shared.write(f"{shard}.rows", rows.astype(np.int64).tobytes())
    shared.write(f"{shard}.weight", weight.astype(np.int64).tobytes())
    shared.write(f"{shard}.v", np.ascontiguousarray(x, np.float64).tobytes())
    for depth, layer in enumerate(graph.layers):
        shared.write(f"{shard}.links{depth}", layer.links.tobytes())
    shared.write(f"{shard}.json", json.dumps(settings | {"layers": len(graph.layers)}).encode())


class Shard:
    """A shard's arrays as mapped from the shared folder."""

    def __init__(self, shared: Shared, shard: int, dims: int):
        self.rows, self.weight = shared.mapped(f"{shard}.rows", np.int64), shared.mapped(f"{shard}.weight", np.int64)
        self.x = np.asarray(shared.mapped(f"{shard}.v", np.float64)).reshape(-1, dims)
        self.norms = np.sqrt(np.einsum("ad,ad->a", self.x, self.x))
        self.shared, self.shard = shared, shard

    def unit(self, places: slice = slice(None)) -> np.ndarray:
        return (self.x[places] / self.norms[places, None]).astype(np.float32)

    def graph(self) -> tuple[Graph, dict]:
        with open(self.shared.path(f"{self.shard}.json"), "rb") as f:
            settings = json.loads(f.read())
        return Graph(self.unit(), [np.asarray(self.shared.mapped(f"{self.shard}.links{d}", np.int32)).reshape(-1, WIDTH) for d in range(settings["layers"])]), settings


def _build_shard(uri: str, sample: list[str], dims: int, cosine: float):
    """(shard, row, weight, v) sorted by shard: builds, audits and stores each shard's graph."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shared = Shared(uri)
        for shard, part in _by_shard(batches):
            rows, weight = part.column(1).to_numpy(), part.column(2).to_numpy()
            order = np.lexsort((rows, (rows.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15 + 2 * SEED)) >> np.uint64(20)))
            x = matrix(part.column(3).combine_chunks(), dims)[order]
            rows, weight = rows[order], weight[order]
            unit = (x / np.sqrt(np.einsum("ad,ad->a", x, x))[:, None]).astype(np.float32)
            graph = Graph(unit)
            own = np.arange(max(0, len(rows) - AUDITED), len(rows))
            beam, margin, recall, audited_own = audited(graph, unit[own], own, cosine - SLACK)
            others = [read_block(shared, name, dims) for name in sample]
            if others:
                ids, v = np.concatenate([o[0] for o in others]), np.concatenate([o[1] for o in others])
                v = (v / np.sqrt(np.einsum("ad,ad->a", v, v))[:, None]).astype(np.float32)[~np.isin(ids, rows)]
                beam, margin, r, audited_others = audited(graph, v, None, cosine - SLACK, beam, margin)
                recall = min(recall, r)
            else:
                audited_others = 0
            _save(shared, shard, rows, weight, x, graph, {"beam": beam, "margin": margin})
            yield pa.RecordBatch.from_arrays(
                [pa.array([shard], pa.int64()), pa.array([len(rows)], pa.int64()), pa.array([beam], pa.int64()), pa.array([recall]), pa.array([audited_own + audited_others], pa.int64())], ["shard", "n", "beam", "recall", "audited"]
            )
        shared.close()

    return run


def _by_shard(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, pa.Table]]:
    now, held = None, []
    for batch in batches:
        keys = batch.column(0).to_numpy()
        at = np.concatenate([[0], np.flatnonzero(keys[1:] != keys[:-1]) + 1, [len(keys)]])
        for a, b in zip(at[:-1], at[1:], strict=True):
            if b > a:
                if held and keys[a] != now:
                    yield now, pa.Table.from_batches(held)
                    held = []
                now = int(keys[a])
                held.append(batch.slice(a, b - a))
    if held:
        yield now, pa.Table.from_batches(held)


def _search_slices(uri: str, dims: int, cosine: float):
    """(graph, shard, slice), any order, to counts (row, n, -1) and ties (row, 0, tie)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shared, held = Shared(uri), {}
        jobs = sorted((g, s, k) for b in batches for g, s, k in zip(*(c.to_pylist() for c in b.columns), strict=True))
        for g, s, k in jobs:
            if held.get("graph") != g:
                target = Shard(shared, g, dims)
                graph, settings = target.graph()
                held = {"graph": g}
            source = target if s == g else Shard(shared, s, dims)
            places = np.arange(k * SLICE, min((k + 1) * SLICE, len(source.rows)))
            offset = 0 if s == g else len(target.rows)
            # Places: the graph's vectors, then (another shard's) the slice's.
            here = places if s == g else offset + np.arange(len(places))
            count, ties = np.zeros(offset + len(places) if offset else len(target.rows), np.int64), Ties(offset + len(places) if offset else len(target.rows))

            def report(a: np.ndarray, b: np.ndarray) -> None:
                for i in range(0, len(a), 1 << 15):
                    p, r = a[i : i + (1 << 15)], b[i : i + (1 << 15)]
                    other = here[p] != r
                    p, r = p[other], r[other]
                    good = _dots(source.x, places[p], target.x, r) / (source.norms[places[p]] * target.norms[r]) >= cosine
                    p, r = p[good], r[good]
                    # A link within a shard is met from either end, one between shards here only.
                    np.add.at(count, here[p], target.weight[r])
                    if offset:
                        np.add.at(count, r, source.weight[places[p]])
                    ties.unite(here[p], r)

            graph.within(source.unit(slice(places[0], places[-1] + 1)), cosine - SLACK, settings["beam"], settings["margin"], report)
            rows = np.concatenate([target.rows, source.rows[places]]) if offset else np.asarray(target.rows)
            some, tied = np.flatnonzero(count), np.flatnonzero(ties.label != np.arange(len(ties.label)))
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.concatenate([rows[some], rows[tied]])), pa.array(np.concatenate([count[some], np.zeros(len(tied), np.int64)])), pa.array(np.concatenate([np.full(len(some), -1), rows[ties.label[tied]]]))], ["row", "n", "tie"]
            )
        shared.close()

    return run


def link_answers(reps: DataFrame, n: int, dims: int, cosine: float = COSINE, shard_rows: int | None = None) -> tuple[DataFrame, DataFrame]:
    """(row, n, tie) of all search tasks, and each shard's audit (shard, n, beam, recall, audited)."""
    spark = reps.sparkSession
    uri = fresh_folder(spark, "hnsw")
    shards = -(-n // (shard_rows or max(TINY, SHARD_BYTES // (8 * dims))))
    sample = reps.orderBy(F.xxhash64(F.lit(SEED), "row"), "row").limit(AUDITED).select("row", "v") if shards > 1 else None
    names = [name for name, _ in write_blocks(sample, uri, dims, BLOCK)] if sample is not None else []
    dealt = reps.select(F.pmod(F.xxhash64("row"), F.lit(shards)).alias("shard"), "row", "weight", "v").repartition(shards, "shard").sortWithinPartitions("shard")
    built = cut(dealt.mapInArrow(_build_shard(uri, names, dims, cosine), "shard long, n long, beam long, recall double, audited long"))
    # Each graph with the shards up to its own, by slices.
    pairs = built.select(F.col("shard").alias("g"), F.explode(F.sequence(F.lit(0).cast("long"), F.col("shard"))).alias("s"))
    jobs = pairs.join(built.select(F.col("shard").alias("s"), "n"), "s").select("g", "s", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("n") - 1) / SLICE))).alias("k"))
    slices = -(-n // SLICE) + shards
    tasks = min(slices * (shards + 1) // 2 + 1, 20_000)
    answers = cut(cut(jobs).repartition(tasks).mapInArrow(_search_slices(uri, dims, cosine), "row long, n long, tie long"))
    drop_folder(spark, uri)
    return answers, built


def near_vectors(embeddings: DataFrame, cosine: float = COSINE, shard_rows: int | None = None) -> DataFrame:
    """vec_id, n_links, component_id, kept of each row."""
    vectors = packed(embeddings)
    live = vectors.where("v is not null and vec_id is not null and dims > 0")
    classes = cut(live.groupBy("h1", "h2").agg(F.min_by("row", "vec_id").alias("row"), F.count("*").alias("weight"), F.min("vec_id").alias("first")))
    reps = classes.join(live.select("row", "v", "dims"), "row")
    reps = cut(reps.mapInArrow(_without_zero, "h1 long, h2 long, row long, weight long, first long, v binary, dims int"))
    size = reps.agg(F.count("*").alias("n"), F.max("dims").alias("dims")).first()
    if size["n"]:
        answers, _ = link_answers(reps, size["n"], size["dims"], cosine, shard_rows)
    else:
        answers = embeddings.sparkSession.createDataFrame([], "row long, n long, tie long")
    counts = answers.where("tie < 0").groupBy("row").agg(F.sum("n").alias("links"))
    ties = components(answers.where("tie >= 0").select(F.col("row").alias("a"), F.col("tie").alias("b")))
    # Components of classes by row, then named by their smallest vec_id.
    named = reps.select("row", "h1", "h2", "weight", "first").join(counts, "row", "left").join(ties.withColumnRenamed("node", "row"), "row", "left").withColumn("component", F.coalesce("component", "row"))
    smallest = named.groupBy("component").agg(F.min("first").alias("component_id"))
    known = named.join(smallest, "component").select("h1", "h2", (F.coalesce("links", F.lit(0)) + F.col("weight") - 1).alias("links"), "component_id")
    out = vectors.select("vec_id", F.when(F.col("v").isNotNull() & F.col("vec_id").isNotNull(), F.col("h1")).alias("h1"), "h2").join(known, ["h1", "h2"], "left")
    return out.select(
        "vec_id", F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"),
        F.coalesce(F.col("vec_id") == F.coalesce("component_id", "vec_id"), F.lit(True)).alias("kept"),
    )


def _without_zero(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Drops vectors whose length in double precision is zero or not finite."""
    names = ["h1", "h2", "row", "weight", "first", "v", "dims"]
    for batch in batches:
        v = batch.column(batch.schema.get_field_index("v"))
        keep = []
        for data in v.to_pylist():
            x = np.frombuffer(data, np.float64)
            s = float((x * x).sum())
            keep.append(s > 0 and np.isfinite(s))
        yield batch.select(names).filter(pa.array(keep, pa.bool_()))
