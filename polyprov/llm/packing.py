"""Best-fit packing (4) into bins of several permitted lengths.

Each row's tokens become one item, or, above the largest capacity, full pieces
of that capacity and a last item.  Shards of rows are packed side by side, each
by one task: items go longest first into the open bin that they leave with the
least room (best fit).  Where none fits, a bin of the length is opened whose cost
per token is least for what is still to come.  A bin of c tokens costs
``overhead`` + c + c * c / ``attention`` (a sequence's fixed share of a step, the
part in proportion, and attention's part); the tokens it can expect to hold are
the item and, up to its room, the shard's remaining items that are small enough
for the room, less the room that is open already.  In the end every bin is
downsized to the smallest permitted length that holds its contents.

The lengths are optimised jointly: a shard is packed with every set of permitted
lengths that has the largest (and either with or without regard to open room), and
the packing of least cost is kept.  So none costs more than the largest length alone.

The open bins are kept by their room (a list per room and a bitmap of rooms with
bins), so a packing takes time in proportion to its items.

A null or empty text has no tokens: it is a row with length 0, no bin and no
capacity.  A text of any length is covered whole by its pieces.  Equal lengths
are packed in the order of doc_id, and repeated rows are items of their own, dealt
apart.  An empty table gives no rows; other columns, whatever their names, are
ignored.
"""

from __future__ import annotations

from bisect import bisect_left
from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polyprov.llm.common import word_count
from polyprov.llm.token_counts import token_lengths

CAPACITIES = (512, 1024, 2048, 4096)
OVERHEAD = 48
#: Tokens of a sequence at which attention costs as much as all the rest.
ATTENTION = 16_384
#: Permitted lengths at most: a packing is made for each set of them.
MOST_CAPACITIES = 6
#: Rows that a shard is made for.
SHARD_ROWS = 20_000
SEED = 17

SCHEMA = "doc_id long, piece int, start long, length long, shard int, bin long, bin_offset long, capacity int, bin_fill int"


class Rooms:
    """Open bins by room: the smallest room that is at least ``need``."""

    def __init__(self, most: int):
        self.bins: list[list[int]] = [[] for _ in range(most + 1)]
        self.bits = 0

    def take(self, need: int) -> tuple[int, int] | None:
        higher = self.bits >> need
        if not higher:
            return None
        room = need + ((higher & -higher).bit_length() - 1)
        bin_id = self.bins[room].pop()
        if not self.bins[room]:
            self.bits &= ~(1 << room)
        return bin_id, room

    def put(self, bin_id: int, room: int) -> None:
        if room:
            self.bins[room].append(bin_id)
            self.bits |= 1 << room


def bin_cost(capacity: int, overhead: int = OVERHEAD, attention: int = ATTENTION) -> float:
    return overhead + capacity + capacity * capacity / attention


def _best_fit(lengths: np.ndarray, order: np.ndarray, capacities: tuple[int, ...], costs: list[float], regard: bool) -> tuple[np.ndarray, np.ndarray, list[int]]:
    """Bin and offset of each item, and the bins' fills, for one set of lengths."""
    bins, offsets = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64)
    rooms, fill, open_room = Rooms(capacities[-1]), [], 0
    falling = lengths[order]
    # Tokens of the items from each place on, and the first place of items that fit a room.
    after = np.append(np.cumsum(falling[::-1])[::-1], 0).tolist()
    first = np.searchsorted(-falling, -np.arange(capacities[-1] + 1)).tolist()
    for at, (i, n) in enumerate(zip(order.tolist(), falling.tolist(), strict=True)):
        got = rooms.take(n)
        if got is None:
            room, least = 0, float("inf")
            for c, cost in zip(capacities, costs, strict=True):
                if c >= n:
                    coming = after[max(at + 1, first[c - n])] - (open_room if regard else 0)
                    per_token = cost / (n + min(c - n, max(0, coming)))
                    if per_token < least:
                        room, least = c, per_token
            b = len(fill)
            fill.append(0)
            open_room += room
        else:
            b, room = got
        bins[i], offsets[i] = b, fill[b]
        fill[b] += n
        open_room -= n
        rooms.put(b, room - n)
    return bins, offsets, fill


def pack(lengths: np.ndarray, capacities: tuple[int, ...] = CAPACITIES, overhead: int = OVERHEAD, attention: int = ATTENTION) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Bin, offset in it, and the bin's downsized capacity and fill, per item.

    ``lengths`` are positive and at most the largest capacity.
    """
    if len(capacities) > MOST_CAPACITIES:
        raise ValueError(f"at most {MOST_CAPACITIES} permitted lengths")
    order = np.argsort(-lengths, kind="stable")
    price = {c: bin_cost(c, overhead, attention) for c in capacities}
    best = None
    for size in range(len(capacities)):
        for smaller in combinations(capacities[:-1], size):
            some = (*smaller, capacities[-1])
            for regard in (False, True) if smaller else (False,):
                bins, offsets, fill = _best_fit(lengths, order, some, [price[c] for c in some], regard)
                final = [capacities[bisect_left(capacities, f)] for f in fill]
                cost = sum(price[c] for c in final)
                if best is None or cost < best[0]:
                    best = (cost, bins, offsets, np.array(final, np.int64), np.array(fill, np.int64))
    _, bins, offsets, final, fills = best
    return bins, offsets, final[bins] if len(bins) else bins, fills[bins] if len(bins) else bins


def pack_documents(docs: DataFrame, capacities: tuple[int, ...] = CAPACITIES, overhead: int = OVERHEAD, attention: int = ATTENTION, shard_rows: int = SHARD_ROWS, seed: int = SEED, model_path: str | None = None) -> DataFrame:
    """One row per piece: doc_id, piece, start, length, shard, bin, bin_offset, capacity, bin_fill.

    With ``model_path``, tokens are those of this sentencepiece model; else they are words.
    """
    capacities = tuple(sorted(capacities))
    if model_path is None:
        items = docs.select(F.col("doc_id").cast("long").alias("doc_id"), word_count(F.col("text")).alias("n"))
    else:
        items = token_lengths(docs, model_path)
    shards = max(1, -(-docs.count() // shard_rows))
    # Rows that repeat an id, or have none, are dealt apart by their place in the table.
    lot = F.xxhash64(F.lit(seed), "doc_id", "n", F.monotonically_increasing_id())
    dealt = items.select(F.pmod(lot, F.lit(shards)).cast("int").alias("shard"), "doc_id", "n")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held = None, []
        for batch in batches:
            shard = batch.column(0).to_numpy()
            for a, b in zip(*(lambda at: (at[:-1], at[1:]))(np.concatenate([[0], np.flatnonzero(shard[1:] != shard[:-1]) + 1, [len(shard)]])), strict=True):
                if b <= a:
                    continue
                if shard[a] != now and held:
                    yield _packed(now, held, capacities, overhead, attention)
                    held = []
                now = int(shard[a])
                held.append(batch.slice(a, b - a))
        if held:
            yield _packed(now, held, capacities, overhead, attention)

    # Within a shard the rows come in a fixed order, so that a rerun packs alike.
    return dealt.repartition(shards, "shard").sortWithinPartitions("shard", "doc_id", "n").mapInArrow(run, SCHEMA)


def _packed(shard: int, held: list[pa.RecordBatch], capacities: tuple[int, ...], overhead: int, attention: int) -> pa.RecordBatch:
    rows = pa.Table.from_batches(held).combine_chunks()
    n, most = rows.column(2).to_numpy(), capacities[-1]
    pieces = np.maximum(1, -(-n // most))
    row = np.repeat(np.arange(len(n)), pieces)
    piece = np.arange(len(row)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
    start = piece * most
    length = np.minimum(most, n[row] - start)
    some = length > 0
    bins, offsets, capacity, fill = pack(length[some], capacities, overhead, attention)

    def whole(values: np.ndarray, kind) -> pa.Array:
        out = np.zeros(len(row), np.int64)
        out[some] = values
        return pa.array(out, kind, mask=~some)

    return pa.RecordBatch.from_arrays(
        [rows.column(1).combine_chunks().take(pa.array(row)), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(np.full(len(row), shard), pa.int32()), whole(bins, pa.int64()), whole(offsets, pa.int64()), whole(capacity, pa.int32()), whole(fill, pa.int32())],
        ["doc_id", "piece", "start", "length", "shard", "bin", "bin_offset", "capacity", "bin_fill"],
    )
