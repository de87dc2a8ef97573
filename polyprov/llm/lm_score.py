"""LM scoring (5): an interpolated modified Kneser-Ney n-gram model.

Counted in Spark, kept as sorted arrays in a shared folder, and memory-mapped by
the workers that score.

* Level 1 is the vocabulary: sorted 64-bit hashes of the lower-cased words and of
  the end of a text.  A word's id is its place in that order.
* Level k holds the k-grams as sorted 64-bit keys, ``context * M + word``: the
  context is the place of the (k-1)-gram before the word, M the number of words
  plus one.  So keys need no second hash, and a context's grams lie side by side.
  A level is cut into files by ranges of keys that hold about equally many tokens,
  as counted one level down: a frequent context is spread over several files, and
  its sums are added up when they are read.
* Workers count runs of texts with sorting, and send packed blocks (sorted
  differences, compressed) to the task that merges a range; nothing is gathered
  in one place.  The highest level keeps counts, lower levels keep the number of
  distinct left neighbours; either level has the three discounts of modified
  modified Kneser-Ney from its own counts of counts, and the sums its contexts need.
* Counts and sums take one byte each; the few that do not fit are listed beside
  them.  Shuffled blocks are let go level by level.

A text's tokens are its words and one end.  A word never seen in training has
the share of one extra type in the level-0 uniform distribution.

Null and empty texts are one end token.  Long texts are scored whole.  Repeated
rows count each in training and get equal scores.  Without training rows every
token has probability 1.  A row with a null doc_id is a training row.  An empty
table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import gc
import json
from collections.abc import Iterator
from dataclasses import asdict, dataclass, field

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from polyprov.llm.common import Shared, fresh_folder, hash_words, text_steps

#: Order of the model of the registered query.
ORDER = 3

#: Tokens that a worker counts before it sends blocks off, and text bytes or grams a file is made for.
RUN_TOKENS = 4_000_000
WORD_FILE_BYTES = 64_000_000
GRAM_FILE_TOKENS = 4_000_000

#: Text bytes of a step: larger ones share more look-ups in the arrays.
TEXT_STEP = 1 << 20

#: Files that a reader keeps mapped at once.
MAPS = 8192

#: Byte of a value that is listed beside the bytes.
LISTED = 255

_END = np.uint64(0xE9D5A1B4C3F28761)
BLOCKS = "shard int, n long, keys binary, counts binary"


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 7 == 2, F.lit(False))


@dataclass
class Model:
    """Where the arrays lie and the numbers that go with them."""

    uri: str
    order: int
    tokens: int = 0
    #: Per level: first id of each file (and the end), least key of each file, discounts, totals.
    starts: dict[int, list[int]] = field(default_factory=dict)
    ranges: dict[int, list[int]] = field(default_factory=dict)
    discounts: dict[int, list[float]] = field(default_factory=dict)
    totals: dict[int, list[float]] = field(default_factory=dict)

    @property
    def types(self) -> int:
        return self.starts[1][-1] if 1 in self.starts else 0


# ------------------------------------------------------------ packed blocks


def _pack(values: np.ndarray) -> bytes:
    planes = np.ascontiguousarray(values.view(np.uint8).reshape(len(values), values.itemsize).T)
    return zstandard.ZstdCompressor(level=1).compress(planes.tobytes())


def _unpack(data: bytes, n: int, dtype) -> np.ndarray:
    planes = np.frombuffer(zstandard.ZstdDecompressor().decompress(data), np.uint8).reshape(np.dtype(dtype).itemsize, n)
    return np.ascontiguousarray(planes.T).view(dtype).reshape(n)


def _summed(keys: np.ndarray, counts: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct keys and their summed counts (1 each without counts)."""
    if not len(keys):
        return keys, np.empty(0, np.uint64)
    if counts is None:
        keys = np.sort(keys)
    else:
        order = np.argsort(keys)
        keys, counts = keys[order], counts[order]
    at = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))
    sums = np.diff(np.append(at, len(keys))).astype(np.uint64) if counts is None else np.add.reduceat(counts, at)
    return keys[at], sums


def _blocks(keys: np.ndarray, counts: np.ndarray, cuts: np.ndarray) -> pa.RecordBatch:
    """One row per file: ``cuts`` are the lower bounds of the files' keys, but the first."""
    at = np.concatenate([[0], np.searchsorted(keys, cuts), [len(keys)]])
    rows = []
    for s, (a, b) in enumerate(zip(at[:-1], at[1:], strict=True)):
        if b > a:
            k = keys[a:b].copy()
            k[1:] -= keys[a : b - 1]
            rows.append((s, int(b - a), _pack(k), _pack(counts[a:b].astype(np.uint64))))
    cols = list(zip(*rows, strict=True)) if rows else [[], [], [], []]
    return pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), pa.array(cols[1], pa.int64()), pa.array(cols[2], pa.binary()), pa.array(cols[3], pa.binary())], ["shard", "n", "keys", "counts"])


def _merged(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """Blocks sorted by file to (file, keys, counts); runs are merged as they come."""
    now, held, size = None, [], 0

    def joined():
        return _summed(np.concatenate([h[0] for h in held]), np.concatenate([h[1] for h in held])) if len(held) > 1 else held[0]

    for batch in batches:
        for shard, n, keys, counts in zip(*(batch.column(i) for i in range(4)), strict=True):
            shard, n = shard.as_py(), n.as_py()
            if shard != now:
                if now is not None:
                    yield now, *joined()
                now, held, size = shard, [], 0
            held.append((np.cumsum(_unpack(keys.as_py(), n, np.uint64), dtype=np.uint64), _unpack(counts.as_py(), n, np.uint64)))
            size += n
            if size > 2 * RUN_TOKENS and size > 2 * len(held[0][0]):
                held = [joined()]
                size = len(held[0][0])
    if now is not None:
        yield now, *joined()


# ------------------------------------------------------------ reading the model


class Reader:
    """The model's arrays, memory-mapped."""

    def __init__(self, model: Model):
        self.m, self.shared = model, Shared(model.uri)
        self.width = np.uint64(model.types + 1)
        self.arrays: dict[tuple[str, int, int], np.ndarray] = {}
        self._spans: dict[int, tuple[np.ndarray, np.ndarray]] = {}

    def file(self, kind: str, level: int, shard: int, dtype) -> np.ndarray:
        found = self.arrays.get((kind, level, shard))
        if found is None:
            if len(self.arrays) >= MAPS:
                self.arrays.clear()
            found = self.arrays[kind, level, shard] = self.shared.mapped(f"{kind}{level}-{shard}", dtype)
        return found

    def ids(self, level: int, keys: np.ndarray) -> np.ndarray:
        """Ids of sorted distinct keys; the number of grams for those not there."""
        starts = self.m.starts[level]
        out = np.full(len(keys), starts[-1], np.int64)
        at = np.concatenate([[0], np.searchsorted(keys, self.cuts(level)), [len(keys)]])
        for s in np.flatnonzero(np.diff(at)).tolist():
            a, b = at[s], at[s + 1]
            n = starts[s + 1] - starts[s]
            if n:
                have = self.file("keys", level, s, np.uint64)
                i = np.minimum(np.searchsorted(have, keys[a:b]), n - 1)
                out[a:b] = np.where(have[i] == keys[a:b], i + starts[s], starts[-1])
        return out

    def cuts(self, level: int) -> np.ndarray:
        return np.array(self.m.ranges[level][1:], dtype=np.uint64)

    def spans(self, level: int) -> tuple[np.ndarray, np.ndarray]:
        """First context of each file of a level above 1, and the one after its last."""
        if level not in self._spans:
            least, width = np.array(self.m.ranges[level], np.uint64), self.width
            above = np.append((least[1:] - np.uint64(1)) // width + np.uint64(1), np.uint64(self.m.starts[level - 1][-1] + 2))
            self._spans[level] = (least // width).astype(np.int64), above.astype(np.int64)
        return self._spans[level]

    def at(self, kind: str, level: int, ids: np.ndarray, dtype, bounds: list[int]) -> np.ndarray:
        """Values of ``kind`` at ids (any order); 0 beyond the last bound."""
        out = np.zeros(len(ids), dtype)
        order = np.argsort(ids, kind="stable")
        ordered = ids[order]
        cut = np.searchsorted(ordered, bounds)
        for s in np.flatnonzero(np.diff(cut)).tolist():
            have = self.file(kind, level, s, dtype)
            if len(have):
                out[order[cut[s] : cut[s + 1]]] = have[ordered[cut[s] : cut[s + 1]] - bounds[s]]
        return out

    def listed(self, kind: str, level: int, places: np.ndarray, shard: int, width: int) -> np.ndarray:
        """The columns of values listed beside a file's bytes."""
        lists = self.file(kind, level, shard, np.uint32).reshape(width, -1)
        return lists[1:, np.searchsorted(lists[0], places.astype(np.uint32))].astype(np.int64)

    def adjusted(self, level: int, ids: np.ndarray) -> np.ndarray:
        """Counts (of left neighbours below the highest level) of grams; 0 for unknown ones."""
        bounds = np.array(self.m.starts[level])
        out = self.at("adj", level, ids, np.uint8, bounds).astype(np.int64)
        large = np.flatnonzero(out == LISTED)
        shard = np.searchsorted(bounds, ids[large], side="right") - 1
        for s in np.unique(shard):
            of = large[shard == s]
            out[of] = self.listed("adjx", level, ids[of] - bounds[s], int(s), 2)[0]
        return out

    def sums(self, level: int, contexts: np.ndarray) -> tuple[np.ndarray, list[np.ndarray]]:
        """Sum of counts, and numbers of 1, 2, 3+, of contexts, over all files that hold grams of theirs."""
        low, above = self.spans(level)
        out = np.zeros((4, len(contexts)), np.int64)
        at, last = np.searchsorted(above, contexts, side="right"), np.searchsorted(low, contexts, side="right") - 1
        left = np.arange(len(contexts))
        while len(left):
            for s in np.unique(at[left]):
                of = left[at[left] == s]
                out[:, of] += self._sums_in(level, int(s), contexts[of] - low[s])
            at[left] += 1
            left = left[at[left] <= last[left]]
        return out[0], list(out[1:])

    def _sums_in(self, level: int, shard: int, places: np.ndarray) -> np.ndarray:
        have = self.file("sum", level, shard, np.uint8)
        out = np.zeros((4, len(places)), np.int64)
        if len(have):
            code = have[places].astype(np.int64)
            out[1], out[2] = code % 16, code // 16
            out[0] = out[1] + 2 * out[2]
            large = np.flatnonzero(code == LISTED)
            if len(large):
                columns = self.listed("sumx", level, places[large], shard, 6)
                out[0, large] = columns[0] + (columns[1] << 32)
                out[1:, large] = columns[2:]
        return out

    def known(self, level: int, keys: np.ndarray) -> np.ndarray:
        """Ids of keys in any order."""
        distinct, back = np.unique(keys, return_inverse=True)
        return self.ids(level, distinct)[back]


@dataclass
class Step:
    """Tokens of a run of texts: word ids, and where each text starts and ends."""

    first: np.ndarray
    last: np.ndarray
    hashes: np.ndarray


def _steps(column: pa.Array) -> Iterator[Step]:
    for _, data, offsets in text_steps(column, TEXT_STEP):
        words, at = hash_words(data, offsets)
        n = len(at) - 1
        hashes = np.empty(len(words) + n, np.uint64)
        last = at[1:] + np.arange(n)
        body = np.ones(len(hashes), bool)
        body[last] = False
        hashes[body] = words
        hashes[last] = _END
        yield Step(at[:-1] + np.arange(n), last, hashes)


def _contexts(ids: np.ndarray, first: np.ndarray, grams: int) -> np.ndarray:
    """Per token the id of the gram before it: grams = unknown, grams + 1 = start."""
    out = np.empty(len(ids), np.int64)
    out[1:] = ids[:-1]
    out[first] = grams + 1
    return out


# ------------------------------------------------------------ counting


def _count(blocks: DataFrame, model: Model, level: int, ranges: list[int], finish) -> dict[int, dict]:
    """Merge blocks into the level's files; ``finish`` writes them and gives numbers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader = Reader(model)
        for shard, keys, counts in _merged(batches):
            yield pa.RecordBatch.from_arrays([pa.array([shard], pa.int32()), pa.array([json.dumps(finish(reader, shard, keys, counts))])], ["shard", "numbers"])

    # One row per file comes to the driver.
    rows = blocks.repartition("shard").sortWithinPartitions("shard").mapInArrow(run, "shard int, numbers string").collect()
    by = {r.shard: json.loads(r.numbers) for r in rows}
    sizes = [by[s]["n"] if s in by else 0 for s in range(len(ranges))]
    for s in range(len(ranges)):
        if s not in by:
            for kind in ("keys", "count", "adj", "adjx", "suffix", "sum", "sumx"):
                Shared(model.uri).write(f"{kind}{level}-{s}", b"")
    if "keys" in next(iter(by.values()), {"keys": 1}):
        model.starts[level] = [0, *np.cumsum(sizes).tolist()]
    of_counts = np.sum([by[s]["of_counts"] for s in by if "of_counts" in by[s]] or [[0] * 5], axis=0)
    if level == 1:
        model.tokens = int(sum(by[s].get("tokens", 0) for s in by)) or model.tokens
    model.totals[level] = [float(x) for x in np.sum([by[s]["totals"] for s in by if "totals" in by[s]] or [[0] * 4], axis=0)]
    model.discounts[level] = discounts(of_counts)
    # Spark drops the blocks' shuffle files once nothing refers to them.
    gc.collect()
    blocks.sparkSession.sparkContext._jvm.System.gc()
    return by


def _cut_points(counts: np.ndarray, file_tokens: int) -> dict:
    """Where the grams that follow a file's grams are cut: (place, piece, pieces) in order.

    No run between cuts follows more than ``file_tokens`` tokens, but for one gram's
    excess, and a gram that more follow is cut in pieces.  ``before`` and ``after`` are the tokens
    up to the first cut and from the last one.
    """
    total = np.cumsum(counts.astype(np.int64))
    if not len(total):
        return {"cuts": [], "before": 0, "after": 0}
    part = np.maximum(total - 1, 0) // file_tokens
    new = np.flatnonzero(part[1:] != part[:-1]) + 1
    if counts[0] > file_tokens:
        new = np.append(0, new)
    cuts = [(int(i), j, pieces) for i in new for pieces in [-(-int(counts[i]) // file_tokens) or 1] for j in range(pieces)]
    whole = int(total[-1])
    if not cuts:
        return {"cuts": [], "before": whole, "after": whole}
    i, _, pieces = cuts[-1]
    return {"cuts": cuts, "before": int(total[new[0]] - counts[new[0]]), "after": whole - int(total[i]) + int(counts[i]) // pieces}


def _ranges(points: dict[int, dict], model: Model, level: int, texts: int, file_tokens: int) -> list[int]:
    """Least keys of a level's files, from the points of the files one level down."""
    starts, width = model.starts[level - 1], model.types + 1
    least, held = [0], 0
    for s in sorted(points):
        p = points[s]
        if held + p["before"] > file_tokens:
            least.append(starts[s] * width)
            held = 0
        least += [(starts[s] + i) * width + width * j // pieces for i, j, pieces in p["cuts"]]
        held = p["after"] if p["cuts"] else held + p["before"]
    # The start of a text is a context beside the grams.
    if held + texts > file_tokens:
        pieces = max(1, -(-texts // file_tokens))
        least += [(starts[-1] + 1) * width + width * j // pieces for j in range(pieces)]
    return sorted(set(least))


def discounts(n: np.ndarray) -> list[float]:
    """D1, D2, D3+ from the numbers of grams seen 1, 2, 3 and 4 times (n[1:])."""
    n1, n2, n3, n4 = (float(x) for x in n[1:5])
    if not n1 or not n2:
        return [0.5, 1.0, 1.5]
    y = n1 / (n1 + 2 * n2)
    d = [1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3 if n3 else 1.5]
    return [min(max(x, 0.05), k) for x, k in zip(d, (1.0, 2.0, 3.0), strict=True)]


def _of_counts(counts: np.ndarray) -> tuple[list[int], list[float]]:
    seen = np.bincount(np.minimum(counts, 5).astype(np.int64), minlength=6)
    return seen[:5].tolist(), [float(counts.sum()), float((counts == 1).sum()), float((counts == 2).sum()), float((counts >= 3).sum())]


def _write_counts(reader: Reader, level: int, shard: int, counts: np.ndarray) -> None:
    large = np.flatnonzero(counts >= LISTED)
    reader.shared.write(f"adj{level}-{shard}", np.minimum(counts, LISTED).astype(np.uint8).tobytes())
    reader.shared.write(f"adjx{level}-{shard}", np.stack([large, counts[large]]).astype(np.uint32).tobytes())


def _write_sums(reader: Reader, level: int, shard: int, contexts: np.ndarray, counts: np.ndarray) -> None:
    """Sum of counts and numbers of 1, 2, 3+ per context of the file's range.

    Without a 3+ the numbers say all: n1 + 16 * n2 in a byte, if they are small.
    """
    low, above = reader.spans(level)
    i, n = contexts - low[shard], int(above[shard] - low[shard])
    n1, n2, n3 = (np.bincount(i[mask], minlength=n).astype(np.uint32) for mask in (counts == 1, counts == 2, counts >= 3))
    large = np.flatnonzero((n3 > 0) | (n1 > 15) | (n2 > 14))
    code = (n1 + 16 * n2).astype(np.uint8)
    code[large] = LISTED
    total = np.bincount(i, weights=counts, minlength=n)[large].astype(np.uint64)
    reader.shared.write(f"sum{level}-{shard}", code.tobytes())
    columns = [large, total & np.uint64(0xFFFFFFFF), total >> np.uint64(32), n1[large], n2[large], n3[large]]
    reader.shared.write(f"sumx{level}-{shard}", np.stack([c.astype(np.uint32) for c in columns]).tobytes())


def train(texts: DataFrame, order: int = ORDER, file_tokens: int = GRAM_FILE_TOKENS) -> Model:
    """Count the ``text`` column of a table into a model of ``order`` 2 or more, in files of about ``file_tokens``."""
    if order < 2:
        raise ValueError("the order is 2 or more")
    spark = texts.sparkSession
    model = Model(fresh_folder(spark, "lm"), order)
    texts = texts.select("text")
    n_bytes = texts.agg(F.sum(F.octet_length("text")).alias("n")).first()["n"] or 0
    bits = max(1, int(np.ceil(np.log2(1 + n_bytes / WORD_FILE_BYTES))))
    model.ranges[1] = [s << (64 - bits) for s in range(1 << bits)]

    def count_words(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cuts, held, n = np.array(model.ranges[1][1:], np.uint64), [], 0
        for batch in batches:
            for step in _steps(batch.column(0)):
                held.append(_summed(step.hashes, None))
                n += len(held[-1][0])
                if n > RUN_TOKENS // 2:
                    yield _blocks(*_summed(*map(np.concatenate, zip(*held, strict=True))), cuts)
                    held, n = [], 0
        if held:
            yield _blocks(*_summed(*map(np.concatenate, zip(*held, strict=True))), cuts)

    def finish_words(reader: Reader, shard: int, keys: np.ndarray, counts: np.ndarray) -> dict:
        reader.shared.write(f"keys1-{shard}", keys.tobytes())
        reader.shared.write(f"count1-{shard}", counts.astype(np.uint64).tobytes())
        # Nothing follows an end.
        ends = keys == _END
        return {"n": len(keys), "keys": 1, "tokens": int(counts.sum()), "texts": int(counts[ends].sum()), **_cut_points(np.where(ends, 0, counts), file_tokens)}

    points = _count(texts.mapInArrow(count_words, BLOCKS), model, 1, model.ranges[1], finish_words)
    n_texts = sum(p["texts"] for p in points.values())
    for level in range(2, order + 1):
        model.ranges[level] = _ranges(points, model, level, n_texts, file_tokens)
        points = _count_grams(texts, model, level, file_tokens)
    for level in range(order - 1, 0, -1):
        _count_neighbours(spark, model, level)
        if level > 2:
            Shared(model.uri).remove([f"suffix{level}-{s}" for s in range(len(model.ranges[level]))])
    return model


def _count_grams(texts: DataFrame, model: Model, level: int, file_tokens: int) -> dict[int, dict]:
    width = np.uint64(model.types + 1)
    if (model.starts[level - 1][-1] + 2) * (model.types + 1) >= 1 << 64:
        raise OverflowError("keys of this order do not fit 64 bits")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader, held, n = Reader(model), [], 0
        cuts = np.array(model.ranges[level][1:], np.uint64)
        for batch in batches:
            for step in _steps(batch.column(0)):
                held.append(_summed(_token_keys(reader, step, level)[-1], None))
                n += len(held[-1][0])
                if n > RUN_TOKENS:
                    yield _blocks(*_summed(*map(np.concatenate, zip(*held, strict=True))), cuts)
                    held, n = [], 0
        if held:
            yield _blocks(*_summed(*map(np.concatenate, zip(*held, strict=True))), cuts)

    top = level == model.order

    def finish(reader: Reader, shard: int, keys: np.ndarray, counts: np.ndarray) -> dict:
        reader.shared.write(f"keys{level}-{shard}", keys.tobytes())
        before, word = (keys // width).astype(np.int64), keys % width
        if not top:
            if level > 2:
                reader.shared.write(f"suffix{level}-{shard}", _suffixes(reader, level, before, word).tobytes())
            end = reader.ids(1, np.array([_END]))[0]
            return {"n": len(keys), "keys": 1, **_cut_points(np.where(word == np.uint64(end), 0, counts), file_tokens)}
        _write_counts(reader, level, shard, counts)
        _write_sums(reader, level, shard, before, counts)
        seen, totals = _of_counts(counts)
        return {"n": len(keys), "keys": 1, "of_counts": seen, "totals": totals}

    return _count(texts.mapInArrow(count, BLOCKS), model, level, model.ranges[level], finish)


def _suffixes(reader: Reader, level: int, before: np.ndarray, word: np.ndarray) -> np.ndarray:
    """Id of each gram without its first word, one level down."""
    if level == 2:
        return word.astype(np.int64)
    grams, lower = reader.m.starts[level - 1][-1], reader.m.starts[level - 2][-1]
    if level == 3:
        context = (reader.at("keys", 2, before, np.uint64, reader.m.starts[2]) % reader.width).astype(np.int64)
    else:
        context = reader.at("suffix", level - 1, before, np.int64, reader.m.starts[level - 1])
    context[before == grams + 1] = lower + 1
    return reader.known(level - 1, context.astype(np.uint64) * reader.width + word)


def _count_neighbours(spark, model: Model, level: int) -> None:
    """Distinct left neighbours of the grams of a level, from the level above."""
    starts = model.starts[level]
    upper = level + 1
    width = np.uint64(model.types + 1)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        reader = Reader(model)
        for batch in batches:
            for shard in batch.column(0).to_pylist():
                keys = reader.file("keys", upper, shard, np.uint64)
                for i in range(0, len(keys), RUN_TOKENS):
                    part = np.asarray(keys[i : i + RUN_TOKENS])
                    grams = _suffixes(reader, upper, (part // width).astype(np.int64), part % width)
                    yield _blocks(*_summed(grams.astype(np.uint64), None), np.array(starts[1:-1], np.uint64))

    def finish(reader: Reader, shard: int, grams: np.ndarray, counts: np.ndarray) -> dict:
        adjusted = np.zeros(starts[shard + 1] - starts[shard], np.uint32)
        adjusted[grams.astype(np.int64) - starts[shard]] = counts
        _write_counts(reader, level, shard, adjusted)
        if level > 1:
            before = (np.asarray(reader.file("keys", level, shard, np.uint64)) // width).astype(np.int64)
            _write_sums(reader, level, shard, before, adjusted)
        seen, totals = _of_counts(adjusted)
        return {"n": len(adjusted), "of_counts": seen, "totals": totals}

    files = len(model.starts[upper]) - 1
    shards = spark.range(0, files, 1, files).select(F.col("id").cast("int").alias("shard"))
    _count(shards.mapInArrow(count, BLOCKS), model, level, starts[:-1], finish)


def _token_keys(reader: Reader, step: Step, upto: int) -> list[np.ndarray]:
    """Word ids (level 1), then the keys of levels 2 .. upto, of each token."""
    words = reader.known(1, step.hashes)
    out, ids, word = [words], words, words.astype(np.uint64)
    for level in range(2, upto + 1):
        context = _contexts(ids, step.first, reader.m.starts[level - 1][-1])
        out.append(context.astype(np.uint64) * reader.width + word)
        if level < upto:
            ids = reader.known(level, out[-1])
    return out


# ------------------------------------------------------------ scoring


def _discounted(counts: np.ndarray, d: list[float]) -> np.ndarray:
    return np.maximum(counts - np.array([0.0, *d])[np.minimum(counts, 3).astype(np.int64)], 0.0)


def probabilities(reader: Reader, step: Step) -> tuple[np.ndarray, np.ndarray]:
    """(probability, training count) of each token."""
    m = reader.m
    if not m.tokens:
        return np.ones(len(step.hashes)), np.zeros(len(step.hashes), np.uint64)
    words = reader.known(1, step.hashes)
    # Values per distinct word or gram, then spread to the tokens.
    distinct, back = np.unique(words, return_inverse=True)
    counts = reader.at("count", 1, distinct, np.uint64, m.starts[1])[back]
    total, n1, n2, n3 = m.totals[1]
    d = m.discounts[1]
    rest = (d[0] * n1 + d[1] * n2 + d[2] * n3) / total
    p = (_discounted(reader.adjusted(1, distinct), d) / total + rest / (m.types + 1))[back]
    ids, word = words, words.astype(np.uint64)
    for level in range(2, m.order + 1):
        d = m.discounts[level]
        context = _contexts(ids, step.first, m.starts[level - 1][-1])
        keys, back = np.unique(context.astype(np.uint64) * reader.width + word, return_inverse=True)
        grams = reader.ids(level, keys)
        seen = reader.adjusted(level, grams)
        before, of = np.unique((keys // reader.width).astype(np.int64), return_inverse=True)
        total, numbers = reader.sums(level, before)
        held = sum(x * n for x, n in zip(d, numbers, strict=True))
        total, held = total[of], held[of]
        there = total > 0
        safe = np.where(there, total, 1.0)
        p = np.where(there, _discounted(seen, d) / safe, 0.0)[back] + np.where(there, held / safe, 1.0)[back] * p
        ids = grams[back]
    return p, counts


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of each row."""
    settings = asdict(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = Model(**settings)
        reader = Reader(m)
        for batch in batches:
            out = [[], [], [], []]
            for step in _steps(batch.column(2)):
                p, counts = probabilities(reader, step)
                base = np.log10((counts.astype(np.float64) + 1) / (m.tokens + m.types + 1))
                out[0].append(step.last - step.first + 1)
                out[1].append(np.add.reduceat((counts > 0).astype(np.int64), step.first))
                out[2].append(np.add.reduceat(base, step.first))
                out[3].append(np.add.reduceat(np.log10(p), step.first))
            n, known, base, full = (np.concatenate(x) if x else np.empty(0) for x in out)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), batch.column(1), pa.array(n, pa.int64()), pa.array(known, pa.int64()), pa.array(np.full(len(n), m.tokens), pa.int64()), pa.array(base, pa.float64()), pa.array(full, pa.float64())],
                ["doc_id", "held_out", "n_tokens", "n_known", "train_tokens", "base_score", "score"],
            )

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text").mapInArrow(run, f"doc_id {kind}, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double")


def lm_scores(docs: DataFrame, order: int = ORDER) -> DataFrame:
    """Train on the rows that are not held out, score all."""
    return score(docs, train(docs.where(~held_out(F.col("doc_id"))), order))


def perplexity(scores: DataFrame) -> DataFrame:
    """Per row: 10 ** (-score / n_tokens), beside the unigram base's."""
    return scores.withColumns({"perplexity": F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens")), "base_perplexity": F.pow(F.lit(10.0), -F.col("base_score") / F.col("n_tokens"))})
