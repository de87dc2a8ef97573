"""Quality classifier (2): compression against good and bad dictionaries.

Two zstandard dictionaries hold text of good and of bad labelled rows.  A text
is cut into pieces of ``PIECE`` bytes; each piece is compressed with either
dictionary, so that the dictionaries matter as much at the end of a long text as
at its start, and the whole text is used.  The normalised difference of the two
compressed sizes (good minus bad, over their sum) becomes a score by a logistic
curve fitted on labelled rows that are in no dictionary.  The curve also sees
the text's compressed share (how much it repeats itself) and its length.

The dictionaries and the curve come from a bounded sample of labelled rows
(``Fit``): ``per_class`` rows of each class, chosen by a hash of doc_id.  Rows
with crc32(doc_id as text) mod 5 = 0 are held out and never learned from.

Null and empty texts compress to nothing: their difference is 0 and they get the
score of the curve there.  Repeated rows get equal scores; of rows that repeat a
sampled doc_id the fit sees the smallest text.  Without two different labelled
texts of either class (no labels, an empty table) there is nothing to learn: every
score is 0.5, no row is rejected.  An empty table gives no rows; other columns,
source and language among them, are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

PIECE = 4096
LEVEL = 1
#: Score where there is nothing to learn from.
UNKNOWN = 0.5


@dataclass(frozen=True)
class Fit:
    """Bounds of what the classifier is fitted on: ``per_class`` rows of each class, with their whole texts."""

    per_class: int = 1500
    dictionary_bytes: int = 112_640
    seed: int = 11


@dataclass(frozen=True)
class Model:
    good: bytes
    bad: bytes
    weights: tuple[float, ...]
    mean: tuple[float, ...]
    scale: tuple[float, ...]


def held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


class Compressor:
    def __init__(self, model_good: bytes, model_bad: bytes):
        # Only the tail of a dictionary is in reach of a frame's window; the pieces are far smaller.
        self.sides = [zstandard.ZstdCompressor(level=LEVEL, dict_data=self._ready(d), write_checksum=False, write_content_size=False, write_dict_id=False) for d in (model_good, model_bad)]
        self.plain = zstandard.ZstdCompressor(level=LEVEL, write_checksum=False, write_content_size=False)

    @staticmethod
    def _ready(data: bytes) -> zstandard.ZstdCompressionDict:
        d = zstandard.ZstdCompressionDict(data)
        d.precompute_compress(level=LEVEL)
        return d

    def features(self, text: bytes) -> tuple[float, float, float, float]:
        """Normalised difference, worst piece's difference, compressed share, log length."""
        if not text:
            return 0.0, 0.0, 1.0, 0.0
        good = bad = 0
        worst = -1.0
        a, b = self.sides[0].compress, self.sides[1].compress
        for i in range(0, len(text), PIECE):
            piece = text[i : i + PIECE]
            g, w = len(a(piece)), len(b(piece))
            good += g
            bad += w
            if len(piece) >= 200 or i == 0:
                worst = max(worst, (g - w) / (g + w))
        return (good - bad) / (good + bad), worst, min(good, bad) / len(text), float(np.log1p(len(text)))


def train_dictionary(texts: list[bytes], size: int) -> bytes:
    pieces = [t[i : i + PIECE] for t in texts for i in range(0, len(t), PIECE)]
    pieces = [p for p in pieces if len(p) >= 8]
    try:
        return zstandard.train_dictionary(size, pieces, level=LEVEL).as_bytes()
    except zstandard.ZstdError:
        # Too little text for a trained one: a dictionary of the text itself.
        return b"".join(texts)[-size:] or b"\0" * 8


def _curve_inputs(rows: np.ndarray) -> np.ndarray:
    return np.column_stack([rows[:, :4], rows[:, 0] * rows[:, 2], rows[:, 2] ** 2])


def fit_curve(x: np.ndarray, y: np.ndarray, rounds: int = 60) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Logistic regression by Newton steps, with a small ridge."""
    x = _curve_inputs(x)
    mean, scale = x.mean(0), x.std(0) + 1e-9
    z = np.column_stack([np.ones(len(x)), (x - mean) / scale])
    w = np.zeros(z.shape[1])
    ridge = np.diag([1e-6] + [1e-2] * (z.shape[1] - 1))
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + ridge, z.T @ (y - p) - ridge @ w)
        w += step
        if np.abs(step).max() < 1e-8:
            break
    return w, mean, scale


def curve(model: Model, rows: np.ndarray) -> np.ndarray:
    z = (_curve_inputs(rows) - np.array(model.mean)) / np.array(model.scale)
    return 1 / (1 + np.exp(-np.clip(model.weights[0] + z @ np.array(model.weights[1:]), -30, 30)))


def fit(docs: DataFrame, labels: DataFrame, bounds: Fit = Fit()) -> Model | None:
    """Dictionaries and curve from at most 2 * per_class labelled rows; None where they teach nothing."""
    usable = labels.where(F.col("quality").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.min("quality").alias("quality"))
    lot = F.xxhash64(F.lit(bounds.seed), "doc_id")
    chosen = [usable.where(F.col("quality") == c).orderBy(lot, "doc_id").limit(bounds.per_class) for c in (0, 1)]
    # At most 2 * per_class ids: a bound that does not grow with the data.
    sample = docs.select("doc_id", "text").where(~held_out(F.col("doc_id"))).join(F.broadcast(chosen[0].union(chosen[1])), "doc_id")
    one_each = sample.groupBy("doc_id", "quality").agg(F.min("text").alias("text"))
    rows = sorted((r.doc_id, r.quality, (r.text or "").encode()) for r in one_each.collect())
    order = np.random.default_rng(bounds.seed).permutation(len(rows))
    parts: dict[tuple[int, int], list[bytes]] = {(c, k): [] for c in (0, 1) for k in (0, 1)}
    seen: set[bytes] = set()
    for i in order:
        _, quality, text = rows[i]
        if text in seen:  # copies would count for the dictionaries and again for the curve
            continue
        seen.add(text)
        parts[quality, int(len(parts[quality, 0]) > len(parts[quality, 1]))].append(text)
    if not all(parts.values()):
        return None
    good, bad = (train_dictionary(parts[c, 0], bounds.dictionary_bytes) for c in (1, 0))
    tool = Compressor(good, bad)
    x = np.array([tool.features(t) for c in (0, 1) for t in parts[c, 1]])
    y = np.repeat([0.0, 1.0], [len(parts[0, 1]), len(parts[1, 1])])
    # The sample has as many of either class; the curve is moved to the shares among the labels.
    w, mean, scale = fit_curve(x, y)
    shares = {r.quality: r.n for r in usable.groupBy("quality").agg(F.count("*").alias("n")).collect()}
    w[0] += np.log(shares[1] / shares[0]) - np.log(y.sum() / (len(y) - y.sum()))
    return Model(good, bad, tuple(w), tuple(mean), tuple(scale))


def score(docs: DataFrame, model: Model | None, threshold: float = 0.3) -> DataFrame:
    """doc_id, held_out, score, predicted, difference of each row."""
    schema = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, held_out boolean, score double, predicted int, difference double"
    if model is None:
        return docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), F.lit(UNKNOWN).alias("score"), F.lit(int(UNKNOWN >= threshold)).alias("predicted"), F.lit(0.0).alias("difference"))
    held = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = held.value
        tool = Compressor(m.good, m.bad)
        for batch in batches:
            text = pc.fill_null(batch.column(2), "").cast(pa.binary())
            rows = np.array([tool.features(x.as_py()) for x in text]).reshape(-1, 4)
            s = curve(m, rows)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(s), pa.array((s >= threshold).astype(np.int32)), pa.array(rows[:, 0])], ["doc_id", "held_out", "score", "predicted", "difference"])

    return docs.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "text").mapInArrow(run, schema)


def accepted(docs: DataFrame, model: Model | None, threshold: float = 0.3) -> DataFrame:
    """The rows, with all their columns, whose text scores ``threshold`` or more."""
    if model is None:
        return docs if threshold <= UNKNOWN else docs.limit(0)
    held, at = docs.sparkSession.sparkContext.broadcast(model), docs.columns.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = held.value
        tool = Compressor(m.good, m.bad)
        for batch in batches:
            text = pc.fill_null(batch.column(at), "").cast(pa.binary())
            rows = np.array([tool.features(x.as_py()) for x in text]).reshape(-1, 4)
            yield batch.filter(pa.array(curve(m, rows) >= threshold))

    return docs.mapInArrow(run, docs.schema)


def quality_scores(docs: DataFrame, labels: DataFrame, bounds: Fit = Fit(), threshold: float = 0.3) -> DataFrame:
    return score(docs, fit(docs, labels, bounds), threshold)
