"""What the training-data operators share: tables, shared storage, hashing.

Null, empty and repeated rows: a null text counts as the empty text; rows that
repeat are kept as rows.  Columns beyond those an operator reads are ignored.
"""

from __future__ import annotations

import os
import shutil
import tempfile
import uuid
from collections.abc import Iterator
from urllib.parse import urlparse

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Java regular expression of one word: a run without space, tab, LF, VT, FF, CR.
WORD = r"[^\x20\x09-\x0D]+"

#: Bytes of text that one vectorised step works on (a longer text is one step).
STEP_BYTES = 1 << 18


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def word_count(text) -> F.Column:
    """Number of words of a text column, in the JVM; null counts as 0."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


# ------------------------------------------------------------ shared storage


def checkpoint_root(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; where it is unset and the session
    runs on one machine (as in tests), one of our own.  A cluster must name one."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that all machines share")
    root = os.environ.get("POLYPROV_SHARED_DIR") or os.path.join(tempfile.gettempdir(), "polyprov-shared")
    return "file://" + root


def cut(df: DataFrame) -> DataFrame:
    """Materialise ``df`` in the shared checkpoint folder and drop its lineage."""
    spark = df.sparkSession
    if spark.conf.get("spark.checkpoint.dir", None) is None and spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(checkpoint_root(spark))
    return df.checkpoint(eager=True)


def fresh_folder(spark: SparkSession, kind: str) -> str:
    """URI of a new folder below the shared one; it goes when the session ends, if not before."""
    uri = f"{checkpoint_root(spark).rstrip('/')}/{kind}-{uuid.uuid4().hex}"
    path = spark._jvm.org.apache.hadoop.fs.Path(uri)
    store = path.getFileSystem(spark._jsc.hadoopConfiguration())
    store.mkdirs(path)
    store.deleteOnExit(path)
    return uri


def drop_folder(spark: SparkSession, uri: str) -> None:
    """Remove a folder of ours and what it holds."""
    path = spark._jvm.org.apache.hadoop.fs.Path(uri)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


#: Ids that are broadcast at most: 8 MB, some 50 MB as a hash table.
BROADCAST_IDS = 1_000_000


def by_ids(rows: DataFrame, ids: DataFrame, how: str) -> DataFrame:
    """Semi or anti join of wide rows with distinct ids (one column, cut off).

    Where the ids' checked number allows, they are broadcast and the rows stay
    where they are; beyond that both sides are shuffled.  The result is the same.
    """
    name = ids.columns[0]
    small = ids.count() <= BROADCAST_IDS
    return rows.join(F.broadcast(ids) if small else ids, name, how).select(rows.columns)


class Shared:
    """Small-file access to a shared folder from driver and workers.

    ``file:`` folders are used in place (so arrays can be memory-mapped); other
    schemes go through ``pyarrow.fs`` and are mapped from copies of this process,
    which ``close`` removes (arrays mapped before stay readable).
    """

    def __init__(self, uri: str):
        self.uri = uri
        self.copies = os.path.join(tempfile.gettempdir(), f"{uri.rsplit('/', 1)[-1]}-{os.getpid()}-{uuid.uuid4().hex[:8]}")
        parsed = urlparse(uri)
        self.local = parsed.path if parsed.scheme in ("", "file") else None

    def write(self, name: str, data: bytes) -> None:
        """Atomic and repeatable: a retried task replaces the file by equal bytes."""
        temp = f".{name}.{uuid.uuid4().hex}"
        if self.local is not None:
            os.makedirs(self.local, exist_ok=True)
            with open(os.path.join(self.local, temp), "wb") as f:
                f.write(data)
            os.replace(os.path.join(self.local, temp), os.path.join(self.local, name))
            return
        from pyarrow import fs

        store, base = fs.FileSystem.from_uri(self.uri)
        store.create_dir(base, recursive=True)
        with store.open_output_stream(f"{base}/{temp}") as f:
            f.write(data)
        store.move(f"{base}/{temp}", f"{base}/{name}")

    def path(self, name: str) -> str:
        if self.local is not None:
            return os.path.join(self.local, name)
        from pyarrow import fs

        target = os.path.join(self.copies, name)
        if not os.path.exists(target):
            store, base = fs.FileSystem.from_uri(self.uri)
            os.makedirs(self.copies, exist_ok=True)
            part = f"{target}.{uuid.uuid4().hex}"
            with store.open_input_stream(f"{base}/{name}") as src, open(part, "wb") as dst:
                while chunk := src.read(1 << 24):
                    dst.write(chunk)
            os.replace(part, target)
        return target

    def close(self) -> None:
        shutil.rmtree(self.copies, ignore_errors=True)

    def mapped(self, name: str, dtype) -> np.ndarray:
        path = self.path(name)
        if os.path.getsize(path) == 0:
            return np.empty(0, dtype)
        return np.memmap(path, dtype=dtype, mode="r")

    def remove(self, names) -> None:
        for name in names:
            if self.local is not None:
                path = os.path.join(self.local, name)
                if os.path.exists(path):
                    os.remove(path)
            else:
                from pyarrow import fs

                store, base = fs.FileSystem.from_uri(self.uri)
                store.delete_file(f"{base}/{name}")


# ------------------------------------------------------------ vectorised words

_PRIME = np.uint64(0x9E3779B97F4A7C15 | 1)
_INVERSE = np.uint64(pow(int(_PRIME), -1, 1 << 64))
_powers: dict[str, np.ndarray] = {}


def _power(which: str, base: np.uint64, n: int) -> np.ndarray:
    have = _powers.get(which)
    if have is None or len(have) < n:
        size = max(n, STEP_BYTES + 1)
        have = np.full(size, base, np.uint64)
        have[0] = 1
        with np.errstate(over="ignore"):
            np.multiply.accumulate(have, out=have)
        if size <= 32 * STEP_BYTES:
            _powers[which] = have
    return have[:n]


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads 64-bit values (an invertible mixing)."""
    with np.errstate(over="ignore"):
        x = x ^ (x >> np.uint64(30))
        x = x * np.uint64(0xBF58476D1CE4E5B9)
        x = x ^ (x >> np.uint64(27))
        x = x * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def text_steps(column: pa.Array, step: int = STEP_BYTES) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """(first row, bytes, row offsets) for runs of rows of about ``step`` bytes."""
    column = pc.fill_null(column, "").cast(pa.large_string())
    if len(column) == 0:
        return
    _, off, data = column.buffers()
    offsets = np.frombuffer(off, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.empty(0, np.uint8)
    row = 0
    while row < len(column):
        end = int(np.searchsorted(offsets, offsets[row] + step, side="right")) - 1
        end = min(max(end, row + 1), len(column))
        yield row, raw[offsets[row] : offsets[end]], offsets[row : end + 1] - offsets[row]
        row = end


def hash_words(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """64-bit hashes of all words (A-Z lower-cased), and each row's word offsets."""
    n = len(data)
    if n == 0:
        return np.empty(0, np.uint64), np.zeros(len(offsets), np.int64)
    upper = (data - np.uint8(65)) < np.uint8(26)
    low = data + (upper.view(np.uint8) << np.uint8(5))
    solid = ~((data == 32) | ((data - np.uint8(9)) < np.uint8(5)))
    inner = offsets[1:-1]
    inner = inner[(inner > 0) & (inner < n)]
    before = np.empty(n, bool)
    before[0] = False
    before[1:] = solid[:-1]
    before[inner] = False
    starts = np.flatnonzero(solid & ~before)
    after = np.empty(n, bool)
    after[-1] = False
    after[:-1] = solid[1:]
    after[inner - 1] = False
    ends = np.flatnonzero(solid & ~after) + 1
    with np.errstate(over="ignore"):
        total = np.zeros(n + 1, np.uint64)
        np.cumsum((low.astype(np.uint64) + np.uint64(1)) * _power("p", _PRIME, n), out=total[1:])
        hashes = (total[ends] - total[starts]) * _power("i", _INVERSE, n)[starts]
        hashes = mix64(hashes ^ ((ends - starts).astype(np.uint64) << np.uint64(48)))
    return hashes, np.searchsorted(starts, offsets)


#: Multipliers of the five places of a shingle (odd 64-bit values, fixed).
_PLACES = [np.uint64(0xD6E8FEB86659FD93), np.uint64(0xA0761D6478BD642F), np.uint64(0xE7037ED1A0B428DB), np.uint64(0x8EBC6AF09C88C6E3), np.uint64(0x589965CC75374CC3)]
SHINGLE_WORDS = len(_PLACES)


def shingle_sets(data: np.ndarray, offsets: np.ndarray) -> Iterator[np.ndarray]:
    """Per row: the sorted distinct 64-bit hashes of its five-word shingles."""
    words, at = hash_words(data, offsets)
    width = SHINGLE_WORDS
    with np.errstate(over="ignore"):
        spread = np.zeros(max(len(words) - width + 1, 0), np.uint64)
        for j, k in enumerate(_PLACES):
            spread += words[j : j + len(spread)] * k
        spread = mix64(spread)
        for a, b in zip(at[:-1], at[1:], strict=True):
            if b - a >= width:
                s = np.sort(spread[a : b - width + 1])
                keep = np.empty(len(s), bool)
                keep[0] = True
                np.not_equal(s[1:], s[:-1], out=keep[1:])
                yield s[keep]
            elif b > a:
                whole = np.uint64(b - a)
                for j in range(a, b):
                    whole = mix64(np.array([whole * _PLACES[0] + words[j]], np.uint64))[0]
                yield np.array([whole], np.uint64)
            else:
                yield np.empty(0, np.uint64)
