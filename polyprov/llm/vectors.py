"""Vectors as packed rows, and blocks of query vectors in the shared folder."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from polyprov.llm.common import Shared, cut

BLOCK = 1024


def usable(column: pa.Array) -> Iterator[np.ndarray | None]:
    """Each vector as float64; None if null or with null or non-finite components."""
    if pa.types.is_list(column.type) or pa.types.is_large_list(column.type):
        values = pc.fill_null(column.values.cast(pa.float64()), float("nan")).to_numpy(zero_copy_only=False)
        offsets, valid = column.offsets.to_numpy(), column.is_valid().to_numpy(zero_copy_only=False)
        for ok, a, b in zip(valid, offsets[:-1], offsets[1:], strict=True):
            v = values[a:b]
            yield v if ok and np.isfinite(v).all() else None
    else:
        for x in column.to_pylist():
            v = None if x is None or any(c is None for c in x) else np.array(x, np.float64)
            yield v if v is not None and np.isfinite(v).all() else None


def packed(embeddings: DataFrame, scale=None) -> DataFrame:
    """vec_id, row, dims, v (float64 bytes, null if unusable), h1, h2 (hash of v); cut off.

    ``row`` tells repeated ids apart.  ``scale`` maps a matrix of vectors.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out, dims, h1, h2 = [], [], [], []
            for v in usable(batch.column(1)):
                data = None if v is None else (v if scale is None else scale(v)).astype(np.float64).tobytes()
                out.append(data)
                dims.append(0 if v is None else len(v))
                d = hashlib.blake2b(data or b"", digest_size=16).digest()
                h1.append(int.from_bytes(d[:8], "little", signed=True))
                h2.append(int.from_bytes(d[8:], "little", signed=True))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(dims, pa.int32()), pa.array(out, pa.binary()), pa.array(h1, pa.int64()), pa.array(h2, pa.int64())], ["vec_id", "dims", "v", "h1", "h2"])

    rows = embeddings.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding")
    return cut(rows.mapInArrow(run, "vec_id long, dims int, v binary, h1 long, h2 long").withColumn("row", F.monotonically_increasing_id()))


def matrix(column: pa.Array, dims: int) -> np.ndarray:
    """Rows of float64; shorter vectors are continued by zeros."""
    items = column.to_pylist()
    if all(len(x) == 8 * dims for x in items):
        return np.frombuffer(b"".join(items), np.float64).reshape(-1, dims)
    out = np.zeros((len(items), dims))
    for i, x in enumerate(items):
        v = np.frombuffer(x, np.float64)
        out[i, : len(v)] = v
    return out


def write_blocks(rows: DataFrame, uri: str, dims: int, block: int = BLOCK) -> list[tuple[str, int]]:
    """Write (row, v) as blocks of at most ``block`` vectors; gives names and sizes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shared, held, n = Shared(uri), [], 0

        def flush():
            part = pa.Table.from_batches(held).combine_chunks()
            ids = part.column(0).to_numpy()
            name = f"block-{int(ids[0]):016x}"
            shared.write(f"{name}.rows", ids.tobytes())
            shared.write(f"{name}.v", matrix(part.column(1).combine_chunks(), dims).tobytes())
            return pa.RecordBatch.from_arrays([pa.array([name]), pa.array([len(ids)], pa.int64())], ["name", "n"])

        for batch in batches:
            for i in range(0, batch.num_rows, block):
                piece = batch.slice(i, block)
                if n + piece.num_rows > block and held:
                    yield flush()
                    held, n = [], 0
                held.append(piece)
                n += piece.num_rows
        if held and n:
            yield flush()

    # A name for each thousand queries comes to the driver, no vector does.
    return sorted((r.name, r.n) for r in rows.select("row", "v").mapInArrow(run, "name string, n long").collect())


def read_block(shared: Shared, name: str, dims: int) -> tuple[np.ndarray, np.ndarray]:
    return np.asarray(shared.mapped(f"{name}.rows", np.int64)), np.asarray(shared.mapped(f"{name}.v", np.float64)).reshape(-1, dims)
