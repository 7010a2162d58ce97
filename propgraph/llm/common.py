"""What the training-data operators share: inputs, worker imports and byte-level hashing."""

from __future__ import annotations

import os
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.shared import release, shared_path, written  # noqa: F401

U64 = np.uint64


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def workers_can_import(spark: SparkSession) -> None:
    """Python workers started from now on find this package where the driver found it."""
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    env = spark.sparkContext.environment
    if root not in env.get("PYTHONPATH", "").split(":"):
        env["PYTHONPATH"] = f"{root}:{env['PYTHONPATH']}" if env.get("PYTHONPATH") else root


def text_of(df: DataFrame, *more: str) -> DataFrame:
    """doc_id and text (null: empty) only, so that other columns can't clash."""
    return df.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text"), F.lit("")).alias("text"), *more)


def blocks(batches: Iterable[pa.RecordBatch], column: str = "text", most: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """Slices of at most about `most` bytes of text; a longer text stands alone."""
    for batch in batches:
        col = batch.column(column)
        sizes = np.asarray(pc.binary_length(col).fill_null(0), dtype=np.int64)
        start, total = 0, 0
        for i, n in enumerate(sizes):
            if i > start and total + n > most:
                yield batch.slice(start, i - start)
                start, total = i, 0
            total += int(n)
        if start < batch.num_rows:
            yield batch.slice(start)


def as_bytes(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The UTF-8 bytes of a text column and the n+1 offsets of its values (null: empty)."""
    col = col.fill_null("") if col.null_count else col
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    wide = pa.types.is_large_string(col.type) or pa.types.is_large_binary(col.type)
    _, off, data = col.buffers()
    offsets = np.frombuffer(off, dtype=np.int64 if wide else np.int32)[col.offset : col.offset + len(col) + 1].astype(np.int64)
    raw = np.frombuffer(data, dtype=np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def mix64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finalizer: xor shifts and odd multipliers."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U64(27))
    x = x * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def byte_codes(seed: int) -> np.ndarray:
    return mix64(np.arange(256, dtype=U64) + U64(seed * 1000003 + 17))


def powers(base: int, n: int) -> np.ndarray:
    p = np.full(n, base, dtype=U64)
    if n:
        p[0] = 1
    with np.errstate(over="ignore"):
        return np.multiply.accumulate(p)


class Spans:
    """Polynomial hashes modulo 2^64 of any spans of a byte buffer, from one prefix sum."""

    BASE = 0x9E3779B97F4A7C15 | 1
    INV = pow(BASE, -1, 1 << 64)

    def __init__(self, buf: np.ndarray, seed: int = 1) -> None:
        n = len(buf)
        with np.errstate(over="ignore"):
            self.sums = np.zeros(n + 1, dtype=U64)
            np.cumsum(byte_codes(seed)[buf] * powers(self.BASE, n), out=self.sums[1:])
        self.back = powers(self.INV, n + 1)

    def of(self, start: np.ndarray, end: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            return mix64((self.sums[end] - self.sums[start]) * self.back[start] + (end - start).astype(U64))
