"""Harmonic packing of token sequences.

A document is cut into pieces of the capacity C = 2048 and a rest. The rest is cut into at most a
few pieces whose lengths fit a slot of floor(C / j) tokens closely: class j holds j pieces a bin.
Within a worker group (hash of doc_id, start and ids, so that neither a long
document nor many null ids meet in one) every class fills its bins by count alone, so groups need no
word of each other. What is left in bins that did not fill, fewer than j pieces of a class and group,
is packed per group by best fit.

Cases: null or empty text is one piece, the end id; null doc_ids and repeated rows are documents of
their own; an empty table gives no piece. Only doc_id and text are read. Sequences are padded to C
unless their length is a power of two (column padded_length).
"""

from __future__ import annotations

import bisect
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import blocks, release, table, text_of, workers_can_import, written

CAPACITY, CLOSE, LEAST_PIECE, GROUP_TOKENS = 2048, 0.98, 16, 1_000_000


def cut(n: int, capacity: int = CAPACITY, close: float = CLOSE, least: int = LEAST_PIECE) -> list[tuple[int, int]]:
    """(length, class) of the pieces of a document of n tokens, in order."""
    out = [(capacity, 1)] * (n // capacity)
    rest = n % capacity
    while rest:
        j = capacity // rest
        if rest >= close * (capacity // j) or rest < 2 * least:
            out.append((rest, j))
            break
        size = capacity // (j + 1)
        out.append((size, j + 1))
        rest -= size
    return out


def pieces(docs: DataFrame, vocabulary: str, end_id: int = 1, capacity: int = CAPACITY) -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens, class of every piece."""
    workers_can_import(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from propgraph.llm.tokens import tokenizer

        tok = tokenizer(vocabulary)
        for batch in blocks(batches):
            rows = []
            for d, ids in zip(batch.column("doc_id").to_pylist(), tok.ids(batch.column("text")), strict=True):
                ids = np.append(ids, np.uint32(end_id)).astype("<u4")
                at = 0
                for n, k in cut(len(ids), capacity):
                    rows.append((d, at, n, zlib.crc32(ids[at : at + n]), len(ids), k))
                    at += n
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], names=["doc_id", "start", "length", "ids_crc32", "doc_tokens", "class"])

    return text_of(docs).mapInArrow(run, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, class long")


def best_fit(lengths: list[int], capacity: int) -> list[tuple[int, int]]:
    """(bin, offset) of each length, longest first, each into the fullest bin that has room."""
    out: list[tuple[int, int]] = [(0, 0)] * len(lengths)
    room: list[tuple[int, int]] = []
    n = 0
    for i in sorted(range(len(lengths)), key=lambda i: (-lengths[i], i)):
        at = bisect.bisect_left(room, (lengths[i], -1))
        left, k = room.pop(at) if at < len(room) else (capacity, n)
        n += k == n
        out[i] = k, capacity - left
        bisect.insort(room, (left - lengths[i], k))
    return out


def pack(rows: DataFrame, capacity: int = CAPACITY, group_tokens: int = GROUP_TOKENS) -> DataFrame:
    """Adds sequence_id, offset and padded_length to pieces."""
    total = rows.agg(F.sum("length")).first()[0] or 0
    groups = max(1, min(1 << 22, total // group_tokens))
    rows = rows.withColumn("_group", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32"), F.lit(groups)))
    one = Window.partitionBy("_group", "class").orderBy("doc_id", "start", "ids_crc32", "doc_tokens")
    rows = rows.withColumn("_bin", F.floor((F.row_number().over(one) - 1) / F.col("class")))
    each = Window.partitionBy("_group", "class", "_bin").orderBy("doc_id", "start", "ids_crc32", "doc_tokens")
    full = Window.partitionBy("_group", "class", "_bin")
    rows = rows.withColumn("offset", F.coalesce(F.sum("length").over(each.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    rows = rows.withColumn("_n", F.count("*").over(full)).withColumn("_sum", F.sum("length").over(full))
    rows = written(rows, "packed")
    base = F.shiftleft(F.col("_group"), 40)
    out = ["doc_id", "start", "length", "ids_crc32", "doc_tokens"]
    filled = rows.where("_n = class").select(*out, (base + F.shiftleft(F.col("class"), 28) + F.col("_bin")).alias("sequence_id"), "offset", F.col("_sum").alias("used"))

    def rest(part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values(["doc_id", "start", "ids_crc32", "doc_tokens"], kind="stable")
        got = best_fit(part["length"].tolist(), capacity)
        part["_bin"], part["offset"] = [g[0] for g in got], [g[1] for g in got]
        part["used"] = part.groupby("_bin")["length"].transform("sum")
        part["sequence_id"] = part["_group"] * (1 << 40) + part["_bin"]
        return part[[*out, "sequence_id", "offset", "used"]].astype("Int64")

    kinds = ", ".join(f"{c} long" for c in [*out, "sequence_id", "offset", "used"])
    left = rows.where("_n < class").select(*out, "_group").groupBy("_group").applyInPandas(rest, kinds)
    power = F.bit_count("used") == 1
    return filled.unionByName(left).withColumn("padded_length", F.when(power, F.col("used")).otherwise(F.lit(capacity).cast("long"))).drop("used")


def pack_documents(docs: DataFrame, vocabulary: str) -> DataFrame:
    """pieces() and pack(), with a table between them that is deleted when packing has read it."""
    rows = written(pieces(docs, vocabulary), "pieces")
    out = pack(rows)
    release(rows)
    return out


def op3_harmonic_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .tokens import vocabulary

    return pack_documents(table(spark, sf_dir, "documents"), vocabulary("byte_bpe_50k.json"))
