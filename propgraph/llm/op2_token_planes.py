"""Token files whose id blocks are transposed into byte or bit planes, each compressed alone.

File: b"TPLN", version, plane kind and block length; the compressed planes of every block; an index
(document ids, tokens of each document, and for each block its ids, planes, offset and sizes) and,
last, the index's offset and length. A block can be read by its index entry alone.

Files are whole documents in ascending doc_id, at most about `file_ids` ids each (a longer document
is a file of its own). Spark writes them as one BINARY value a row, so that any shared storage works
and a lost executor leaves no half file.

Cases: null or empty text gives the end id alone; null doc_ids come first; repeated rows are
documents of their own, ordered by a hash of the text (so that many null ids don't meet in one task); an empty table gives no file. Only doc_id and text are read.
"""

from __future__ import annotations

import json
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import blocks, shared_path, table, text_of, workers_can_import
from .ordered import LEAST

MAGIC, END_ID, BLOCK, FILE_IDS = b"TPLN", 1, 1 << 16, 1 << 21


def split_planes(ids: np.ndarray, kind: str) -> list[bytes]:
    """The planes of a block, lowest first, without the highest ones that are all zero."""
    width = max(1, int(ids.max(initial=0)).bit_length())
    raw = np.ascontiguousarray(ids, dtype="<u4").view(np.uint8).reshape(-1, 4)
    if kind == "byte":
        return [raw[:, i].tobytes() for i in range(-(-width // 8))]
    bits = np.unpackbits(raw, axis=1, bitorder="little")
    return [np.packbits(bits[:, i], bitorder="little").tobytes() for i in range(width)]


def join_planes(planes: list[bytes], n: int, kind: str) -> np.ndarray:
    if kind == "byte":
        raw = np.zeros((n, 4), np.uint8)
        for i, p in enumerate(planes):
            raw[:, i] = np.frombuffer(p, np.uint8)
    else:
        bits = np.zeros((n, 32), np.uint8)
        for i, p in enumerate(planes):
            bits[:, i] = np.unpackbits(np.frombuffer(p, np.uint8), count=n, bitorder="little")
        raw = np.packbits(bits, axis=1, bitorder="little")
    return raw.reshape(-1).view("<u4").astype(np.uint32)


def encode_file(doc_ids: list[int | None], docs: list[np.ndarray], kind: str = "byte", block: int = BLOCK, level: int = 3) -> bytes:
    import zstandard

    z = zstandard.ZstdCompressor(level=level)
    ids = np.concatenate(docs) if docs else np.zeros(0, np.uint32)
    out, entries = [MAGIC + struct.pack("<BBI", 1, kind == "bit", block)], []
    at = len(out[0])
    for i in range(0, len(ids), block):
        part = ids[i : i + block]
        planes = [z.compress(p) for p in split_planes(part, kind)]
        entries.append([len(part), at, [len(p) for p in planes]])
        out += planes
        at += sum(map(len, planes))
    index = z.compress(json.dumps({"docs": doc_ids, "tokens": [len(d) for d in docs], "blocks": entries}).encode())
    return b"".join([*out, index, struct.pack("<QQ", at, len(index))])


def read_index(data: bytes) -> dict:
    import zstandard

    if data[:4] != MAGIC:
        raise ValueError("not a token-plane file")
    at, n = struct.unpack("<QQ", data[-16:])
    return json.loads(zstandard.ZstdDecompressor().decompress(data[at : at + n])) | {"kind": "bit" if data[5] else "byte"}


def read_block(data: bytes, index: dict, i: int) -> np.ndarray:
    import zstandard

    z = zstandard.ZstdDecompressor()
    n, at, sizes = index["blocks"][i]
    planes = []
    for size in sizes:
        planes.append(z.decompress(data[at : at + size]))
        at += size
    return join_planes(planes, n, index["kind"])


def decode_file(data: bytes) -> tuple[list[int | None], list[np.ndarray]]:
    index = read_index(data)
    ids = [read_block(data, index, i) for i in range(len(index["blocks"]))]
    flat = np.concatenate(ids) if ids else np.zeros(0, np.uint32)
    return index["docs"], np.split(flat, np.cumsum(index["tokens"])[:-1]) if index["tokens"] else []


def write_token_files(docs: DataFrame, path: str, vocabulary: str, kind: str = "byte", file_ids: int = FILE_IDS, end_id: int = END_ID) -> None:
    """Tokenizes whole texts and writes the files, in ascending doc_id over (part, file)."""
    workers_can_import(docs.sparkSession)
    rows = text_of(docs).withColumn("_order", F.coalesce("doc_id", F.lit(LEAST)))
    rows = rows.withColumn("_tie", F.xxhash64("text"))
    rows = rows.repartitionByRange("_order", "_tie").sortWithinPartitions("_order", "_tie").select("doc_id", "text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        from propgraph.llm.tokens import tokenizer

        tok, part, number = tokenizer(vocabulary), TaskContext.get().partitionId(), 0
        who, have, total = [], [], 0

        def done() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([part], pa.int64()), pa.array([number], pa.int64()), pa.array([len(who)], pa.int64()), pa.array([total], pa.int64()), pa.array([encode_file(who, have, kind)], pa.binary())], names=["part", "file", "n_docs", "n_tokens", "content"])

        for batch in blocks(batches):
            got = tok.ids(batch.column("text"))
            for d, ids in zip(batch.column("doc_id").to_pylist(), got, strict=True):
                who.append(d)
                have.append(np.append(ids, np.uint32(end_id)))
                total += len(ids) + 1
                if total >= file_ids:
                    yield done()
                    number, who, have, total = number + 1, [], [], 0
        if who:
            yield done()

    rows.mapInArrow(run, "part long, file long, n_docs long, n_tokens long, content binary").write.parquet(path)


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, from the files."""
    files = spark.read.parquet(path)
    narrow = files.select("part", "file", "n_tokens")
    parts = narrow.groupBy("part").agg(F.sum("n_tokens").alias("n")).collect()  # one row a partition
    base, total = [], 0
    for r in sorted(parts):
        base.append((r["part"], total))
        total += r["n"]
    w = Window.partitionBy("part").orderBy("file")
    starts = narrow.join(F.broadcast(spark.createDataFrame(base, "part long, base long")), "part")
    starts = starts.select("part", "file", (F.col("base") + F.sum("n_tokens").over(w) - F.col("n_tokens")).alias("base"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                who, docs = decode_file(batch.column("content")[i].as_py())
                n = np.array([len(d) for d in docs], np.int64)
                cols = [pa.array([batch.column(c)[i].as_py()] * len(who), pa.int64()) for c in ("part", "file")]
                cols += [pa.array(who, pa.int64()), pa.array(np.cumsum(n) - n), pa.array(n), pa.array([zlib.crc32(np.ascontiguousarray(d, "<u4")) for d in docs], pa.int64())]
                yield pa.RecordBatch.from_arrays(cols, names=["part", "file", "doc_id", "inner", "n_tokens", "ids_crc32"])

    docs = files.select("part", "file", "content").mapInArrow(run, "part long, file long, doc_id long, inner long, n_tokens long, ids_crc32 long")
    return docs.join(starts, ["part", "file"]).select("doc_id", (F.col("base") + F.col("inner")).alias("start"), "n_tokens", "ids_crc32")


def op2_token_planes(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .tokens import vocabulary

    path = shared_path(spark, "token-planes")
    write_token_files(table(spark, sf_dir, "documents"), path, vocabulary("word_bpe_49k.json"))
    return read_token_files(spark, path)
