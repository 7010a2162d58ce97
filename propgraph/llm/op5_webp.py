"""Texts as lossless WebP images: stored, read back, and described by their pixels.

A text's UTF-8 bytes, padded with bytes 255 to a positive multiple of 576, are the samples of a grey
image 576 pixels wide (the green channel, with the subtract-green transform making red and blue the
same). A repeated line and the padding are back-references. Where a text has few different bytes, or
mostly runs of one, a palette and the left-neighbour predictor are tried too, and the smallest file is
kept. What exceeds the format's 16,384 rows goes to a further image; the stored form is the images' files,
one after another.

Stored forms are written as BINARY values of a Parquet table in shared storage, and everything that the
query returns about them is computed from that table, by tasks that see nothing but the stored bytes.

Cases: null text is empty: one row of 255; repeated rows give equal values; an empty table gives no
row. Only doc_id and text are read.
"""

from __future__ import annotations

import hashlib
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import as_bytes, blocks, shared_path, table, text_of, workers_can_import
from .webp import BLACK, MAX_COPY, MAX_SIDE, decode, encode

WIDTH, LEAST_COPY, PREDICT_BITS, LEFT = 576, 12, 9, 1
#: Fixed value: the farthest distance of a back-reference, less the 120 codes for near ones.
FARTHEST = (1 << 20) - 120


def payload_of(text: bytes, width: int = WIDTH) -> bytes:
    return text + b"\xff" * ((-len(text)) % width or (0 if text else width))


def line_copies(payload: bytes, text_size: int) -> list[tuple[int, int, int]]:
    """(start, length, distance): lines that were there before, and the padding after its first byte."""
    out: list[tuple[int, int, int]] = []
    seen: dict[bytes, int] = {}
    at = 0
    for line in payload[:text_size].split(b"\n"):
        if len(line) >= LEAST_COPY:
            was = seen.setdefault(line, at)
            if at - was > FARTHEST:
                was = seen[line] = at
            if was < at:
                out += [(at + i, min(MAX_COPY, len(line) - i), at - was) for i in range(0, len(line), MAX_COPY)]
        at += len(line) + 1
    if len(payload) - text_size > 4:
        out += [(text_size + 1, len(payload) - text_size - 1, 1)]
    return out


def store(payload: bytes, text_size: int, width: int = WIDTH) -> bytes:
    out = []
    step = width * MAX_SIDE
    for a in range(0, len(payload), step):
        part = payload[a : a + step]
        grey = np.frombuffer(part, np.uint8).astype(np.uint32).reshape(-1, width)
        # written after subtract-green: red and blue are 0 and cost no bit
        out.append(encode_grey(grey, line_copies(part, min(text_size - a, len(part))) if text_size > a else []))
    return b"".join(out)


def encode_grey(grey: np.ndarray, copies: list[tuple[int, int, int]]) -> bytes:
    """The smallest of the forms that suit the samples; the first one at a tie, so that equal samples give equal files."""
    v, flat = np.uint32(BLACK) | grey * np.uint32(0x010101), grey.ravel()
    forms = [encode(v, copies, (("green",),))]
    if np.count_nonzero(np.bincount(flat, minlength=256)) <= 16:
        forms.append(encode(v, (), (("palette",),)))
    if np.count_nonzero(flat[1:] == flat[:-1]) * 2 > len(flat):
        cells = [(n + (1 << PREDICT_BITS) - 1) >> PREDICT_BITS for n in grey.shape]
        forms.append(encode(v, (), (("predictor", PREDICT_BITS, np.full(cells, LEFT << 8, np.uint32)), ("green",))))
    return min(forms, key=len)


def restore(media: bytes) -> np.ndarray:
    """The samples of all images of a stored form, (rows, width)."""
    out, at = [], 0
    while at < len(media):
        n = 8 + struct.unpack("<I", media[at + 4 : at + 8])[0]
        out.append(((decode(media[at : at + n]) >> np.uint32(8)) & np.uint32(255)).astype(np.uint8))
        at += n
    return np.concatenate(out)


def features(samples: np.ndarray) -> str:
    """Rows, mean, deviation, and 64 bits: which of 64 runs of samples are brighter than the mean."""
    flat = samples.ravel()
    cells = np.add.reduceat(flat, np.linspace(0, len(flat), 64, endpoint=False).astype(np.int64), dtype=np.int64) / (len(flat) / 64)
    mean = float(flat.mean())
    return f"{len(samples)}:{mean:.3f}:{float(flat.std()):.3f}:{int.from_bytes(np.packbits(cells > mean).tobytes(), 'big'):016x}"


def write_media(docs: DataFrame, path: str) -> None:
    """The table of stored forms: doc_id, n_bytes, media. It holds bytes that no codec shortens, so it isn't compressed again."""
    workers_can_import(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            raw, off = as_bytes(batch.column("text"))
            raw, off = raw.tobytes(), off.tolist()
            texts = [raw[a:b] for a, b in zip(off[:-1], off[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([len(t) for t in texts], pa.int64()), pa.array([store(payload_of(t), len(t)) for t in texts], pa.binary())], names=["doc_id", "n_bytes", "media"])

    rows = text_of(docs).mapInArrow(run, "doc_id long, n_bytes long, media binary")
    rows.write.option("compression", "uncompressed").parquet(path)


def read_media(spark: SparkSession, path: str) -> DataFrame:
    """One row a stored form: sizes, digests and features of the samples decoded from it."""
    workers_can_import(spark)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches, "media"):
            rows = []
            for media in batch.column("media").to_pylist():
                samples = restore(media)
                back = samples.tobytes()
                rows.append((len(back), hashlib.sha256(back).hexdigest(), zlib.crc32(back[-32:]), len(media), hashlib.sha256(media).hexdigest(), features(samples)))
            cols = list(zip(*rows, strict=True))
            kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.string(), pa.string()]
            out = [batch.column("doc_id"), batch.column("n_bytes"), *[pa.array(c, k) for c, k in zip(cols, kinds, strict=True)]]
            yield pa.RecordBatch.from_arrays(out, names=["doc_id", "n_bytes", "payload_bytes", "payload_sha256", "tail_crc32", "media_bytes", "media_sha256", "feature"])

    schema = "doc_id long, n_bytes long, payload_bytes long, payload_sha256 string, tail_crc32 long, media_bytes long, media_sha256 string, feature string"
    return spark.read.schema("doc_id long, n_bytes long, media binary").parquet(path).mapInArrow(run, schema)


def op5_webp(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = shared_path(spark, "media")
    write_media(table(spark, sf_dir, "documents"), path)
    return read_media(spark, path)
