"""The k nearest vectors of each vector by cosine, over all pairs of different vectors.

Equal vectors stand as one, under their least id, and get their links at the end. Vectors are dealt to
groups by a hash of their id. A group holds its own vectors as queries while all vectors pass by in blocks,
and keeps the best k of each query so far; so only vectors and the final k of a query leave a task, never
pairs. Single precision only leaves out pairs that its largest error can't lift to the best k; cosines are
those of double precision. The work grows with the square of the number of different vectors, the rows
moved with that number times the number of groups.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .sites import kept

#: Queries that a group holds at least, about, vectors of a block, queries that meet a block at a time.
GROUP, BLOCK, STEP = 4096, 2048, 512
#: Groups at most, or twice the session's cores where that is more, so that large tables don't move more often.
GROUPS = 32


def nearest_pairs(v: DataFrame, k: int) -> DataFrame:
    """src, dst, rank (from 0), cosine: of v(id, embedding), the k nearest others of each; ids are unique.

    Cosines are rounded to 12 places, so that no block's shape decides; at a tie the least id comes first.
    A vector without a direction (null, empty, a null or not finite element, all zero) has no cosine and
    stands on neither side; vectors of different lengths are not compared."""
    named = kept(_named(v))
    count, copies = named.agg(F.count_if(F.col("place") == 0), F.max("place")).first()
    links = _of_different(named.where("place = 0").select("id", "u"), count, k)
    if not copies:
        return links.where("rank >= 0")
    ids = named.select("id", "first", "place")
    # a vector's k nearest others and itself have the k + 1 nearest ids, of each not more than its k + 1 least
    near = links.join(ids.where(F.col("place") <= k).select(F.col("first").alias("dst"), "id"), "dst").select("src", F.col("id").alias("dst"), "cosine")
    order = Window.partitionBy("src").orderBy(F.desc("cosine"), "dst")
    near = near.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k + 1)
    near = near.join(ids.select(F.col("first").alias("src"), "id"), "src").where("id != dst").select(F.col("id").alias("src"), "dst", "cosine")
    return near.withColumn("rank", F.row_number().over(order) - 1).where(F.col("rank") < k).select("src", "dst", "rank", "cosine")


def _named(v: DataFrame) -> DataFrame:
    """id, first, place, u: each vector, the least id of those equal to it, and its place among them (from 0)."""
    kind = "float" if dict(v.dtypes)["embedding"] == "array<float>" else "double"
    rows = v.select(F.col("id").cast("long").alias("id"), F.col("embedding").cast(f"array<{kind}>").alias("u"))
    rows = rows.where("id IS NOT NULL AND size(u) > 0 AND NOT exists(u, x -> x IS NULL)").withColumn("h", F.xxhash64("u"))

    def name(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, seen = None, {}
        for batch in batches:
            ids, h = (batch.column(c).to_numpy(zero_copy_only=False) for c in ("id", "h"))
            if not len(ids):
                continue
            lists = batch.column("u")
            ends, flat = lists.offsets.to_numpy() - lists.offsets[0].as_py(), lists.flatten().to_numpy(zero_copy_only=False)
            same = h[1:] == h[:-1]
            first, place = ids.copy(), np.zeros(len(ids), np.int64)
            # rows whose hash stands beside them, and those at the ends, which the next batch may go on with
            for i in np.flatnonzero(np.r_[True, same] | np.r_[same, True]):
                if h[i] != now:
                    now, seen = h[i], {}
                held = seen.setdefault(flat[ends[i] : ends[i + 1]].tobytes(), [ids[i], -1])
                held[1] += 1
                first[i], place[i] = held
            yield pa.RecordBatch.from_arrays([batch.column("id"), pa.array(first), pa.array(place), lists], ["id", "first", "place", "u"])

    return rows.repartition("h").sortWithinPartitions("h", "id").mapInArrow(name, f"id long, first long, place long, u array<{kind}>")


def _of_different(v: DataFrame, count: int, k: int) -> DataFrame:
    """src, dst, rank, cosine of v(id, u), no two of which are equal, and of each with a direction itself, at rank -1."""
    groups = max(1, min(-(-count // GROUP), max(GROUPS, 2 * v.sparkSession.sparkContext.defaultParallelism)))
    most, size, step = k, BLOCK, STEP
    number = np.float32 if dict(v.dtypes)["u"] == "array<float>" else np.float64

    def unit(x: np.ndarray) -> np.ndarray:
        x = x.astype(np.float64)
        x /= np.abs(x).max(axis=1)[:, None]  # so that no square leaves the range of doubles
        x /= np.sqrt((x * x).sum(axis=1))[:, None]
        return x

    def deal(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, size):
                part = batch.slice(start, size)
                ids, h = (part.column(c).to_numpy(zero_copy_only=False) for c in ("id", "h"))
                lists = part.column("u")
                length, flat = np.diff(lists.offsets.to_numpy()), lists.flatten().to_numpy(zero_copy_only=False)
                at = np.repeat(length, length)
                for n in np.unique(length):
                    mine = length == n
                    x = flat[at == n].reshape(-1, n)
                    top = np.abs(x).max(axis=1)
                    good = np.isfinite(top) & (top > 0)
                    x, own, to = x[good], ids[mine][good], h[mine][good] % groups
                    out = [(int(g), 0, int(n), own[to == g].tobytes(), x[to == g].tobytes()) for g in np.unique(to)]
                    out += [(g, 1, int(n), None, None) for g in range(groups)] if len(own) else []
                    for g, kind, n_, a, b in out:
                        yield pa.RecordBatch.from_pylist([{"g": g, "kind": kind, "n": n_, "ids": a or own.tobytes(), "xs": b or x.tobytes()}], schema)

    def best(held: list, ids: np.ndarray, x: np.ndarray) -> None:
        """held: own ids, vectors in single and in double precision, the best cosines and ids so far, in order."""
        own, short, mine, top, who = held
        brief, n = np.ascontiguousarray(x.astype(np.float32).T), x.shape[1]
        wide = (n + 8) * 2.0**-23  # over twice what a cosine of n factors in single precision can be off
        cosines = np.empty((step, len(x)), np.float32)
        for s in range(0, len(own), step):
            cut = slice(s, s + step)
            cos = np.matmul(short[cut], brief, out=cosines[: len(own[cut])])
            least = (top[cut, -1] - wide).astype(np.float32)
            new = np.flatnonzero(least == -np.inf)
            if len(new) and cos.shape[1] > most:  # one more, as a vector may meet itself
                least[new] = np.partition(cos[new], -most - 1, axis=1)[:, -most - 1] - np.float32(2 * wide)
            some = np.flatnonzero(cos.max(axis=1) >= least)
            at = np.flatnonzero(cos[some] >= least[some, None])
            for a in range(0, len(at), size * 8):
                r, c = np.divmod(at[a : a + size * 8], cos.shape[1])
                r = some[r]
                val = np.round(np.einsum("ij,ij->i", mine[s + r], x[c]), 12)
                good = (own[s + r] != ids[c]) & (val >= top[s + r, -1])
                if not good.any():
                    continue
                val, name = val[good], ids[c[good]]
                hit, r = np.unique(r[good], return_inverse=True)
                row = np.concatenate([r, np.repeat(np.arange(len(hit)), most)])
                val = np.concatenate([val, top[s + hit].ravel()])
                name = np.concatenate([name, who[s + hit].ravel()])
                order = np.lexsort((name, -val, row))
                row, val, name = row[order], val[order], name[order]
                place = np.arange(len(row)) - np.searchsorted(row, row)
                keep = place < most
                top[s + hit[row[keep]], place[keep]] = val[keep]
                who[s + hit[row[keep]], place[keep]] = name[keep]

    def result(held: dict) -> Iterator[pa.RecordBatch]:
        for own, _, _, top, who in held.values():
            r, c = np.nonzero(top > -np.inf)
            columns = [np.r_[own, own[r]], np.r_[own, who[r, c]], np.r_[np.full(len(own), -1, np.int32), c.astype(np.int32)], np.r_[np.ones(len(own)), top[r, c]]]
            yield pa.RecordBatch.from_arrays([pa.array(a) for a in columns], ["src", "dst", "rank", "cosine"])

    def compare(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, held, waiting = None, {}, {}
        for batch in batches:
            for i in range(batch.num_rows):
                g, kind, n = (batch.column(c)[i].as_py() for c in ("g", "kind", "n"))
                if g != now:
                    yield from result(held)
                    now, held, waiting = g, {}, {}
                ids = np.frombuffer(batch.column("ids")[i].as_buffer(), np.int64)
                x = np.frombuffer(batch.column("xs")[i].as_buffer(), number).reshape(-1, n)
                if kind == 0:
                    waiting.setdefault(n, []).append((ids.copy(), x.copy()))
                    continue
                if n in waiting:
                    a, b = (np.concatenate(p) for p in zip(*waiting.pop(n), strict=True))
                    b = unit(b)
                    held[n] = [a, b.astype(np.float32), b, np.full((len(a), most), -np.inf), np.full((len(a), most), np.iinfo(np.int64).max)]
                if n in held:
                    best(held[n], ids, unit(x))
        yield from result(held)

    schema = pa.schema([("g", pa.int64()), ("kind", pa.int32()), ("n", pa.int32()), ("ids", pa.binary()), ("xs", pa.binary())])
    dealt = v.withColumn("h", F.pmod(F.xxhash64("id"), F.lit(1 << 31))).mapInArrow(deal, "g long, kind int, n int, ids binary, xs binary")
    return dealt.repartitionById(groups, F.col("g").cast("int")).sortWithinPartitions("g", "kind").mapInArrow(compare, "src long, dst long, rank int, cosine double")
