"""Near-duplicate classes by circulant MinHash, with every link confirmed on whole shingle sets.

Signature: one permutation scrambles a shingle's hash, a second one, shifted circularly by 1, 2, ... K,
gives all K coordinates (both permute the 32-bit numbers). BANDS bands of ROWS coordinates make the
buckets: a pair of similarity 0.75 shares none with probability (1 - 0.75^5)^52, under one in a million.

Links: texts with equal sets are one representative. In each bucket every representative is compared
with a centre, the one that shares most buckets with most others; classes are formed; what is in
other classes than the centre's gets a centre of its own, up to STARS times; at last, pairs of a bucket
whose ends are still in different classes are compared, unless too few of their shingles occur in any
other text, or too many bits of their parity maps differ, for them to be near; both tests are exact, so
only the banding itself can miss a pair. So a bucket of one class emits no pairs, however large it is. A comparison
reads whole texts, at most CHUNK of them with each copy of their centre's, whatever a group's size.

A set's node is the least doc_id that has it; where an id has rows of different texts, its further sets
get numbers of their own from 2^62 up, which are linked to the id and never name a class.

Cases: null text is empty; without words a document has no shingle, links with nothing and is kept;
repeated rows and rows of different text that share a doc_id are linked by it, each with its own n_shingles; a null
doc_id takes no part (component_id null, kept true); an empty table gives no row. Only doc_id and text are read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import U64, blocks, mix64, release, table, text_of, workers_can_import, written
from .links import classes
from .shingles import shingle_sets

ROWS, BANDS, THRESHOLD, CHUNK, STARS = 5, 52, 75, 64, 1
#: Candidates' ids that are sent to every task to fetch their texts (about 60 bytes each); more are joined by shuffle.
MOST_BROADCAST = 200_000
#: From here up lie the numbers of further sets of one doc_id.
FURTHER = 1 << 62
#: 64-bit words of a parity map.
PARITY = 32
#: Rows of a file of ids, and the fewest files that a table may be kept to.
FILE_ROWS, FEWEST_FILES = 20_000, 16
K = ROWS * BANDS


def scramble(x: np.ndarray, a: int, b: int) -> np.ndarray:
    """A permutation of the 32-bit numbers, in place."""
    x ^= x >> np.uint32(16)
    x *= np.uint32(a)
    x ^= x >> np.uint32(15)
    x *= np.uint32(b)
    x ^= x >> np.uint32(16)
    return x


def signatures(hashes: np.ndarray, offsets: np.ndarray, k: int = K) -> np.ndarray:
    """(documents, k) least shifted-permutation values; documents without shingles get the largest number."""
    n = len(offsets) - 1
    out = np.full((n, k), 0xFFFFFFFF, np.uint32)
    at = np.flatnonzero(np.diff(offsets))
    if not len(at):
        return out
    first = offsets[at]
    with np.errstate(over="ignore"):
        base = scramble((hashes >> U64(32)).astype(np.uint32) ^ hashes.astype(np.uint32), 0x7FEB352D, 0x846CA68B)
        for i in range(k):
            out[at, i] = np.minimum.reduceat(scramble(base + np.uint32(i), 0x21F0AAAD, 0xD35A2D97), first)
    return out


def bands_of(sig: np.ndarray, rows: int = ROWS) -> np.ndarray:
    n, k = sig.shape
    part = sig.reshape(n, k // rows, rows).astype(U64)
    with np.errstate(over="ignore"):
        h = np.broadcast_to(np.arange(1, k // rows + 1, dtype=U64) * U64(0x9E3779B97F4A7C15), (n, k // rows)).copy()
        for j in range(rows):
            h = mix64(h * U64(0xD6E8FEB86659FD93) + part[:, :, j])
    return h.view(np.int64)


def parity_maps(hashes: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """(documents, PARITY) longs in which every shingle of a document flips one bit.

    The maps of two sets differ in at most as many bits as there are shingles that only one set has."""
    n = len(offsets) - 1
    out = np.zeros((n, PARITY), U64)
    doc = np.repeat(np.arange(n), np.diff(offsets))
    np.bitwise_xor.at(out, (doc, ((hashes >> U64(6)) % U64(PARITY)).astype(np.int64)), U64(1) << (hashes & U64(63)))
    return out.view(np.int64)


def odd_bits(a: str, b: str, words: range) -> Column:
    """In how many bits of these words two parity maps differ."""
    total = F.lit(0)
    for i in words:
        total = total + F.bit_count(F.col(a)[i].bitwiseXOR(F.col(b)[i]))
    return total


def features(docs: DataFrame) -> DataFrame:
    """doc_id, tag (of the text), n_shingles, set_key (128 bits), bands: one row a row."""
    workers_can_import(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import hashlib

        for batch in blocks(batches, most=1 << 18):
            hashes, off = shingle_sets(batch.column("text"))
            n = np.diff(off)
            sig = signatures(hashes, off)
            bands = bands_of(sig)
            keys = [hashlib.blake2b(np.ascontiguousarray(hashes[a:b]), digest_size=16).digest() for a, b in zip(off[:-1], off[1:], strict=True)]
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(n) + 1) * BANDS, pa.int32()), pa.array(bands.ravel()))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("tag"), pa.array(n), pa.array(keys, pa.binary()), lists], names=["doc_id", "tag", "n_shingles", "set_key", "bands"])

    return text_of(docs, F.xxhash64(F.coalesce("text", F.lit(""))).alias("tag")).mapInArrow(run, "doc_id long, tag long, n_shingles long, set_key binary, bands array<long>")


def confirm(pairs: DataFrame, texts: DataFrame, threshold: int = THRESHOLD, files: int | None = None) -> DataFrame:
    """The pairs (a, b) whose sets have 100 * shared >= threshold * all; texts: doc_id, text, one row an id."""
    workers_can_import(pairs.sparkSession)
    # both sides of the join are tables, so that the pairs of a frequent centre can be split over tasks
    hot = written(pairs.groupBy("a").agg(F.count("*").alias("n")).select("a", F.ceil(F.col("n") / CHUNK).cast("int").alias("parts")), "centres", files)
    ends = pairs.join(hot, "a").select("a", "b", F.pmod(F.xxhash64("b"), F.col("parts")).cast("int").alias("part"))
    member = ends.join(texts.withColumnRenamed("doc_id", "b"), "b").select("a", "part", F.lit(1).alias("side"), "b", "text")
    centre = hot.join(texts.withColumnRenamed("doc_id", "a"), "a").select("a", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)).alias("part"), F.lit(0).alias("side"), F.lit(None).cast("long").alias("b"), "text")
    rows = member.unionByName(centre).repartition("a", "part").sortWithinPartitions("a", "part", "side", "b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        centre = np.zeros(0, U64)
        for batch in blocks(batches):
            hashes, off = shingle_sets(batch.column("text"))
            a, side, b = (batch.column(c).to_pylist() for c in ("a", "side", "b"))
            left, right = [], []
            for i in range(batch.num_rows):
                s = hashes[off[i] : off[i + 1]]
                if side[i] == 0:
                    centre = s.copy()
                    continue
                if 100 * min(len(s), len(centre)) < threshold * max(len(s), len(centre)):
                    continue
                at = np.searchsorted(centre, s)
                shared = int((centre[np.minimum(at, len(centre) - 1)] == s).sum())
                if 100 * shared >= threshold * (len(s) + len(centre) - shared):
                    left.append(a[i])
                    right.append(b[i])
            yield pa.RecordBatch.from_arrays([pa.array(left, pa.int64()), pa.array(right, pa.int64())], names=["a", "b"])

    return rows.mapInArrow(run, "a long, b long")


def set_nodes(known: DataFrame, files: int | None = None) -> DataFrame:
    """node, rep, tag, n, bands: one row a distinct set; rep and tag name a row whose text has it."""
    key = F.xxhash64("set_key")
    twins = written(known.groupBy(F.col("doc_id").alias("rep")).agg(F.min(key).alias("own"), F.max(key).alias("last")).where("own != last").select("rep", "own"), "twins", files)
    first = F.min(F.struct("doc_id", "tag")).alias("f")
    sets = known.groupBy("set_key").agg(first, F.first("n_shingles").alias("n"), F.first("bands").alias("bands")).select("set_key", F.col("f.doc_id").alias("rep"), F.col("f.tag").alias("tag"), "n", "bands")
    if twins.isEmpty():
        return sets.withColumn("node", F.col("rep"))
    further = F.shiftrightunsigned(key, 2).bitwiseOR(F.lit(FURTHER))
    return sets.join(twins, "rep", "left").withColumn("node", F.when(F.col("own").isNull() | (F.col("own") == key), F.col("rep")).otherwise(further)).drop("own")


def near_duplicates(docs: DataFrame, threshold: int = THRESHOLD) -> DataFrame:
    """doc_id, n_shingles, component_id, kept: one row a row."""
    every = written(features(docs), "shingle-features")
    # a table of a row a document, or fewer, needs no more files than this
    files = max(FEWEST_FILES, -(-every.count() // FILE_ROWS))
    known = every.where("n_shingles > 0 AND doc_id IS NOT NULL")
    # equal sets: one representative, which also carries the bands
    sets = written(set_nodes(known, files), "shingle-sets", files)
    same = known.join(sets.select("set_key", "node"), "set_key").where("doc_id != node").select(F.col("node").alias("a"), F.col("doc_id").alias("b"))
    links = written(same, "equal-sets", files)
    rows = sets.select(F.col("node").alias("rep"), "n", F.explode("bands").alias("band"))
    sizes = written(rows.groupBy("band").agg(F.count("*").alias("m")).where("m > 1"), "bucket-sizes", 4 * files)
    buckets = written(rows.join(sizes, "band"), "buckets")
    # the text that shares most buckets with most others is nearest to the middle of its group
    score = written(buckets.groupBy("rep").agg(F.sum("m").alias("s")), "scores", files)
    texts = written(_texts(docs, sets.join(score.select(F.col("rep").alias("node")), "node").select("rep", "tag", "node"), score.count()), "candidate-texts", files)
    release(sets, sizes)
    member = written(buckets.drop("m").join(score, "rep"), "scored-buckets")
    release(buckets, score)
    best = F.max_by("rep", F.struct("s", -F.col("rep")))
    pivots = written(member.groupBy("band").agg(best.alias("pivot")), "pivots", files)
    held = written(member.withColumn("c", F.col("rep")).join(pivots, "band"), "centred-buckets")
    release(pivots)
    for step in range(STARS):
        stars = held.where("c != pc" if step else "rep != pivot").select(F.least("pivot", "rep").alias("x"), F.greatest("pivot", "rep").alias("y"), F.col("pivot").alias("a"), F.col("rep").alias("b"))
        stars = written(stars.dropDuplicates(["x", "y"]).select("a", "b"), "stars", files)
        before, links = links, written(links.unionByName(confirm(stars, texts, threshold, files)), "links", files)
        release(before, stars)
        label = classes(links, files=files)
        now = member.join(label.select(F.col("id").alias("rep"), "least"), "rep", "left").select("band", "rep", "n", "s", F.coalesce("least", "rep").alias("c"))
        # of a bucket in several classes, the next centre is the best text outside the last centre's class
        named = held.select("band", "pivot").distinct().join(label.select(F.col("id").alias("pivot"), "least"), "pivot", "left").select("band", F.coalesce("least", "pivot").alias("old"))
        outside = written(now.join(written(named, "named-buckets", files), "band").where("c != old"), "outside", files)
        rest = written(outside.groupBy("band").agg(best.alias("pivot"), F.max_by("c", F.struct("s", -F.col("rep"))).alias("pc")), "next-pivots", files)
        before, held = held, written(now.join(rest, "band"), "mixed-buckets")
        release(before, outside, rest)
        if held.isEmpty():
            break
    release(member)
    held = written(able(held, texts, threshold), "able-buckets", files)
    every_band = held.groupBy("rep").agg(F.collect_set("band").alias("all"))
    held = written(held.join(every_band, "rep").join(parities(held, texts), "rep"), "mapped-buckets", files)
    x, y = (held.select("band", F.col("rep").alias(i), F.col("n").alias(f"n{i}"), F.col("c").alias(f"c{i}"), F.col("t").alias(f"t{i}"), F.col("all").alias(f"all{i}"), F.col("parity").alias(f"q{i}")) for i in "ab")
    shared = F.least("ta", "tb")
    # shared >= threshold % of all is the same as: no more than this part of both sizes lies in one set only
    apart = lambda words: odd_bits("qa", "qb", words) * (100 + threshold) <= (F.col("na") + F.col("nb")) * (100 - threshold)
    fits = (shared * 100 >= (F.col("na") + F.col("nb") - shared) * threshold) & (F.col("ca") != F.col("cb")) & (F.col("a") < F.col("b")) & apart(range(8)) & apart(range(PARITY))
    # a pair that shares several buckets comes from the least of them
    more = x.join(y, (x["band"] == y["band"]) & fits & (F.array_min(F.array_intersect("alla", "allb")) == x["band"])).select("a", "b")
    more = written(more, "further-pairs", 4 * files)
    release(held)
    found = written(confirm(more, texts, threshold, files), "further-links", files)
    release(more, texts)
    label = classes(links.unionByName(found), files=files)
    release(links, found)
    out = every.join(least_ids(label, known).withColumnRenamed("id", "doc_id"), "doc_id", "left")
    component = F.coalesce("least", "doc_id")
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"))


def least_ids(label: DataFrame, ids: DataFrame) -> DataFrame:
    """label with each class named by its least doc_id, also where doc_ids lie among the numbers of further sets."""
    odd = label.where(F.col("least") >= FURTHER)
    if odd.isEmpty():
        return label
    members = odd.unionByName(odd.select(F.col("least").alias("id"), "least").distinct())
    real = members.join(ids.select(F.col("doc_id").alias("id")).distinct(), "id", "left_semi").groupBy("least").agg(F.min("id").alias("real"))
    return label.where(F.col("least") < FURTHER).unionByName(members.join(real, "least").select("id", F.col("real").alias("least")))


def able(held: DataFrame, texts: DataFrame, threshold: int) -> DataFrame:
    """held with t, each text's shingles that any other of these texts has; texts that can't link are left out.

    Two texts share at most the lesser t of shingles, so a text that is mostly its own links with none."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            hashes, off = shingle_sets(batch.column("text"))
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.asarray(batch.column("doc_id")), np.diff(off))), pa.array(hashes.view(np.int64))], names=["rep", "h"])

    some = held.select(F.col("rep").alias("doc_id")).distinct()
    rows = some.join(texts, "doc_id").select("doc_id", "text").mapInArrow(run, "rep long, h long")
    own = rows.groupBy("h").agg(F.min("rep").alias("rep"), F.count("*").alias("k")).where("k = 1").groupBy("rep").agg(F.count("*").alias("own"))
    held = held.join(own, "rep", "left").withColumn("t", F.col("n") - F.coalesce("own", F.lit(0))).drop("own")
    return held.where(F.col("t") * 100 >= F.col("n") * threshold)


def parities(held: DataFrame, texts: DataFrame) -> DataFrame:
    """rep, parity: the parity map of each text in held."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            maps = parity_maps(*shingle_sets(batch.column("text")))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(maps) + 1) * PARITY, pa.int32()), pa.array(maps.ravel()))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), lists], names=["rep", "parity"])

    some = held.select(F.col("rep").alias("doc_id")).distinct()
    return some.join(texts, "doc_id").select("doc_id", "text").mapInArrow(run, "rep long, parity array<long>")


def _texts(docs: DataFrame, wanted: DataFrame, n: int) -> DataFrame:
    """doc_id (the node), text: of each wanted (rep, tag, node) a row's text."""
    rows = text_of(docs, F.xxhash64(F.coalesce("text", F.lit(""))).alias("tag"))
    few = wanted.select(F.col("rep").alias("doc_id"), "tag", "node")
    rows = rows.join(F.broadcast(few) if n <= MOST_BROADCAST else few, ["doc_id", "tag"])
    return rows.groupBy("node").agg(F.first("text").alias("text")).select(F.col("node").alias("doc_id"), "text")


def op6_minhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


ORACLE = f"""
WITH RECURSIVE w AS (SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\\x20\\x09-\\x0D]+'), lambda x: x <> '') AS ws FROM documents),
s AS MATERIALIZED (SELECT DISTINCT doc_id, unnest(CASE WHEN len(ws) >= 5 THEN list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i + 4], ' ')) WHEN len(ws) > 0 THEN [array_to_string(ws, ' ')] ELSE [] END) AS g FROM w),
k AS MATERIALIZED (SELECT doc_id, count(*) AS k FROM s GROUP BY doc_id),
m AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS n FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY ALL),
p AS MATERIALIZED (SELECT a, b FROM m JOIN k x ON x.doc_id = a JOIN k y ON y.doc_id = b WHERE 100 * n >= {THRESHOLD} * (x.k + y.k - n)),
e AS MATERIALIZED (SELECT a, b FROM p UNION SELECT b, a FROM p),
cc(id, component) USING KEY (id) AS (SELECT doc_id, doc_id FROM documents UNION (SELECT e.b AS id, min(cc.component) AS component FROM cc JOIN e ON e.a = cc.id JOIN recurring.cc AS r ON r.id = e.b WHERE cc.component < r.component GROUP BY e.b))
SELECT d.doc_id, coalesce(k.k, 0)::BIGINT AS n_shingles, component AS component_id, component = d.doc_id AS kept FROM documents d JOIN cc ON cc.id = d.doc_id LEFT JOIN k ON k.doc_id = d.doc_id
"""
