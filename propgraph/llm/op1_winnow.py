"""Winnowing fingerprints in Spark expressions only.

A text's tokens are its lower-cased form's runs of non-space characters; a run of over LONG = 16 is taken
character by character, so that text without spaces (Chinese, Japanese, base64, minified code) is read at every
offset alike. A rolling (polynomial, prime modulus) hash covers every K = 4 tokens in a row; of each W = 4 hashes in a
row the least is chosen, the rightmost at a tie, and kept with its position. Two texts that share at least
W + K - 1 = 7 tokens in a row share a fingerprint, wherever these stand.

Cases: null text is empty; a text without tokens has an empty fingerprint; with fewer than K tokens
all of them make one hash; with fewer than W hashes they make one window. Two empty fingerprints
are alike (1.0), one empty and one not are unlike (0.0). Null doc_ids come first in the order; rows
of one doc_id, or without any, are ordered by a hash of the text, then the text. Only doc_id and text are
read, so other columns can't clash.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import table, text_of
from .ordered import LEAST, MOST_BUCKETS, PER_BUCKET, range_bucket

K, W, LONG = 4, 4, 16
PRIME, BASE = 2147483647, 1540483477
#: Fixed value: what isn't white space.
INK = r"[^\x20\x09-\x0D]"
TOKEN = rf"(?<!{INK}){INK}{{1,{LONG}}}(?!{INK})|{INK}"


def _pairs(a: str, step: int, f) -> Column:
    """f over the elements `step` apart; the array is shorter by `step`."""
    n = F.greatest(F.size(a) - step, F.lit(0))
    return F.zip_with(F.slice(a, F.lit(1), n), F.slice(a, F.lit(step + 1), n), f)


def _joined(power: int) -> Callable[[Column, Column], Column]:
    """The hash of two stretches in a row from theirs: the first one's moved up by the second one's length."""
    return lambda a, b: (a * power + b) % PRIME


def fingerprints(df: DataFrame, text: str, out: str) -> DataFrame:
    """df with the column `out`: array of (hash << 32 | 2^32 - 1 - position), in text order.

    Hashes of 2 and 4 tokens come from two of half the length, least values likewise. Steps are selects of
    their own, so that no array is made twice."""
    keep = df.columns
    h, g, v, m = (f"_{out}_{x}" for x in "hgvm")
    none = F.array().cast("array<long>")
    token = lambda t: F.conv(F.substring(F.md5(t), 1, 7), 16, 10).cast("long")
    df = df.select(*keep, F.transform(F.regexp_extract_all(F.lower(text), F.lit(TOKEN), 0), token).alias(h))
    power, grams = BASE, h
    for step in (1, 2):
        df = df.select(*keep, h, _pairs(grams, step, _joined(power)).alias(g))
        power, grams = power * power % PRIME, g
    short = F.array(F.aggregate(h, F.lit(0).cast("long"), lambda a, b: (a * BASE + b) % PRIME))
    df = df.select(*keep, F.when(F.size(h) >= K, F.col(g)).when(F.size(h) > 0, short).otherwise(none).alias(g))
    df = df.select(*keep, F.transform(g, lambda x, i: F.shiftleft(x, 32).bitwiseOR(F.lit((1 << 32) - 1) - i)).alias(v))
    least = v
    for step in (1, 2):
        df = df.select(*keep, v, _pairs(least, step, lambda a, b: F.least(a, b)).alias(m))
        least = m
    chosen = F.when(F.size(v) >= W, F.col(m)).when(F.size(v) > 0, F.array(F.array_min(v))).otherwise(none)
    return df.select(*keep, F.array_distinct(chosen).alias(out))


def hashes(fp: str) -> Column:
    return F.array_distinct(F.transform(fp, lambda x: F.shiftright(x, 32)))


def positions(fp: str) -> Column:
    return F.transform(fp, lambda x: F.lit((1 << 32) - 1) - x.bitwiseAND(F.lit((1 << 32) - 1)))


def likeness(a: str, b: str) -> Column:
    """Shared hashes over all hashes (arrays of distinct hashes)."""
    both = F.size(F.array_intersect(a, b))
    return F.when((F.size(a) == 0) & (F.size(b) == 0), F.lit(1.0)).otherwise(both / (F.size(a) + F.size(b) - both).cast("double"))


def digest(fp: str) -> Column:
    return F.concat_ws(":", F.size(fp).cast("string"), F.lpad(F.lower(F.hex(F.xxhash64(fp))), 16, "0"), F.lpad(F.lower(F.hex(F.xxhash64(F.lit("second"), F.col(fp)))), 16, "0"))


def with_next(docs: DataFrame) -> DataFrame:
    """doc_id, text, _bucket, _order, _tie, _ghost: each bucket ends with a copy of the next bucket's first rows.

    Buckets are ranges of the order, so that it needs no task that sees all rows; null ids are dealt to
    buckets before all others by ranges of the hash that orders them."""
    rows = text_of(docs).withColumn("_order", F.coalesce("doc_id", F.lit(LEAST))).withColumn("_tie", F.shiftrightunsigned(F.xxhash64("text"), 11))
    bucket = range_bucket(rows.select("_order"), "_order")
    nulls = rows.where("doc_id IS NULL").count()
    if nulls:
        n = min(MOST_BUCKETS, -(-nulls // PER_BUCKET))
        bucket = F.when(F.col("doc_id").isNull(), F.floor(F.col("_tie") / float(1 << 53) * n) - n).otherwise(bucket)
    rows = rows.withColumn("_bucket", bucket.cast("long"))
    first = sorted((r["_bucket"], *r["f"]) for r in rows.groupBy("_bucket").agg(F.min(F.struct("_order", "_tie")).alias("f")).collect())  # a row a bucket
    ghosts = docs.sparkSession.createDataFrame([(o, t, first[i - 1][0]) for i, (_, o, t) in enumerate(first)], "_order long, _tie long, _before long")
    own = F.struct(F.col("_bucket").alias("b"), F.lit(0).alias("g"))
    places = F.when(F.col("_before").isNull(), F.array(own)).otherwise(F.array(own, F.struct(F.col("_before").alias("b"), F.lit(1).alias("g"))))
    return rows.join(F.broadcast(ghosts), ["_order", "_tie"], "left").select("doc_id", "text", "_order", "_tie", F.explode(places).alias("_p")).select("doc_id", "text", "_order", "_tie", F.col("_p.b").alias("_bucket"), F.col("_p.g").alias("_ghost"))


def compare_neighbours(docs: DataFrame) -> DataFrame:
    """Each text, its half-replaced form and the next document's, with fingerprints and likenesses.

    Texts are shuffled before anything is made of them; the second window finds them dealt out and in order."""
    w = Window.partitionBy("_bucket").orderBy("_ghost", "_order", "_tie", "text")
    rows = with_next(docs)
    rows = fingerprints(rows.select("*", F.lead("text").over(w).alias("_next")), "text", "fp")
    rows = rows.select("*", F.lead("fp").over(w).alias("_next_fp")).where("_ghost = 0")
    rows = rows.withColumn("n_chars", F.char_length("text").cast("long"))
    half = F.floor(F.col("n_chars") / 2).cast("int")
    rows = rows.select("doc_id", "n_chars", "fp", "_next_fp", F.concat(F.substring(F.col("text"), F.lit(1), F.col("n_chars").cast("int") - half), F.substring(F.col("_next"), F.lit(1), half)).alias("edited"))
    rows = fingerprints(rows, "edited", "efp")
    rows = rows.select("*", hashes("fp").alias("_a"), hashes("efp").alias("_b"), hashes("_next_fp").alias("_c"))
    return rows.select("doc_id", "n_chars", "edited", "fp", "efp", likeness("_a", "_b").alias("near_edited"), likeness("_a", "_c").alias("near_next"))


def op1_winnowing(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = compare_neighbours(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), digest("fp").alias("fingerprint"), digest("efp").alias("edited_fingerprint"), "near_edited", "near_next", F.size("fp").alias("n_prints"))


def op1_likeness(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The columns of op1_winnowing that SQL can say: all but the digests of the fingerprints."""
    rows = compare_neighbours(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "n_chars", F.sha2("edited", 256).alias("edited_sha256"), "near_edited", "near_next", F.size("fp").cast("long").alias("n_prints"))


_POWERS = [pow(BASE, K - 1 - j, PRIME) for j in range(K)]
ORACLE = f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS t, row_number() OVER (ORDER BY doc_id) AS k, count(*) OVER () AS n FROM documents),
e AS MATERIALIZED (SELECT a.doc_id, b.doc_id AS after, a.t, left(a.t, length(a.t) - length(a.t) // 2) || left(b.t, length(a.t) // 2) AS edited FROM d a JOIN d b ON b.k = a.k % a.n + 1),
r AS (SELECT doc_id, v, list_filter(regexp_split_to_array(lower(s), '[\\x20\\x09-\\x0D]+'), lambda z: z <> '') AS runs FROM (SELECT doc_id, 0 AS v, t AS s FROM e UNION ALL SELECT doc_id, 1, edited FROM e) y),
o AS (SELECT doc_id, v, flatten(list_transform(runs, lambda z: CASE WHEN length(z) <= {LONG} THEN [z] ELSE string_split(z, '') END)) AS tokens FROM r),
x AS (SELECT doc_id, v, list_transform(tokens, lambda z: ('0x' || substr(md5(z), 1, 7))::BIGINT) AS codes, len(tokens) AS n FROM o WHERE len(tokens) > 0),
c AS (SELECT doc_id, v, n, unnest(codes) AS c, generate_subscripts(codes, 1) AS i FROM x),
g AS (SELECT doc_id, v, i, n, ({" + ".join(f"lead(c, {j}) OVER w * {p} % {PRIME}" for j, p in enumerate(_POWERS))}) % {PRIME} AS h FROM c WINDOW w AS (PARTITION BY doc_id, v ORDER BY i)),
h AS (SELECT doc_id, v, i, n - {K - 1} AS m, (h << 32) | ({(1 << 32) - 1} - (i - 1)) AS p FROM g WHERE i <= n - {K - 1}
  UNION ALL SELECT doc_id, v, 1, 1, (list_reduce(codes, lambda a, b: (a * {BASE} + b) % {PRIME}) % {PRIME} << 32) | {(1 << 32) - 1} FROM x WHERE n < {K}),
f AS MATERIALIZED (SELECT DISTINCT doc_id, v, least AS p FROM (SELECT doc_id, v, i, m, min(p) OVER (PARTITION BY doc_id, v ORDER BY i ROWS BETWEEN CURRENT ROW AND {W - 1} FOLLOWING) AS least FROM h) q WHERE i <= greatest(m - {W - 1}, 1)),
s AS MATERIALIZED (SELECT DISTINCT doc_id, v, p >> 32 AS h FROM f), z AS (SELECT doc_id, v, count(*) AS k FROM s GROUP BY doc_id, v),
pairs AS (SELECT doc_id, 'edited' AS what, doc_id AS other, 1 AS ov FROM e UNION ALL SELECT doc_id, 'next', after, 0 FROM e),
shared AS (SELECT r.doc_id, r.what, count(*) AS k FROM pairs r JOIN s a ON a.doc_id = r.doc_id AND a.v = 0 JOIN s b ON b.doc_id = r.other AND b.v = r.ov AND b.h = a.h GROUP BY r.doc_id, r.what),
near AS (SELECT r.doc_id, r.what, CASE WHEN coalesce(a.k, 0) + coalesce(b.k, 0) = 0 THEN 1.0::DOUBLE ELSE coalesce(o.k, 0) / (coalesce(a.k, 0) + coalesce(b.k, 0) - coalesce(o.k, 0))::DOUBLE END AS likeness
  FROM pairs r LEFT JOIN z a ON a.doc_id = r.doc_id AND a.v = 0 LEFT JOIN z b ON b.doc_id = r.other AND b.v = r.ov LEFT JOIN shared o ON o.doc_id = r.doc_id AND o.what = r.what)
SELECT e.doc_id, length(t)::BIGINT AS n_chars, sha256(edited) AS edited_sha256, a.likeness AS near_edited, b.likeness AS near_next, coalesce((SELECT count(*) FROM f WHERE f.doc_id = e.doc_id AND v = 0), 0)::BIGINT AS n_prints
FROM e JOIN near a ON a.doc_id = e.doc_id AND a.what = 'edited' JOIN near b ON b.doc_id = e.doc_id AND b.what = 'next'
"""
