"""Mixing sources to target weights by Poisson replication, in Spark expressions.

Each source has a target share of the mixed corpus's documents; a document of it is repeated k times,
k Poisson with mean rate = share * documents / documents of the source. k comes from inverting that
distribution at a uniform number made from a hash of doc_id, text length and seed, so every run and
every retry draws the same. Copies are then ordered globally by a hash of document and copy number.

Targets: given shares by source (others get none), or, by default, shares in proportion to
documents ** temperature, here 0.5, which lifts small sources. A rate above `most_rate` is split: the
sum of m independent draws at rate / m is Poisson with the whole rate, so no tail is cut off; the
tables of the distribution reach where a double cannot tell the rest from one.

Cases: a null source is a source of its own; null texts and doc_ids are kept; repeated rows draw the
same count, each for itself; an empty table stays empty; all other columns are carried along
untouched. Columns copy_no and mix_key are added; a column of such a name in the input is replaced.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table, written

SEED, TEMPERATURE, MOST_RATE, STEPS = 20240607, 0.5, 8.0, 48
#: Sources whose rates (about 400 bytes each) are broadcast; with more, a source's documents are dealt to SALTS parts.
MOST_BROADCAST, SALTS = 20_000, 64


def unit(*parts: Column | str) -> Column:
    """A uniform number in [0, 1): the first 48 bits of an MD5 over the parts."""
    h = F.md5(F.concat_ws("|", *parts))
    return F.conv(F.substring(h, 1, 12), 16, 10).cast("long") / F.lit(float(1 << 48))


def rates(docs: DataFrame, targets: dict[str, float] | None = None, temperature: float = TEMPERATURE) -> DataFrame:
    """_source, n, rate: one row a source."""
    n = docs.groupBy(F.col("source").alias("_source")).agg(F.count("*").alias("n"))
    if targets is None:
        share = n.withColumn("_w", F.pow(F.col("n").cast("double"), F.lit(temperature)))
    else:
        given = docs.sparkSession.createDataFrame([(k, float(v)) for k, v in targets.items()], "_source string, _w double")
        share = n.join(F.broadcast(given), "_source", "left").fillna(0.0, ["_w"])
    total = share.agg(F.sum("_w").alias("_sum"), F.sum("n").alias("_all"))
    return share.crossJoin(F.broadcast(total)).select("_source", "n", F.when(F.col("_sum") > 0, F.round(F.col("_w") / F.col("_sum") * F.col("_all") / F.col("n"), 9)).otherwise(F.lit(0.0)).alias("rate"))


def cumulative(rate: Column) -> Column:
    """P(X <= 0), P(X <= 1), ... for rates up to MOST_RATE: what is left after STEPS is under 2^-60."""
    first = F.exp(-rate)
    start = F.struct(first.alias("p"), F.array(first).alias("c"))
    step = F.aggregate(F.sequence(F.lit(1), F.lit(STEPS)), start, lambda a, k: F.struct((a["p"] * rate / k).alias("p"), F.concat(a["c"], F.array(F.element_at(a["c"], -1) + a["p"] * rate / k)).alias("c")))
    return step["c"]


def replicate(docs: DataFrame, targets: dict[str, float] | None = None, seed: int = SEED, temperature: float = TEMPERATURE) -> DataFrame:
    """docs with each row as often as it is drawn, plus copy_no and mix_key, in global order of mix_key."""
    keep = [c for c in docs.columns if c not in ("copy_no", "mix_key")]
    by = rates(docs, targets, temperature).withColumn("_m", F.greatest(F.ceil(F.col("rate") / MOST_RATE), F.lit(1)).cast("int"))
    by = written(by.select("_source", "_m", cumulative(F.col("rate") / F.col("_m")).alias("_cdf")), "rates")
    ids = [F.coalesce(F.col("doc_id").cast("string"), F.lit("")), F.coalesce(F.length("text"), F.lit(-1)).cast("string")]
    # rates have a row a source: few enough are sent to every task, so that no text moves before the copies are made
    few = by.count() <= MOST_BROADCAST
    parts = 1 if few else SALTS
    by = F.broadcast(by.withColumn("_salt", F.lit(0))) if few else by.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(parts - 1))))
    salt = F.lit(0) if few else F.pmod(F.xxhash64(*ids), F.lit(parts)).cast("int")
    rows = docs.select(*keep, salt.alias("_of")).join(by, F.col("source").eqNullSafe(F.col("_source")) & (F.col("_of") == F.col("_salt")))
    draw = F.transform(F.sequence(F.lit(1), F.col("_m")), lambda i: unit(*ids, F.lit(str(seed)), i.cast("string")))
    count = F.aggregate(draw, F.lit(0), lambda a, u: a + F.size(F.filter("_cdf", lambda c: c <= u)))
    rows = rows.withColumn("_k", count).where("_k > 0").select(*keep, F.explode(F.sequence(F.lit(1), F.col("_k"))).alias("copy_no"))
    rows = rows.withColumn("mix_key", F.md5(F.concat_ws("|", *ids, F.lit(str(seed)), F.lit("order"), F.col("copy_no").cast("string"))))
    return rows.repartitionByRange("mix_key").sortWithinPartitions("mix_key")


def op8_poisson_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = replicate(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "source", F.col("copy_no").cast("long").alias("copy_no"), "mix_key", F.length("text").cast("long").alias("n_chars"), F.md5("text").alias("text_md5"))


def draw_counts(rate: float, u: list[float]) -> int:
    """One document's count by plain inversion, for tests."""
    m = max(1, math.ceil(rate / MOST_RATE))
    total = 0
    for x in u[:m]:
        p = c = math.exp(-rate / m)
        k = 0
        while x >= c and k <= STEPS:
            k += 1
            p *= rate / m / k
            c += p
        total += k
    return total


ORACLE = f"""
WITH n AS (SELECT source, count(*) AS n FROM documents GROUP BY source),
t AS (SELECT sum(sqrt(n::DOUBLE)) AS s, sum(n) AS a FROM n),
r AS (SELECT source, round(sqrt(n::DOUBLE) / s * a / n, 9) AS rate FROM n, t),
m AS (SELECT source, rate, greatest(ceil(rate / {MOST_RATE}), 1)::BIGINT AS m FROM r),
steps AS (SELECT source, m, k, exp(-rate / m) * pow(rate / m, k) / gamma(k + 1) AS p FROM m, (SELECT unnest(range(0, {STEPS + 1})) AS k) s),
cdf AS (SELECT source, m, k, sum(p) OVER (PARTITION BY source ORDER BY k) AS c FROM steps),
draws AS (SELECT d.doc_id, d.source, d.text, i,
  ('0x' || substr(md5(coalesce(d.doc_id::VARCHAR, '') || '|' || coalesce(length(d.text), -1)::VARCHAR || '|{SEED}|' || i::VARCHAR), 1, 12))::BIGINT / {float(1 << 48)!r} AS u
  FROM documents d JOIN m ON d.source IS NOT DISTINCT FROM m.source, LATERAL (SELECT unnest(range(1, m.m + 1)) AS i) x),
counts AS (SELECT w.doc_id, w.source, w.text, w.i, count(*) FILTER (c.c <= w.u) AS k FROM draws w JOIN cdf c ON w.source IS NOT DISTINCT FROM c.source GROUP BY ALL),
per AS (SELECT doc_id, source, text, sum(k)::BIGINT AS k FROM counts GROUP BY ALL)
SELECT doc_id, source, j AS copy_no,
  md5(coalesce(doc_id::VARCHAR, '') || '|' || coalesce(length(text), -1)::VARCHAR || '|{SEED}|order|' || j::VARCHAR) AS mix_key,
  length(text)::BIGINT AS n_chars, md5(text) AS text_md5
FROM per, LATERAL (SELECT unnest(range(1, k + 1)) AS j) y
"""
