"""Removal of repeated content-defined line chunks, in Spark expressions only.

A text's lines get hashes; a rolling hash over each two lines in a row ends a chunk where it is 0
modulo 4, so an inserted line moves only the chunk borders near it. Chunks of two or more lines that
occur more than once in all texts keep their first place (least doc_id, then position) and go from
every other place, after their bytes have been compared with the first place's.

remove_passages() finds what chunks miss: each two lines in a row that stand at an earlier place too
(other document, or at least two lines before) go, wherever the chunk borders fall, so a repeated run of
two or more lines goes whole. These lines are told by their SHA-256, since fetching the texts of both places
again would shuffle all text a second time. The first place of every line stays. Two lines without any letter or digit
don't count as a repeat of their own.

Cases: null text has no line and stays null; an empty text is one empty line; chunks of a single line
are never removed; rows that share doc_id and text are one document (all keep the same rest); null
doc_ids come before others; an empty table stays empty. Other columns are carried along untouched.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table, written
from .ordered import LEAST

PRIME, BASE, BORDER, LEAST_LINES = 268435399, 92821, 4, 2
CONTENT = r"[\p{L}\p{N}]"


def _line_hash(line: Column) -> Column:
    return F.conv(F.substring(F.md5(line), 1, 7), 16, 10).cast("long") % PRIME


def with_chunks(df: DataFrame, lines: Column) -> DataFrame:
    """df with _chunks: the lines of each chunk, in order. In steps, so that no array is made twice."""
    keep = df.columns
    df = df.select(*keep, lines.alias("_lines"))
    df = df.select(*keep, "_lines", F.transform("_lines", _line_hash).alias("_h"))
    before = F.concat(F.array(F.lit(0).cast("long")), F.slice("_h", F.lit(1), F.size("_h") - 1))
    df = df.select(*keep, "_lines", F.zip_with(before, "_h", lambda a, b: (a * BASE + b) % PRIME).alias("_h"))
    ends = F.transform("_h", lambda r, i: F.when((r % BORDER == 0) | (i == F.size("_h") - 1), i + 1))
    df = df.select(*keep, "_lines", F.concat(F.array(F.lit(0)), F.filter(ends, lambda e: e.isNotNull())).alias("_b"))
    cut = F.transform(F.slice("_b", F.lit(2), F.size("_b") - 1), lambda e, i: F.slice("_lines", F.element_at("_b", i + 1) + 1, e - F.element_at("_b", i + 1)))
    return df.select(*keep, cut.alias("_chunks"))


def _who(docs: DataFrame, *more: Column) -> DataFrame:
    return docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(LEAST)).alias("_id"), F.xxhash64("text").alias("_tag"), *more)


def repeats(docs: DataFrame) -> DataFrame:
    """_id, _tag, _gone: the positions of chunks to remove, of documents that have any."""
    texts = _who(docs, F.col("text").alias("_t")).where("_t IS NOT NULL")
    # the outer form: for the inner one Spark infers a filter and repeats the array expressions in it
    every = with_chunks(texts, F.split("_t", "\n", -1)).select("_id", "_tag", F.posexplode_outer("_chunks").alias("_pos", "_c")).where(F.size("_c") >= LEAST_LINES)
    every = every.select("_id", "_tag", "_pos", F.array_join("_c", "\n").alias("_text")).withColumn("_key", F.md5("_text"))
    place = F.struct("_id", "_pos", "_tag")
    first = every.groupBy("_key").agg(F.min(place).alias("_first"), F.max(place).alias("_last")).where("_first != _last").select("_key", "_first")
    # both joins are with tables, and always by shuffle, so that the rows of a frequent chunk can be split over tasks
    marked = written(every.join(written(first, "first-chunks").hint("merge"), "_key"), "repeated-chunks")
    kept = written(marked.where(F.col("_first") == place).select("_key", F.col("_text").alias("_kept")).dropDuplicates(["_key"]), "kept-chunks")
    gone = marked.where(F.col("_first") != place).join(kept.hint("merge"), "_key").where(F.col("_text") == F.col("_kept"))
    return gone.groupBy("_id", "_tag").agg(F.collect_set("_pos").alias("_gone"))


def remove_repeats(docs: DataFrame) -> DataFrame:
    """docs with text replaced by what is left, plus n_lines, n_chunks, n_removed_chunks, n_removed_lines."""
    added = ("n_lines", "n_chunks", "n_removed_chunks", "n_removed_lines")
    keep = [c for c in docs.columns if c not in added]
    rows = _who(docs, F.struct(*keep).alias("_row")).join(written(repeats(docs), "gone-chunks"), ["_id", "_tag"], "left")
    rows = with_chunks(rows.select("_row", F.coalesce("_gone", F.array().cast("array<int>")).alias("_gone")), F.split("_row.text", "\n", -1))
    rows = rows.select("_row", "_gone", "_chunks", F.filter("_chunks", lambda c, i: ~F.array_contains("_gone", i)).alias("_left"))
    lines = lambda c: F.when(F.col(c).isNull(), F.lit(0)).otherwise(F.aggregate(c, F.lit(0), lambda a, x: a + F.size(x))).cast("long")
    text = F.when(F.size("_gone") == 0, F.col("_row.text")).otherwise(F.array_join(F.flatten("_left"), "\n"))
    full = [text.alias("text") if c == "text" else F.col(f"_row.`{c}`").alias(c) for c in keep]
    return rows.select(*full, lines("_chunks").alias("n_lines"), F.coalesce(F.size("_chunks"), F.lit(0)).cast("long").alias("n_chunks"), F.size("_gone").cast("long").alias("n_removed_chunks"), (lines("_chunks") - lines("_left")).alias("n_removed_lines"))


def passages(docs: DataFrame) -> DataFrame:
    """_id, _tag, _gone: the positions of lines that start two repeated lines, of documents that have any."""
    texts = _who(docs, F.col("text").alias("_t")).where("_t IS NOT NULL")
    lines = texts.select("_id", "_tag", F.split("_t", "\n", -1).alias("_l"))
    key = lambda a, b: F.when(F.concat(a, b).rlike(CONTENT), F.unhex(F.sha2(F.concat(a, F.lit("\n"), b), 256)))
    keys = F.zip_with(F.slice("_l", F.lit(1), F.size("_l") - 1), F.slice("_l", F.lit(2), F.size("_l") - 1), key)
    every = lines.select("_id", "_tag", F.posexplode_outer(keys).alias("_pos", "_key")).where("_key IS NOT NULL")
    place = F.struct("_id", "_tag", "_pos")
    first = every.groupBy("_key").agg(F.min(place).alias("_first"), F.max(place).alias("_last")).where("_first != _last").select("_key", "_first")
    first = written(first, "first-lines").hint("merge")
    apart = (F.col("_first._id") != F.col("_id")) | (F.col("_first._tag") != F.col("_tag")) | (F.col("_pos") >= F.col("_first._pos") + 2)
    return every.join(first, "_key").where(apart).groupBy("_id", "_tag").agg(F.collect_set("_pos").alias("_gone"))


def remove_passages(docs: DataFrame) -> DataFrame:
    """docs with text replaced by what is left, plus n_lines, n_removed_lines."""
    keep = [c for c in docs.columns if c not in ("n_lines", "n_removed_lines")]
    rows = _who(docs, F.struct(*keep).alias("_row")).join(written(passages(docs), "gone-lines").hint("merge"), ["_id", "_tag"], "left")
    rows = rows.select("_row", "_gone", F.split("_row.text", "\n", -1).alias("_l"))
    rows = rows.select("_row", "_gone", "_l", F.array_except(F.sequence(F.lit(0), F.size("_l") - 1), F.concat("_gone", F.transform("_gone", lambda i: i + 1))).alias("_at"))
    text = F.when(F.col("_gone").isNull(), F.col("_row.text")).otherwise(F.array_join(F.transform("_at", lambda i: F.element_at("_l", i + 1)), "\n"))
    full = [text.alias("text") if c == "text" else F.col(f"_row.`{c}`").alias(c) for c in keep]
    n = F.when(F.col("_l").isNull(), F.lit(0)).otherwise(F.size("_l")).cast("long")
    return rows.select(*full, n.alias("n_lines"), F.when(F.col("_gone").isNull(), F.lit(0).cast("long")).otherwise(n - F.size("_at")).alias("n_removed_lines"))


def op9_line_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = remove_passages(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "n_lines", "n_removed_lines", F.sha2("text", 256).alias("clean_sha256"))


def op9_line_chunk_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = remove_repeats(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "n_lines", "n_chunks", "n_removed_chunks", "n_removed_lines", F.sha2("text", 256).alias("clean_sha256"))


ORACLE = f"""
WITH l AS (SELECT doc_id, string_split(text, chr(10)) AS x FROM documents WHERE text IS NOT NULL),
e AS (SELECT doc_id, i, x[i] AS line, len(x) AS n, ('0x' || substr(md5(x[i]), 1, 7))::BIGINT % {PRIME} AS h FROM l, LATERAL (SELECT unnest(range(1, len(x) + 1)) AS i) y),
r AS (SELECT *, (coalesce(lag(h) OVER (PARTITION BY doc_id ORDER BY i), 0) * {BASE} + h) % {PRIME} % {BORDER} = 0 AS ends FROM e),
c AS (SELECT *, coalesce(sum(ends::INT) OVER (PARTITION BY doc_id ORDER BY i ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS pos FROM r),
k AS (SELECT doc_id, pos, count(*) AS lines, string_agg(line, chr(10) ORDER BY i) AS body FROM c GROUP BY doc_id, pos),
f AS (SELECT *, lines >= {LEAST_LINES} AND row_number() OVER (PARTITION BY body ORDER BY doc_id, pos) > 1 AS gone FROM k)
SELECT doc_id, sum(lines)::BIGINT AS n_lines, count(*)::BIGINT AS n_chunks, count(*) FILTER (gone)::BIGINT AS n_removed_chunks,
  coalesce(sum(lines) FILTER (gone), 0)::BIGINT AS n_removed_lines,
  sha256(coalesce(string_agg(body, chr(10) ORDER BY pos) FILTER (NOT gone), '')) AS clean_sha256
FROM f GROUP BY doc_id
"""
PASSAGES_ORACLE = f"""
WITH l AS (SELECT doc_id, string_split(text, chr(10)) AS x FROM documents WHERE text IS NOT NULL),
e AS (SELECT doc_id, i, x[i] AS line, x[i + 1] AS below, len(x) AS n FROM l, LATERAL (SELECT unnest(range(1, len(x) + 1)) AS i) y),
p AS (SELECT doc_id, i, first_value(doc_id) OVER w AS d0, first_value(i) OVER w AS i0 FROM e WHERE i < n AND regexp_matches(line || below, '{CONTENT}') WINDOW w AS (PARTITION BY line, below ORDER BY doc_id, i)),
g AS (SELECT doc_id, i FROM p WHERE d0 <> doc_id OR i >= i0 + 2),
c AS (SELECT e.*, h.i IS NOT NULL AS gone FROM e LEFT JOIN (SELECT doc_id, i FROM g UNION SELECT doc_id, i + 1 FROM g) h ON h.doc_id = e.doc_id AND h.i = e.i)
SELECT doc_id, count(*)::BIGINT AS n_lines, count(*) FILTER (gone)::BIGINT AS n_removed_lines, sha256(coalesce(string_agg(line, chr(10) ORDER BY i) FILTER (NOT gone), '')) AS clean_sha256
FROM c GROUP BY doc_id
"""
