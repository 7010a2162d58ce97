"""From raw documents to packed token sequences: five stages, each a table between them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from propgraph.llm import op3_harmonic, op4_language, op6_minhash, op8_poisson, op9_line_chunks
from propgraph.llm.common import release, written
from propgraph.llm.tokens import vocabulary

#: The least score of a document that stays: with four languages 0.25 is a blind guess; of sf0.1's documents none is below 0.5.
LEAST_SCORE = 0.4


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a language go: no text, no letter, or the network's score below LEAST_SCORE; a null lang becomes the predicted one.

    Where nothing could be learned (no labelled row), documents with a letter stay as they are. An empty table stays empty."""
    net = op4_language.train(docs)
    if net is None:
        return docs.where(F.col("text").rlike(r"\p{L}"))
    got = op4_language.label_languages(docs, net, carry=True).where((F.col("lang_pred") != op4_language.UND) & (F.col("score") >= LEAST_SCORE))
    full = [F.coalesce("row.lang", "lang_pred").alias(c) if c == "lang" else F.col(f"row.`{c}`").alias(c) for c in docs.columns]
    return got.select(*full)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that stand in a run of two or more at an earlier place go; no document goes, null texts stay null."""
    return op9_line_chunks.remove_passages(docs).select(*docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each class of near copies one document stays, that of the least id; rows without an id or without words all stay.

    Of several rows of the id that stays, one does, the first by text."""
    gone = op6_minhash.near_duplicates(docs).where("NOT kept").select("doc_id").distinct()
    left = docs.join(gone, "doc_id", "left_anti").select(*docs.columns)
    named = F.col("doc_id").isNotNull() & F.col("text").rlike(r"[^\x20\x09-\x0D]")
    twice = written(docs.where(named).groupBy("doc_id").agg(F.count("*").alias("_n")).where("_n > 1").select("doc_id"), "repeated-ids")
    if twice.isEmpty():
        return left
    some = left.where(named).join(twice, "doc_id", "left_semi").select(*docs.columns)
    one = some.withColumn("_k", F.row_number().over(Window.partitionBy("doc_id").orderBy("text"))).where("_k = 1").drop("_k")
    rest = left.where(~F.coalesce(named, F.lit(False))).unionByName(left.where(named).join(twice, "doc_id", "left_anti").select(*docs.columns))
    return rest.unionByName(one)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources at their target shares; a document stands there as often as it was drawn."""
    return op8_poisson.replicate(docs).select(*docs.columns)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of sequences of at most 2048 tokens; an empty table gives none, a null text its end id."""
    return op3_harmonic.pack_documents(docs, vocabulary("byte_bpe_50k.json"))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("language", language),
    ("line_dedup", line_dedup),
    ("near_dedup", near_dedup),
    ("mix", mix),
    ("packing", packing),
]
#: Language prediction and tokenization can't be said in SQL; the stages are tested one by one.
ORACLE_SQL: str | None = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages, each written and reread; a stage's table is deleted when the next one has been written."""
    docs, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    for name, stage in STAGES[:-1]:
        now = written(stage(spark, docs, sf_dir), f"pipeline-{name}")
        release(before)
        docs = before = now
    return STAGES[-1][1](spark, docs, sf_dir)
