"""The page-ranking pipeline: parse, link, rank, and join the best with their texts."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources import workloads
from ..sources.shared import remove, shared_path, written
from .algorithms import pagerank
from .graph import Layout, PropertyGraph


def _best(ranks: DataFrame, pages: DataFrame, k: int) -> DataFrame:
    """The k best with their texts: pages are reduced to the winners before anything is taken out of their html."""
    top = ranks.select("id", F.round("pr", 9).alias("pr")).orderBy(F.col("pr").desc(), "id").limit(k)
    rows = pages.select(F.col("page_id").alias("id"), "url", "html").join(F.broadcast(top), "id")
    return rows.select("id", F.round("pr", 6).alias("pr"), "url", F.regexp_extract("html", r"<title>([^<]*)</title>", 1).alias("title"), F.length("html").cast("long").alias("html_chars"))


def rank_pages(spark: SparkSession, sf_dir: str, k: int = 20, rounds: int = 20) -> DataFrame:
    """One application: no file between the stages, and texts fetched for the winners only."""
    g = workloads.weblinks(spark, sf_dir)
    return _best(pagerank(g, rounds), workloads.table(spark, sf_dir, "pages"), k)


def rank_pages_by_files(spark: SparkSession, sf_dir: str, k: int = 20, rounds: int = 20) -> DataFrame:
    """The same with files handed from stage to stage; the first stage's are deleted when the second has read them."""
    base = shared_path(spark, "handoff")
    g = workloads.weblinks(spark, sf_dir)
    g.vertices.select("id").write.parquet(f"{base}/vertices")
    g.edges.select("src", "dst").write.parquet(f"{base}/edges")
    h = PropertyGraph(spark.read.parquet(f"{base}/vertices"), spark.read.parquet(f"{base}/edges"), Layout())
    ranks = written(pagerank(h, rounds), "handoff-ranks")
    remove(spark, base)
    return _best(ranks, workloads.table(spark, sf_dir, "pages"), k)


def stage_seconds(spark: SparkSession, sf_dir: str, k: int = 20, rounds: int = 20) -> dict[str, float]:
    """Seconds of parsing the links, ranking, and joining the best with their texts, each made whole; and their total."""
    out, began = {}, time.time()

    def lap(name: str) -> None:
        nonlocal began
        out[name], began = round(time.time() - began, 3), time.time()

    g = workloads.weblinks(spark, sf_dir)
    v, e = written(g.vertices.select("id"), "stage-vertices"), written(g.edges.select("src", "dst"), "stage-edges")
    lap("parse")
    ranks = written(pagerank(PropertyGraph(v, e, Layout()), rounds), "stage-ranks")
    lap("rank")
    _best(ranks, workloads.table(spark, sf_dir, "pages"), k).collect()
    lap("join")
    return out | {"total": round(sum(out.values()), 3)}
