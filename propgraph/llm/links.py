"""Connected classes of links between ids, by repeated min-labelling of stars, all in Spark.

Large-star and small-star rounds in turn: every vertex's larger neighbours, then its smaller ones,
are linked to the least of its neighbourhood, until no link changes; then each links to its class's
least id. Minima are combined before the exchange, and are tables when the links are joined with them, so
that a hub's links can be split over tasks. Every round ends with a table in shared storage; the
former round's is deleted."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import release, written


def classes(links: DataFrame, a: str = "a", b: str = "b", files: int | None = None) -> DataFrame:
    """id, least: for every linked id other than its class's least, that least. files: at most, of each table."""
    now = written(links.select(F.greatest(a, b).alias("hi"), F.least(a, b).alias("lo")).where("hi != lo").distinct(), "links", files)
    before = None
    while True:
        both = now.unionByName(now.select(F.col("lo").alias("hi"), F.col("hi").alias("lo")))
        least = written(both.groupBy("hi").agg(F.min("lo").alias("m")).select("hi", F.least("hi", "m").alias("m")), "least", files)
        large = written(both.join(least, "hi").where("lo > hi").select(F.col("lo").alias("hi"), F.col("m").alias("lo")).where("hi != lo").distinct(), "large-stars", files)
        down = written(large.groupBy("hi").agg(F.min("lo").alias("m")), "down", files)
        small = large.join(down, "hi").select(F.explode(F.array(F.struct("hi", F.col("m").alias("lo")), F.struct(F.col("lo").alias("hi"), F.col("m").alias("lo")))).alias("e")).select("e.hi", "e.lo").where("hi != lo").distinct()
        last, now = now, written(small, "links", files)
        release(last, least, large, down)
        sums = now.agg(F.count("*"), F.sum(F.xxhash64("hi", "lo").cast("decimal(38,0)")))
        state = tuple(sums.first())
        if state == before:
            return now.select(F.col("hi").alias("id"), F.col("lo").alias("least"))
        before = state
