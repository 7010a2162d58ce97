"""Graphs on disk and edges in text."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.graph import Layout, PropertyGraph


def save(g: PropertyGraph, path: str, mode: str = "errorifexists") -> None:
    g.vertices.write.mode(mode).parquet(f"{path}/vertices")
    g.edges.write.mode(mode).parquet(f"{path}/edges")
    spark = g.vertex_rows.sparkSession
    spark.createDataFrame([(json.dumps({"strategy": g.layout.strategy, "partitions": g.layout.partitions}),)], "value string").coalesce(1).write.mode(mode).text(f"{path}/layout")


def load(spark: SparkSession, path: str) -> PropertyGraph:
    layout = Layout(**json.loads(spark.read.text(f"{path}/layout").first()[0]))
    return PropertyGraph(spark.read.parquet(f"{path}/vertices"), spark.read.parquet(f"{path}/edges"), layout)


def save_bucketed(g: PropertyGraph, name: str, buckets: int) -> None:
    """Tables name_vertices and name_edges, bucketed so that the source join moves nothing."""
    g.vertices.write.bucketBy(buckets, "id").sortBy("id").mode("overwrite").saveAsTable(f"{name}_vertices")
    g.edges.write.bucketBy(buckets, "src").sortBy("src").mode("overwrite").saveAsTable(f"{name}_edges")


def load_bucketed(spark: SparkSession, name: str) -> PropertyGraph:
    return PropertyGraph(spark.table(f"{name}_vertices"), spark.table(f"{name}_edges"), Layout("source"))


def parse_edges(lines: DataFrame) -> DataFrame:
    """src, dst of lines of two ids in a column `value`; other lines, such as comments, are left out."""
    part = F.split(F.trim("value"), r"\s+")
    rows = lines.select(F.expr("try_cast(split(trim(value), '\\\\s+')[0] AS BIGINT)").alias("src"), F.try_element_at(part, F.lit(2)).try_cast("long").alias("dst"))
    return rows.where("src IS NOT NULL AND dst IS NOT NULL")


def read_edge_list(spark: SparkSession, path: str) -> PropertyGraph:
    return PropertyGraph.from_edges(parse_edges(spark.read.text(path)))
