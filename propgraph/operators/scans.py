"""Edges at rest in clusters, and the choice between reading all of them and those of active vertices only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.placement import spread
from ..plans.scope import choose_access
from ..sources.shared import remove, shared_path, shuffles_dropped


class ClusteredEdges:
    """Edge files by clusters of the source's hash, sorted by source, and a second copy by target as its index.

    An index scan reads the clusters that hold an active vertex (partition pruning: the other files aren't
    opened), and within them the row groups whose range of ids fits; a sequential scan reads one whole copy."""

    def __init__(self, edges: DataFrame, clusters: int = 64) -> None:
        self.spark, self.clusters, self.columns = edges.sparkSession, clusters, edges.columns
        self.path, self.rows = {}, {}
        for side in ("src", "dst"):
            self.path[side] = shared_path(self.spark, f"edges-by-{side}")
            with shuffles_dropped(self.spark):
                edges.withColumn("cluster", self.cluster(side)).repartition("cluster").sortWithinPartitions("cluster", side).write.partitionBy("cluster").parquet(self.path[side])
            self.rows[side] = {r["cluster"]: r["n"] for r in self.copy(side).groupBy("cluster").agg(F.count("*").alias("n")).collect()}  # a number a cluster

    def cluster(self, column: str):
        return (spread(column) % self.clusters).cast("int")

    def copy(self, side: str) -> DataFrame:
        kinds = ", ".join([*(f"`{c}` long" for c in self.columns), "cluster int"])
        return self.spark.read.schema(kinds).parquet(self.path[side])

    def scan(self, active: DataFrame | None, n_active: int, n: int, fresh: str = "either", threshold: float = 0.8) -> tuple[DataFrame, str, int]:
        """(edges with a fresh end, access, rows read). active None: everything is."""
        how = "scan" if active is None else choose_access(n_active, n, threshold)
        if active is None:
            return self.copy("src").select(*self.columns), how, sum(self.rows["src"].values())
        if how == "scan":
            rows = self.copy("src")
            for side in ("src", "dst"):
                rows = rows.join(active.select(F.col("id").alias(side), F.lit(True).alias(f"_{side}")), side, "left")
            test = {"src": "_src", "dst": "_dst", "either": "_src OR _dst", "both": "_src AND _dst"}[fresh]
            return rows.where(test).select(*self.columns), how, sum(self.rows["src"].values())
        near = sorted(r[0] for r in active.select(self.cluster("id").alias("c")).distinct().collect())  # at most a number a cluster
        out, read = None, 0
        for side in ("src", "dst") if fresh in ("either", "both") else (fresh,):
            rows = self.copy(side).where(F.col("cluster").isin(near)).select(*self.columns)
            rows = rows.join(active.select(F.col("id").alias(side)), side, "left_semi").select(*self.columns)
            read += sum(self.rows[side].get(c, 0) for c in near)
            if out is None:
                out = rows
            elif fresh == "both":
                out = out.join(active.select(F.col("id").alias("dst")), "dst", "left_semi").select(*self.columns)
            else:  # by target only what the copy by source hasn't given
                out = out.unionByName(rows.join(active.select(F.col("id").alias("src")), "src", "left_anti").select(*self.columns))
        return out, how, read

    def drop(self) -> None:
        for p in self.path.values():
            remove(self.spark, p)
