"""Measures of cost and accuracy."""

from __future__ import annotations

import statistics
import time
import zlib
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.placement import ends, place, routing
from ..plans.scope import JoinShape


def timed(make: Callable[[], DataFrame], trials: int = 10) -> dict:
    """Mean and standard deviation of the seconds that computing a frame takes."""
    took = []
    for _ in range(trials):
        began = time.time()
        make().write.format("noop").mode("overwrite").save()
        took.append(time.time() - began)
    return {"mean": statistics.mean(took), "sd": statistics.stdev(took) if trials > 1 else 0.0, "trials": took}


def replication(edges: DataFrame, strategy: str, p: int) -> DataFrame:
    """One row: replicas of a full round, their mean and maximum a vertex."""
    per = ends(edges, place(strategy, p)).groupBy("id").agg(F.count("*").alias("r"))
    return per.agg(F.lit(strategy).alias("strategy"), F.lit(p).cast("long").alias("p"), F.coalesce(F.sum("r"), F.lit(0)).alias("replicas"), F.round(F.avg("r"), 6).alias("mean_replicas"), F.max("r").alias("max_replicas"))


def balance(edges: DataFrame, strategy: str, p: int) -> DataFrame:
    """One row: edges of the fullest partition over the mean."""
    per = edges.groupBy(place(strategy, p).alias("pid")).agg(F.count("*").alias("n"))
    return per.agg(F.lit(strategy).alias("strategy"), F.lit(p).cast("long").alias("p"), F.max("n").alias("most"), F.round(F.max("n") * p / F.sum("n"), 6).alias("max_over_mean"))


def shipped(routes: DataFrame, changed: DataFrame) -> DataFrame:
    """One row: vertex replicas shipped when only the changed ids are."""
    return routes.join(changed.select("id"), "id", "left_semi").agg(F.coalesce(F.sum(F.size("pids")), F.lit(0)).cast("long").alias("shipped"))


def shape_traffic(placed: DataFrame) -> DataFrame:
    """shape, shipped: vertex replicas of a full round under each join shape."""
    need = {JoinShape.NONE: None, JoinShape.SOURCE: ["src"], JoinShape.TARGET: ["dst"], JoinShape.BOTH: ["src", "dst"]}
    out = None
    for shape, sides in need.items():
        if sides is None:
            one = placed.sparkSession.createDataFrame([(shape.value, 0)], "shape string, shipped long")
        else:
            rows = placed.select(F.explode(F.array(*[F.struct(F.lit(s).alias("side"), F.col(s).alias("id")) for s in sides])).alias("e"), "pid").distinct()
            one = rows.agg(F.lit(shape.value).alias("shape"), F.count("*").alias("shipped"))
        out = one if out is None else out.unionByName(one)
    return out


def varint_bytes(x: Column | str) -> Column:
    """Bytes of a non-negative number at 7 bits a byte."""
    x = F.col(x) if isinstance(x, str) else x
    n = F.lit(1)
    for k in range(1, 9):
        n = n + (F.shiftright(x, 7 * k) > 0).cast("int")
    return n


def packing(df: DataFrame) -> DataFrame:
    """Bytes of id blocks compressed row by row and column by column: rows_bytes, columns_bytes a block."""
    names = df.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import numpy as np

        for b in batches:
            cols = np.column_stack([np.asarray(b.column(c), dtype="<i8") for c in names])
            by_row = len(zlib.compress(np.ascontiguousarray(cols).tobytes(), 1))
            by_col = len(zlib.compress(np.ascontiguousarray(cols.T).tobytes(), 1))
            yield pa.RecordBatch.from_arrays([pa.array([b.num_rows]), pa.array([by_row]), pa.array([by_col])], names=["n", "rows_bytes", "columns_bytes"])

    return df.mapInArrow(run, "n long, rows_bytes long, columns_bytes long")


def max_abs_diff(a: DataFrame, b: DataFrame, column: str) -> float:
    x, y = a.select("id", F.col(column).alias("x")), b.select("id", F.col(column).alias("y"))
    return x.join(y, "id").agg(F.max(F.abs(F.col("x") - F.col("y")))).first()[0] or 0.0


def l1_distance(a: DataFrame, b: DataFrame, column: str) -> float:
    x, y = a.select("id", F.col(column).alias("x")), b.select("id", F.col(column).alias("y"))
    return x.join(y, "id", "full").agg(F.sum(F.abs(F.coalesce("x", F.lit(0.0)) - F.coalesce("y", F.lit(0.0))))).first()[0] or 0.0


def top_k_overlap(a: DataFrame, b: DataFrame, column: str, k: int) -> float:
    x, y = (d.orderBy(F.col(column).desc(), "id").limit(k).select("id") for d in (a, b))
    return x.intersect(y).count() / k


def edges_touched(edges: DataFrame, active: DataFrame, fresh: str = "either") -> int:
    from ..operators.graph import _fresh

    return _fresh(edges, active, fresh).count()


def job_traffic(placed: DataFrame, rounds: int, shape: JoinShape) -> DataFrame:
    """One row: replicas shipped by a job of full rounds."""
    return shape_traffic(placed).where(F.col("shape") == shape.value).select("shape", (F.col("shipped") * rounds).alias("shipped"))


def routes_of(edges: DataFrame, strategy: str, p: int) -> DataFrame:
    return routing(edges.withColumn("pid", place(strategy, p)))


def cached_bytes(*frames: DataFrame) -> int:
    """Bytes that the frames take in Spark's cache, which they leave again."""
    spark = frames[0].sparkSession

    def used() -> int:
        return sum(x.memSize() + x.diskSize() for x in spark.sparkContext._jsc.sc().getRDDStorageInfo())

    before = used()
    for df in frames:
        df.persist().count()
    got = used() - before
    for df in frames:
        df.unpersist(True)
    return got


def layout_bytes(vertices: DataFrame, edges: DataFrame, results: int = 2) -> dict[str, int]:
    """Cache for `results` graphs that differ in vertex columns only, with one set of edges for all or one each."""
    v, e = cached_bytes(vertices.select("id")), cached_bytes(edges.select("src", "dst"))
    return {"shared": results * v + e, "own": results * (v + e)}


def scaling(seconds: dict[int, float]) -> dict[int, float]:
    """Speed-up over the least number of cores, from seconds by cores."""
    one = seconds[min(seconds)]
    return {k: one / s for k, s in sorted(seconds.items())}
