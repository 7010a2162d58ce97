"""Where a loop's edges lie: they are dealt out once and stay there, vertex rows come to them.

SourceSite: edges lie by their source, as vertices lie by id; a message that reads no target then moves
nothing but its fold. VertexCut: edges lie by a placement of both ends; a routing table tells which
partitions need a vertex, and a view of vertex copies at the edges is kept up to date by shipping only
what has changed since it was last shipped."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..plans.placement import place
from ..plans.scope import Triplet
from ..sources.shared import checkpoint_dir

FRESH = "_fresh"


def kept(df: DataFrame) -> DataFrame:
    """Cuts the lineage by a reliable checkpoint in the folder of spark.checkpoint.dir. The frame's partitioning and order stay known."""
    checkpoint_dir(df.sparkSession)
    out = df.checkpoint()
    return _without_estimate(out) if _digits(out) > 63 else out


def _digits(df: DataFrame) -> int:
    """Binary digits of the planner's estimate of a frame's bytes."""
    return df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes().bit_length()


def _without_estimate(df: DataFrame) -> DataFrame:
    """A checkpointed frame without the estimate of its bytes that it takes over from its plan.

    A join's estimate is the product of both sides', so in a loop the number's digits multiply by the round,
    until planning takes longer than the work."""
    spark = df.sparkSession
    jvm, plan, none = spark.sparkContext._jvm, df._jdf.queryExecution().analyzed(), spark.sparkContext._jvm.scala.Option.empty()
    bare = jvm.org.apache.spark.sql.execution.LogicalRDD(plan.output(), plan.rdd(), plan.outputPartitioning(), plan.outputOrdering(), False, none, df._jdf.sparkSession(), none, none)
    return DataFrame(jvm.org.apache.spark.sql.classic.Dataset.ofRows(df._jdf.sparkSession(), bare), spark)


def by_key(df: DataFrame, key: str, *order: str, n: int | None = None) -> DataFrame:
    """Dealt out by a hash of the key and sorted, once."""

    def dealt(df: DataFrame) -> DataFrame:
        return kept(df.repartition(*([n] if n else []), key).sortWithinPartitions(key, *order))

    out = dealt(df)
    # a column that is the key under another name may stand for it in what the checkpoint knows; a second one knows no such name
    known = out._jdf.queryExecution().executedPlan().outputPartitioning().toString()
    return out if known.startswith(f"hashpartitioning({key}#") else dealt(out)


def messages(rows: DataFrame, down: Column | None, up: Column | None, fold, several: bool = False) -> DataFrame:
    """id, msg: the messages of joined edge rows to either end, folded by receiver; nulls are no messages."""
    if down is not None and up is not None:
        rows = rows.select(F.explode(F.array(F.struct(F.col("dst").alias("id"), down.alias("msg")), F.struct(F.col("src").alias("id"), up.alias("msg")))).alias("m")).select("m.id", "m.msg")
    else:
        rows = rows.select(F.col("dst" if down is not None else "src").alias("id"), (down if down is not None else up).alias("msg"))
    if several:
        rows = rows.select("id", F.explode("msg").alias("msg"))
    return rows.where("msg IS NOT NULL").groupBy("id").agg(fold(F.col("msg")).alias("msg"))


def keep_fresh(rows: DataFrame, fresh: str | None) -> DataFrame:
    """Of rows with the marks _src and _dst (null: not fresh), those that `fresh` lets through."""
    test = {"src": "_src", "dst": "_dst", "either": "_src OR _dst", "both": "_src AND _dst"}
    return rows.where(test[fresh]) if fresh else rows


class SourceSite:
    """Edges by source. Reads of the source, and fresh None or 'src', need no Exchange of edges or vertices."""

    def __init__(self, edges: DataFrame) -> None:
        self.edges = by_key(edges, "src", "dst")

    def joined(self, t: Triplet, state: DataFrame, fresh: str | None) -> DataFrame:
        """state: vertex rows by id with the mark _fresh."""
        rows = self.edges
        if t.src.read or fresh:
            part = state.where(FRESH) if fresh else state
            rows = rows.join(part.select(F.col("id").alias("src"), *[F.col(c).alias(f"{t.src.prefix}{c}") for c in sorted(t.src.read)]), "src")
        return rows


class VertexCut:
    """Edges by a placement; routes says to which partitions a vertex goes, as a source or as a target."""

    def __init__(self, edges: DataFrame, strategy: str | Column = "grid", partitions: int | None = None) -> None:
        self.p = partitions or int(edges.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        pid = place(strategy, self.p) if isinstance(strategy, str) else strategy
        self.edges = by_key(edges.withColumn("pid", pid.cast("int")), "pid", "src", n=self.p)
        ends = F.explode(F.array(F.struct(F.col("src").alias("id"), F.lit(True).alias("as_src")), F.struct(F.col("dst").alias("id"), F.lit(False).alias("as_src"))))
        pairs = self.edges.select("pid", ends.alias("e")).groupBy("e.id", "pid").agg(F.max("e.as_src").alias("as_src"), F.max(~F.col("e.as_src")).alias("as_dst"))
        self.routes = by_key(pairs, "id")
        self.view: DataFrame | None = None

    def needed(self, sides: tuple[str, ...]) -> DataFrame:
        """id, pid: where vertices are needed that are read on these sides."""
        test = F.lit(False)
        for s in sides:
            test = test | F.col(f"as_{s}")
        return self.routes.where(test).select("id", "pid")

    def counts(self, sides: tuple[str, ...]) -> DataFrame:
        """id, copies: how many partitions a vertex is shipped to; the cost of shipping it once."""
        return self.needed(sides).groupBy("id").agg(F.count("*").alias("copies"))

    def ship(self, rows: DataFrame, sides: tuple[str, ...]) -> DataFrame:
        """Vertex rows (by id) to the partitions that need them: the one Exchange of a round besides the fold's."""
        return self.needed(sides).join(rows, "id").repartition(self.p, "pid")

    def refresh(self, state: DataFrame, columns: list[str], sides: tuple[str, ...], incremental: bool = True) -> DataFrame:
        """pid, id, columns, _fresh: the view of the copies. state: vertex rows by id with the mark _fresh.

        Incremental: only rows marked fresh travel and are laid over the kept view; else all rows travel."""
        if not incremental or self.view is None:
            full = self.ship(state.select("id", FRESH, *columns), sides)
            if not incremental:
                return full
            self.view = kept(full)
        else:
            new = self.ship(state.where(FRESH).select("id", *[F.col(c).alias(f"_new_{c}") for c in columns], F.lit(True).alias("_hit")), sides)
            rows = self.view.drop(FRESH).join(new.hint("shuffle_hash"), ["pid", "id"], "left")
            hit = F.coalesce("_hit", F.lit(False))
            self.view = kept(rows.select("id", "pid", hit.alias(FRESH), *[F.when(hit, F.col(f"_new_{c}")).otherwise(F.col(c)).alias(c) for c in columns]))
        return self.view

    def active(self, view: DataFrame, fresh: str) -> DataFrame:
        """Edges whose ends are marked fresh in the view as `fresh` asks."""
        rows, marks = self.edges, view.where(FRESH).select("pid", "id", F.lit(True).alias("_m"))
        for side in ("src", "dst"):
            if fresh in (side, "either", "both"):
                rows = rows.join(marks.withColumnsRenamed({"id": side, "_m": f"_{side}"}).hint("shuffle_hash"), ["pid", side], "left")
        return keep_fresh(rows, fresh).drop("_src", "_dst")

    def joined(self, t: Triplet, view: DataFrame, fresh: str | None, access: str) -> DataFrame:
        """Edge rows with the copies they read. access 'index': edges without a fresh end are left out before that join, 'scan': after."""
        rows = self.active(view, fresh) if fresh and access == "index" else self.edges
        for side, part in (("src", t.src), ("dst", t.dst)):
            after = fresh if access == "scan" and fresh in (side, "either", "both") else None
            if part.read or after:
                mark = [F.col(FRESH).alias(f"_{side}")] if after else []
                copies = view.select("pid", F.col("id").alias(side), *[F.col(c).alias(f"{part.prefix}{c}") for c in sorted(part.read)], *mark)
                rows = rows.join(copies.hint("shuffle_hash"), ["pid", side])
        return keep_fresh(rows, fresh if access == "scan" else None)


class Overlay:
    """Rounds in which few vertices still change: what changed since state and view were last written lies over them.

    A round reads the kept tables, but writes only vertices that have got a message since then, and their copies."""

    def __init__(self, site: VertexCut, state: DataFrame, columns: list[str], reads: list[str], sides: tuple[str, ...]) -> None:
        """state: vertex rows by id, of which the ones marked _fresh have not been shipped."""
        self.site, self.base, self.columns, self.reads, self.sides = site, state.drop(FRESH), columns, reads, sides
        self.rows, self.view = state.where(FRESH), None

    def _over(self, base: DataFrame, late: DataFrame, on: list[str], columns: list[str], how: str = "left") -> DataFrame:
        """base with the columns of late where it has a row, and that row's other columns."""
        late = late.withColumnsRenamed({c: f"_new_{c}" for c in columns}).withColumn("_hit", F.lit(True))
        rows = base.join(late, on, how)
        return rows.withColumns({c: F.when(F.col("_hit"), F.col(f"_new_{c}")).otherwise(F.col(c)) for c in columns}).drop("_hit", *[f"_new_{c}" for c in columns])

    def joined(self, t: Triplet, fresh: str) -> DataFrame:
        """Edges with a fresh end, with the copies they read; ships the fresh rows first."""
        new = self.site.ship(self.rows.where(FRESH).select("id", *self.reads), self.sides).select("pid", "id", *self.reads, F.lit(True).alias(FRESH))
        if self.view is not None:
            new = new.unionByName(self.view.join(new.select("pid", "id"), ["pid", "id"], "left_anti").withColumn(FRESH, F.lit(False)))
        self.view = kept(new.repartition(self.site.p, "pid"))
        rows = self.site.active(self.view, fresh)
        for side, part in (("src", t.src), ("dst", t.dst)):
            if part.read:
                names = {c: f"{part.prefix}{c}" for c in sorted(part.read)}
                base, late = (v.select("pid", F.col("id").alias(side), *[F.col(c).alias(k) for c, k in names.items()]) for v in (self.site.view, self.view))
                rows = self._over(rows.hint("shuffle_hash").join(base, ["pid", side]), late.hint("shuffle_hash"), ["pid", side], list(names.values()))
        return rows

    def receive(self, sent: DataFrame) -> DataFrame:
        """Vertices with a message in sent(id, msg) and those that lie over the state, as they are now."""
        return self._over(self.base.join(sent.join(self.rows.select("id"), "id", "full"), "id"), self.rows.drop(FRESH, "copies"), ["id"], self.columns)

    def state(self) -> DataFrame:
        return self._over(self.base, self.rows.drop(FRESH, "copies"), ["id"], self.columns)
