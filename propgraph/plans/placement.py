"""Where edges go: placement by functions of both ends, routing tables and replicas."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: A prime modulus and multiplier whose products stay in a BIGINT.
PRIME, MULTIPLIER = 2147483647, 1640531527
STRATEGIES = ("grid", "source", "target", "pair", "pair_undirected")


def spread(x: Column | str) -> Column:
    x = F.col(x) if isinstance(x, str) else x
    return F.pmod(F.pmod(x, F.lit(PRIME)) * MULTIPLIER, F.lit(PRIME))


def place(strategy: str, p: int, src: Column | str = "src", dst: Column | str = "dst") -> Column:
    """The partition of an edge. grid: rows by source, columns by target, so a vertex lies in at most r + c - 1 cells."""
    s, d = spread(src), spread(dst)
    if strategy == "grid":
        r = int(p**0.5)
        c = -(-p // r)
        return ((s % r) * c + d % c) % p
    if strategy == "source":
        return s % p
    if strategy == "target":
        return d % p
    if strategy == "pair":
        return (s * 31 + d) % PRIME % p
    if strategy == "pair_undirected":
        return (F.least(s, d) * 31 + F.greatest(s, d)) % PRIME % p
    raise ValueError(f"no placement {strategy!r}")


def place_sql(strategy: str, p: int, src: str = "src", dst: str = "dst") -> str:
    """The same in SQL, for non-negative ids."""
    s, d = (f"((({x}) % {PRIME}) * {MULTIPLIER} % {PRIME})" for x in (src, dst))
    r = int(p**0.5)
    c = -(-p // r)
    return {"grid": f"(({s} % {r}) * {c} + {d} % {c}) % {p}", "source": f"{s} % {p}", "target": f"{d} % {p}", "pair": f"({s} * 31 + {d}) % {PRIME} % {p}", "pair_undirected": f"(least({s}, {d}) * 31 + greatest({s}, {d})) % {PRIME} % {p}"}[strategy]


def grid_bound(p: int) -> int:
    r = int(p**0.5)
    return r - (-p // r) - 1


def ends(edges: DataFrame, pid: Column | str = "pid") -> DataFrame:
    """id, pid: every vertex with each partition that holds an edge of it."""
    return edges.select(F.explode(F.array("src", "dst")).alias("id"), F.col(pid).alias("pid") if isinstance(pid, str) else pid.alias("pid")).distinct()


def routing(edges: DataFrame) -> DataFrame:
    """id, pids: the routing table of placed edges."""
    return ends(edges).groupBy("id").agg(F.array_sort(F.collect_set("pid")).alias("pids"))


def routing_bitmaps(edges: DataFrame) -> DataFrame:
    """pid, bucket, bitmap: the same by partition, compressed; for ids from 0 up."""
    return ends(edges).groupBy("pid", F.bitmap_bucket_number("id").alias("bucket")).agg(F.bitmap_construct_agg(F.bitmap_bit_position("id")).alias("bitmap"))


class ReplicaView:
    """Vertex rows at the edge partitions, of which a refresh ships only changed ones."""

    def __init__(self, routes: DataFrame, columns: tuple[str, ...]) -> None:
        self.routes, self.columns, self.rows = routes.select("id", F.explode("pids").alias("pid")), columns, None

    def shipped(self, changed: DataFrame) -> DataFrame:
        return self.routes.join(changed.select("id", *self.columns), "id").select("pid", "id", *self.columns)

    def refresh(self, changed: DataFrame, hidden: DataFrame | None = None) -> DataFrame:
        """The view with changed rows laid over it; hidden ids leave it (they are shipped as tombstones)."""
        new = self.shipped(changed)
        self.rows = new if self.rows is None else self.rows.join(new, ["pid", "id"], "left_anti").unionByName(new)
        if hidden is not None:
            self.rows = self.rows.join(hidden.select("id"), "id", "left_anti")
        return self.rows


def changes(old: DataFrame, new: DataFrame, columns: tuple[str, ...]) -> DataFrame:
    """Rows of new that differ, by value and null-safe, from old's row of the id."""
    was = old.select("id", *[F.col(c).alias(f"_was_{c}") for c in columns])
    same = F.lit(True)
    for c in columns:
        same = same & F.col(c).eqNullSafe(F.col(f"_was_{c}"))
    return new.join(was, "id", "left").where(~same).select(*new.columns)
