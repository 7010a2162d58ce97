"""What a message reads, found by calling it once with a recorder, and the join that this needs."""

from __future__ import annotations

import enum
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column
from pyspark.sql import functions as F


class JoinShape(enum.Enum):
    NONE, SOURCE, TARGET, BOTH = "none", "src", "dst", "both"

    @property
    def joins(self) -> int:
        return {"none": 0, "both": 2}.get(self.value, 1)


class Side:
    """Columns of one part of a triplet; every access is noted, so all branches of a when() count."""

    def __init__(self, prefix: str) -> None:
        self.prefix, self.read = prefix, set()

    def __getitem__(self, name: str) -> Column:
        self.read.add(name)
        return F.col(f"{self.prefix}{name}")


@dataclass
class Triplet:
    src: Side = field(default_factory=lambda: Side("src__"))
    dst: Side = field(default_factory=lambda: Side("dst__"))
    edge: Side = field(default_factory=lambda: Side(""))

    @property
    def src_id(self) -> Column:
        return F.col("src")

    @property
    def dst_id(self) -> Column:
        return F.col("dst")

    @property
    def shape(self) -> JoinShape:
        return {(0, 0): JoinShape.NONE, (1, 0): JoinShape.SOURCE, (0, 1): JoinShape.TARGET}.get((bool(self.src.read), bool(self.dst.read)), JoinShape.BOTH)


def record(*messages: Callable[[Triplet], Column] | None) -> tuple[list[Column | None], Triplet]:
    """The messages' columns and the triplet that noted what they read. Ids don't count as reads."""
    t = Triplet()
    return [m(t) if m else None for m in messages], t


def choose_access(active: int, all_vertices: int, threshold: float = 0.8) -> str:
    """Edges of active vertices only, once their share is below the threshold; else all edges."""
    return "index" if all_vertices and active < threshold * all_vertices else "scan"
