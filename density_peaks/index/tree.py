"""What both trees share: nodes with boxes and counts, points with their leaf."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from density_peaks.schemas import PLANE, Space

#: Node tables of at most so many rows are broadcast to joins; larger ones are joined by node.
MOST_BROADCAST = 200_000


@dataclass
class Tree:
    """nodes: node, parent, level (root 0), lo_*, hi_*, nc, is_leaf; leaf_points: leaf, id and coordinates.

    A weighted tree is over spots: leaf_points have a weight too, and nc is the sum of weights.
    """

    nodes: DataFrame
    leaf_points: DataFrame
    space: Space = PLANE
    n_nodes: int = 0
    height: int = 0
    meta: dict = field(default_factory=dict)
    weighted: bool = False
    _arrays: object = field(default=None, repr=False, compare=False)
    _rows: int | None = field(default=None, repr=False, compare=False)

    def arrays(self):
        """The node table as arrays on the driver, None where it is empty or too large for that."""
        from density_peaks.index import descent

        if self._arrays is None and 0 < self.n_nodes <= descent.MOST_NODES:
            self._arrays = descent.Nodes.of(self)
        return self._arrays

    def rows(self) -> int:
        """How many rows leaf_points has."""
        if self._rows is None:
            self._rows = self.leaf_points.count()
        return self._rows

    def lo(self, prefix: str = "") -> list[Column]:
        return [F.col(f"{prefix}lo_{c}") for c in self.space.coords]

    def hi(self, prefix: str = "") -> list[Column]:
        return [F.col(f"{prefix}hi_{c}") for c in self.space.coords]

    @property
    def bounds(self) -> list[str]:
        return [f"{e}_{c}" for e in ("lo", "hi") for c in self.space.coords]

    def small(self, df: DataFrame) -> DataFrame:
        """Marks a table of nodes for broadcast where its checked size allows."""
        return F.broadcast(df) if self.n_nodes <= MOST_BROADCAST else df


def boxes(space: Space) -> list[Column]:
    """Aggregates of the box of points."""
    return [f(c).alias(f"{e}_{c}") for c in space.coords for e, f in (("lo", F.min), ("hi", F.max))]


def merged(space: Space) -> list[Column]:
    """Aggregates of the box of boxes."""
    return [f(f"{e}_{c}").alias(f"{e}_{c}") for c in space.coords for e, f in (("lo", F.min), ("hi", F.max))]


def report(tree: Tree) -> DataFrame:
    """level, nodes, objects, coverage (area of boxes), overlap (area that siblings share) of each level."""
    nodes = tree.nodes
    area = lambda lo, hi: F.aggregate(F.array(*[F.greatest(b - a, F.lit(0.0)) for a, b in zip(lo, hi, strict=True)]), F.lit(1.0), lambda s, v: s * v)
    per = nodes.groupBy("level").agg(F.count(F.lit(1)).alias("nodes"), F.sum("nc").alias("objects"), F.sum(area(tree.lo(), tree.hi())).alias("coverage"))
    two = nodes.select("parent", F.col("node").alias("o_node"), *[F.col(b).alias(f"o_{b}") for b in tree.bounds])
    both = nodes.where("parent is not null").join(two, "parent").where("node < o_node")
    shared = area([F.greatest(a, b) for a, b in zip(tree.lo(), tree.lo("o_"), strict=True)], [F.least(a, b) for a, b in zip(tree.hi(), tree.hi("o_"), strict=True)])
    return per.join(both.groupBy("level").agg(F.sum(shared).alias("overlap")), "level", "left").select("level", "nodes", "objects", "coverage", F.coalesce("overlap", F.lit(0.0)).alias("overlap"))
