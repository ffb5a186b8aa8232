"""The original method: every pair of points, for one cutoff or kept for many.

This is the quadratic baseline that the indices are measured against, and what their
answers must equal.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from density_peaks.dependent import denser, finish
from density_peaks.iterate import cut, settled
from density_peaks.metrics import dist
from density_peaks.schemas import PLANE, Space, points


def pairs(pts: DataFrame, space: Space = PLANE) -> DataFrame:
    """id, nbr, dist of every ordered pair of different points."""
    a = settled(points(pts, space))
    b = a.select(F.col("id").alias("nbr"), *[F.col(c).alias(f"n_{c}") for c in space.coords])
    return a.join(b, F.col("id") != F.col("nbr")).select("id", "nbr", dist(space.of(), space.of("n_"), space).alias("dist"))


def rho(pts: DataFrame, d_c: float, space: Space = PLANE, count_self: bool = False, pair_table: DataFrame | None = None) -> DataFrame:
    """id, rho: how many points are strictly closer than d_c, without the point itself unless count_self."""
    near = (pairs(pts, space) if pair_table is None else pair_table).where(F.col("dist") < d_c).groupBy("id").agg(F.count(F.lit(1)).alias("n"))
    return pts.select(F.col("id").cast("long").alias("id")).join(near, "id", "left").select("id", (F.coalesce("n", F.lit(0)) + F.lit(int(count_self))).cast("long").alias("rho"))


def delta(pts: DataFrame, rho_table: DataFrame, space: Space = PLANE, tie: str = "strict", pair_table: DataFrame | None = None) -> DataFrame:
    """The dependent table: distance to the nearest denser point and that point, largest distance for peaks."""
    p = pairs(pts, space) if pair_table is None else pair_table
    own = rho_table.select("id", "rho")
    other = rho_table.select(F.col("id").alias("nbr"), F.col("rho").alias("nbr_rho"))
    both = p.join(own, "id").join(other, "nbr")
    up = F.when(denser("nbr_rho", "nbr", "rho", "id", tie), F.struct("dist", "nbr"))
    found = both.groupBy("id").agg(F.min(up).alias("best"), F.max("dist").alias("far"))
    return finish(rho_table, found.select("id", F.col("best.dist").alias("delta"), F.col("best.nbr").alias("mu"), "far"))


def run(pts: DataFrame, d_c: float, space: Space = PLANE, tie: str = "strict") -> DataFrame:
    """rho and delta of all points by brute force."""
    return delta(pts, rho(pts, d_c, space), space, tie)


class PairMatrix:
    """Brute force with its distances kept for further cutoffs."""

    def __init__(self, pts: DataFrame, space: Space = PLANE):
        self.pts, self.space = pts, space
        self.pairs = cut(pairs(pts, space))

    def run(self, d_c: float, tie: str = "strict") -> DataFrame:
        return delta(self.pts, rho(self.pts, d_c, self.space, pair_table=self.pairs), self.space, tie, self.pairs)
