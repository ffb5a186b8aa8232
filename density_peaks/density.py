"""Local density by the index that is asked for."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from density_peaks import exact, grid
from density_peaks.schemas import PLANE, Space


def rho(pts: DataFrame, d_c: float, space: Space = PLANE, count_self: bool = False, method: str = "grid") -> DataFrame:
    """id, rho for one cutoff: by a grid of cells as wide as the cutoff, by brute force, or by a tree, which counts whole nodes where cells hold very many places."""
    if method == "brute" or space.vector or space.metric == "haversine":
        return exact.rho(pts, d_c, space, count_self)
    if method in ("rtree", "quadtree"):
        from density_peaks import pipeline

        r = pipeline.tree_rho(pts, d_c, method, space=space)
        return r.withColumn("rho", F.col("rho") + F.lit(1)) if count_self else r
    return grid.rho(pts, d_c, space, count_self)
