"""Dependent distance: what all methods share about ties, peaks and missing parents."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from density_peaks import metrics
from density_peaks.schemas import PLANE, Space, points

TIES = ("strict", "by_id")


def denser(other_rho: str, other_id: str, own_rho: str, own_id: str, tie: str) -> Column:
    """Whether the other point counts as denser: higher rho, and by_id among equals the smaller id."""
    if tie not in TIES:
        raise ValueError(f"tie is one of {TIES}")
    up = F.col(other_rho) > F.col(own_rho)
    return up if tie == "strict" else up | ((F.col(other_rho) == F.col(own_rho)) & (F.col(other_id) < F.col(own_id)))


def key(rho: Column, id_: Column, tie: str) -> Column:
    """One comparable value a point, so that denser means greater."""
    return F.struct(rho.alias("rho"), (-id_ if tie == "by_id" else F.lit(0).cast("long")).alias("turn"))


def finish(rho_table: DataFrame, found: DataFrame, cap: float | None = None) -> DataFrame:
    """The dependent table from rho and found (id, delta, mu, far).

    A point without a denser one is a top. Its delta is far, its largest distance to any
    point (0 for a lone point), or cap where lists are cut short and far is not known.
    """
    out = rho_table.select("id", "rho").join(found, "id", "left")
    top = F.col("mu").isNull()
    peak = F.coalesce("far", F.lit(0.0)) if cap is None else F.lit(float(cap))
    return out.select(
        "id",
        F.col("rho").cast("long").alias("rho"),
        F.when(top, peak).otherwise(F.col("delta")).alias("delta"),
        F.col("mu").cast("long").alias("mu"),
        top.alias("is_top"),
        (top & F.lit(cap is not None)).alias("is_capped"),
    )


def peak_delta(pts: DataFrame, tops: DataFrame, space: Space = PLANE) -> DataFrame:
    """id, far: the largest distance of each top to any point. tops are few by nature: points that nothing exceeds."""
    p = points(pts, space)
    t = p.join(tops.select("id"), "id", "left_semi").select("id", *[F.col(c).alias(f"t_{c}") for c in space.coords])
    q = p.select(*[F.col(c).alias(f"q_{c}") for c in space.coords])
    return q.join(t).groupBy("id").agg(F.max(metrics.dist(space.of("t_"), space.of("q_"), space)).alias("far"))


def delta(pts: DataFrame, rho_table: DataFrame, space: Space = PLANE, tie: str = "strict", method: str = "rtree") -> DataFrame:
    """The dependent table by tree descent, or by brute force where no tree applies."""
    from density_peaks import exact
    from density_peaks.index import quadtree, rtree, tree_query

    if method == "brute" or space.vector or space.metric == "haversine":
        return exact.delta(pts, rho_table, space, tie)
    tree = quadtree.build(pts) if method == "quadtree" else rtree.build(pts, space=space)
    return tree_query.delta(tree, rho_table, tie)
