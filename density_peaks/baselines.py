"""Other ways to cluster that density peaks are set against."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from density_peaks import grid, spots
from density_peaks.iterate import components, cut
from density_peaks.schemas import PLANE, Space, points


def dbscan(pts: DataFrame, eps: float, min_pts: int, space: Space = PLANE) -> DataFrame:
    """id, cluster, is_core: clusters are components of core points closer than eps; noise has none.

    A core point has at least min_pts points closer than eps, itself included. A border
    point joins the cluster of its nearest core point, the smaller id first among equals.
    Pairs are of spots: points of one spot are core together, and in one cluster.
    """
    same = spots.merge(pts, space, apart=eps <= 0)
    near = cut(grid.eps_join(same.spots, same.spots, eps, space))
    weight = same.spots.select("id", spots.WEIGHT)
    n = near.join(weight.select(F.col("id").alias("nbr"), F.col(spots.WEIGHT).alias("n")), "nbr").groupBy("id").agg(F.sum("n").alias("n"))
    every = weight.join(n, "id", "left").select("id", (F.coalesce("n", F.lit(0)) + F.col(spots.WEIGHT) >= min_pts).alias("is_core"))
    every = cut(every)
    core = every.where("is_core").select("id")
    links = near.join(core, "id").join(core.select(F.col("id").alias("nbr")), "nbr").where("id < nbr")
    label = components(links.select(F.col("id").alias("a"), F.col("nbr").alias("b")), core)
    edge = near.join(every.where("not is_core").select("id"), "id").join(label.select(F.col("id").alias("nbr"), "label"), "nbr")
    edge = edge.groupBy("id").agg(F.min_by("label", F.struct("dist", "nbr")).alias("border"))
    found = every.join(label, "id", "left").join(edge, "id", "left").select("id", F.coalesce("label", "border").alias("cluster"), "is_core")
    return same.spread(found).select("id", "cluster", "is_core")


def linkage_cut(pts: DataFrame, eps: float, space: Space = PLANE) -> DataFrame:
    """id, cluster: components of points closer than eps, as single linkage cut at eps gives them."""
    near = grid.eps_join(pts, pts, eps, space).where("id < nbr")
    label = components(near.select(F.col("id").alias("a"), F.col("nbr").alias("b")), points(pts, space))
    return label.withColumnRenamed("label", "cluster")


def kmeans(pts: DataFrame, k: int, seed: int = 7, space: Space = PLANE) -> DataFrame:
    """id, cluster by distance to the nearest of k centroids."""
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.feature import VectorAssembler

    p = VectorAssembler(inputCols=list(space.coords), outputCol="features").transform(points(pts, space))
    return KMeans(k=k, seed=seed).fit(p).transform(p).select("id", F.col("prediction").cast("long").alias("cluster"))
