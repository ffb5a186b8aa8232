"""Assignment: every point follows its parents to a center."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from density_peaks.iterate import cut


def assign(dep: DataFrame, centers: DataFrame, rounds: int = 64) -> DataFrame:
    """id, cluster, depth, is_center: cluster is the first center on the way up, or the root where none is.

    Parents are denser, so links have no cycle; centers and points without a parent point
    to themselves. Each round replaces a pointer by its target's pointer, so the number of
    rounds is the logarithm of the longest way.
    """
    c = centers.select("id", F.lit(True).alias("is_center"))
    s = dep.select("id", "mu").join(c, "id", "left").withColumn("is_center", F.coalesce("is_center", F.lit(False)))
    stop = F.col("is_center") | F.col("mu").isNull()
    s = cut(s.select("id", "is_center", F.when(stop, F.col("id")).otherwise(F.col("mu")).alias("cluster"), F.when(stop, 0).otherwise(1).alias("depth")))
    for _ in range(rounds):
        up = s.select(F.col("id").alias("cluster"), F.col("cluster").alias("next"), F.col("depth").alias("more"))
        s = cut(s.join(up, "cluster").select("id", "is_center", F.col("next").alias("cluster"), (F.col("depth") + F.col("more")).alias("depth"), (F.col("more") > 0).alias("moved")))
        if s.where("moved").isEmpty():
            return s.select("id", "cluster", F.col("depth").cast("int").alias("depth"), "is_center")
    raise RuntimeError("parents do not end")
