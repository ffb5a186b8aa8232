"""Equal points as one: a spot stands for all points of the same coordinates.

Points of a spot have the same density, and the same nearest denser point but for ties
among themselves. So searches run over spots with weights, and their answers are handed to
all points; work then grows with the number of different places.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from density_peaks.iterate import cut
from density_peaks.schemas import PLANE, Space, points

WEIGHT = "weight"


@dataclass
class Merged:
    """points: id, coordinates, alone; spots: id (the smallest of its points), coordinates, alone, weight (how many points).

    alone is the id of a point that is not merged: one without finite coordinates is at no
    distance from its like.
    """

    points: DataFrame
    spots: DataFrame
    space: Space

    def of_spots(self, rho_table: DataFrame) -> DataFrame:
        """id, rho of spots from those of all points."""
        return rho_table.select("id", "rho").join(self.spots.select("id"), "id", "left_semi")

    def spread(self, values: DataFrame) -> DataFrame:
        """Values of spots (id and more) for every point: id, spot and the same columns."""
        named = [f"s_{c}" for c in self.space.coords]
        s = self.spots.select(F.col("id").alias("spot"), F.col("alone").alias("s_alone"), *[F.col(c).alias(n) for c, n in zip(self.space.coords, named, strict=True)]).join(values.withColumnRenamed("id", "spot").hint("merge"), "spot")
        same = [self.points[c].eqNullSafe(s[n]) for c, n in zip((*self.space.coords, "alone"), (*named, "s_alone"), strict=True)]
        # tables of points are never broadcast: their estimated size is that of their files
        return self.points.join(s.hint("merge"), same).drop(*self.space.coords, "alone", *named, "s_alone")

    def rho(self, of_spots: DataFrame) -> DataFrame:
        """id, rho of all points."""
        return self.spread(of_spots.select("id", "rho")).select("id", "rho")

    def dependent(self, of_spots: DataFrame, tie: str = "strict") -> DataFrame:
        """The dependent table of all points; by_id orders the points of a spot, so all but its first depend on that one."""
        every = self.spread(of_spots)
        if tie == "by_id":
            later = F.col("id") != F.col("spot")
            put = {"delta": F.lit(0.0), "mu": F.col("spot"), "is_top": F.lit(False), "is_capped": F.lit(False)}
            every = every.withColumns({c: F.when(later, v).otherwise(F.col(c)) for c, v in put.items()})
        return every.select(of_spots.columns)


@dataclass
class Nowhere:
    """points: id and gap, the distance to anything, of points that have a null (gap null) or NaN coordinate (gap NaN).

    Nothing is within a cutoff of them. A tree cannot hold them, as NaN would spread to all boxes above.
    """

    points: DataFrame

    def rho(self, of_others: DataFrame) -> DataFrame:
        """id, rho with these points."""
        return of_others.unionByName(self.points.select("id", F.lit(0).cast("long").alias("rho")))

    def dependent(self, of_others: DataFrame, rho_table: DataFrame, tie: str) -> DataFrame:
        """The dependent table with these points: any denser one is as far as another, so the smallest id is the parent."""
        zero = F.col("rho") == 0
        n, dense, flat = rho_table.agg(F.count(F.lit(1)), F.min(F.when(~zero, F.col("id"))), F.min(F.when(zero, F.col("id")))).first()
        least, far = self.points.agg(F.min(F.struct("id", "gap")), F.max("gap")).first()
        number = lambda v: F.lit(v).cast("long")
        before = F.when(number(flat) < F.col("id"), number(flat)) if tie == "by_id" else number(None)
        own = self.points.withColumn("mu", F.least(number(dense), before))
        peak = F.when(F.isnan("gap") & F.lit(n > 1), F.col("gap")).otherwise(F.lit(0.0))
        own = own.select("id", F.lit(0).cast("long").alias("rho"), F.when(F.col("mu").isNull(), peak).otherwise(F.col("gap")).alias("delta"), "mu", F.col("mu").isNull().alias("is_top"), F.lit(False).alias("is_capped"))
        # another point depends on one of these where nothing else is before it, and a peak is as far from them as they are
        after = F.lit(tie == "by_id") & F.col("is_top") & zero & (F.col("id") > number(least.id))
        farther = F.when(F.col("is_top") & F.lit(far is not None), F.lit(far).cast("double")).otherwise(F.col("delta"))
        others = of_others.select("id", "rho", F.when(after, F.lit(least.gap).cast("double")).otherwise(farther).alias("delta"), F.when(after, number(least.id)).otherwise(F.col("mu")).alias("mu"), (F.col("is_top") & ~after).alias("is_top"), "is_capped")
        return others.unionByName(own)


def placed(same: Merged) -> tuple[Merged, Nowhere | None]:
    """same without points that have no place, and these, None if there are none."""
    null, nan = F.lit(False), F.lit(False)
    for c in same.space.coords:
        null, nan = null | F.col(c).isNull(), nan | F.isnan(c)
    odd = null | nan
    held = same.spots.where(odd)
    if held.isEmpty():
        return same, None
    gap = F.when(~null, F.lit(float("nan"))).alias("gap")
    return Merged(same.points.where(~odd), same.spots.where(~odd), same.space), Nowhere(cut(held.select("id", gap)))


def merge(pts: DataFrame, space: Space = PLANE, apart: bool = False) -> Merged:
    """Spots of points; with apart, each point is one of its own."""
    p = points(pts, space)
    odd = F.lit(apart)
    for c in space.coords:
        odd = odd | F.col(c).isNull() | F.isnan(c) | (F.abs(c) == F.lit(float("inf")))
    p = p.withColumn("alone", F.when(odd, F.col("id")))
    spots = p.groupBy(*space.coords, "alone").agg(F.min("id").alias("id"), F.count(F.lit(1)).alias(WEIGHT))
    return Merged(p, cut(spots.select("id", *space.coords, "alone", WEIGHT)), space)
