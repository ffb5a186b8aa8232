"""Distance joins by grid cells: an equality join on cells, then the exact predicate.

Cells are slightly wider than the radius, so rounding never puts two points closer than
the radius two cells apart. One side is copied to the neighbouring cells; as the other
sits in one cell, each pair meets once.
"""

from __future__ import annotations

from itertools import product

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from density_peaks import spots
from density_peaks.iterate import cut
from density_peaks.metrics import box_max, box_min, dist
from density_peaks.schemas import PLANE, Space, points

SLACK = 1 + 1e-6
#: Points of a cell beyond which it is spread.
HOT_CELL = 20_000
#: Hot cells up to which their table is sent to all tasks.
MOST_SENT = 50_000


def cells(space: Space, side: float, prefix: str = "") -> list[Column]:
    return [F.floor(c / F.lit(float(side))).cast("long") for c in space.of(prefix)]


def eps_join(a: DataFrame, b: DataFrame, r: float, space: Space = PLANE, hot: int = HOT_CELL, keep: str | None = None) -> DataFrame:
    """id, nbr, dist of all pairs of a and b strictly closer than r, a pair of equal ids excluded. keep names one more column of b.

    Cells that hold more than `hot` points of a are spread over as many keys as they hold
    multiples of it, but no more than a shuffle has partitions. The keys of a cell are a
    square: a point of a has a row of it, one that meets the cell a column, and each is
    copied along its own. So copies grow with the root of the keys.
    """
    side = r * SLACK
    names = [f"cell_{c}" for c in space.coords]
    left = points(a, space)
    left = left.select("id", *[F.col(c).alias(f"a_{c}") for c in space.coords], *[c.alias(n) for c, n in zip(cells(space, side), names, strict=True)])
    more = [keep] if keep else []
    right = points(b, space, keep=keep).select(F.col("id").alias("nbr"), *[F.col(c).alias(f"b_{c}") for c in space.coords], *more)
    around = F.array(*[F.struct(*[(c + F.lit(o)).alias(n) for c, o, n in zip(cells(space, side, "b_"), offsets, names, strict=True)]) for offsets in product((-1, 0, 1), repeat=len(names))])
    right = right.withColumn("at", F.explode(around)).select("nbr", *[f"b_{c}" for c in space.coords], *more, *[F.col(f"at.{n}").alias(n) for n in names])
    # one row a hot cell: at most a `hot`-th of the points
    most = int(a.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    keys = F.least(F.ceil(F.col("n") / F.lit(hot)), F.lit(most))
    crowded = left.groupBy(*names).agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > hot).withColumn("rows", F.ceil(F.sqrt(keys)).cast("int"))
    crowded = cut(crowded.select(*names, "rows", F.ceil(keys / F.col("rows")).cast("int").alias("columns")))
    n_crowded = crowded.count()
    if n_crowded:
        crowded = crowded.hint("broadcast" if n_crowded <= MOST_SENT else "merge")
        rows, columns = (F.coalesce(c, F.lit(1)) for c in ("rows", "columns"))
        left = left.join(crowded, names, "left").withColumn("row", F.pmod(F.xxhash64("id"), rows).cast("int")).withColumn("column", F.explode(F.sequence(F.lit(0), columns - 1))).drop("rows", "columns")
        right = right.join(crowded, names, "left").withColumn("column", F.pmod(F.xxhash64("nbr"), columns).cast("int")).withColumn("row", F.explode(F.sequence(F.lit(0), rows - 1))).drop("rows", "columns")
        names = [*names, "row", "column"]
    # by size of files Spark takes these tables for small, and would send all points to all tasks by way of the driver
    near = left.join(right.hint("merge"), names).withColumn("dist", dist(space.of("a_"), space.of("b_"), space))
    return near.where((F.col("dist") < F.lit(float(r))) & (F.col("id") != F.col("nbr"))).select("id", "nbr", "dist", *more)


def rho(pts: DataFrame, d_c: float, space: Space = PLANE, count_self: bool = False, hot: int = HOT_CELL) -> DataFrame:
    """id, rho for one cutoff by a distance join of spots, whose own other points are as near as can be.

    Weights travel with the spots, so pairs are added up where they meet and never shuffled.
    """
    same = spots.merge(pts, space)
    near = eps_join(same.spots, same.spots, d_c, space, hot, spots.WEIGHT).groupBy("id").agg(F.sum(spots.WEIGHT).alias("n"))
    # a point is near those of its own spot, unless no distance is below the cutoff or there is none
    own = F.when(dist(space.of(), space.of(), space) < F.lit(float(d_c)), F.col(spots.WEIGHT) - 1).otherwise(0)
    found = same.spots.join(near.hint("merge"), "id", "left").select("id", (F.coalesce("n", F.lit(0)) + own + F.lit(int(count_self))).cast("long").alias("rho"))
    return same.rho(found)


def rho_contained(pts: DataFrame, d_c: float, k: int = 4, space: Space = PLANE, count_self: bool = False) -> DataFrame:
    """id, rho with cells of side d_c / k: pairs of cells wholly within d_c add their counts, others are joined by points.

    The cell pairs are judged by the boxes of their members, so the answer is exact.
    """
    side = d_c / k
    names = [f"cell_{c}" for c in space.coords]
    p = points(pts, space).select("id", *space.coords, *[c.alias(n) for c, n in zip(cells(space, side), names, strict=True)])
    boxes = p.groupBy(*names).agg(F.count(F.lit(1)).alias("nc"), *[f(c).alias(f"{e}_{c}") for c in space.coords for f, e in ((F.min, "lo"), (F.max, "hi"))])
    boxes = cut(boxes)
    reach = k + 1
    ends = [f"{e}_{c}" for e in ("lo", "hi") for c in space.coords]
    one = boxes.select(*[F.col(n).alias(f"q_{n}") for n in names], *[F.col(e).alias(f"q_{e}") for e in ends])
    # near cells by an equality join: each cell is copied to the coarse cells around it
    coarse = [f"coarse_{n}" for n in names]
    two = boxes.select(*[F.col(n).alias(f"n_{n}") for n in names], *[F.col(e).alias(f"n_{e}") for e in ends], "nc", *[F.floor(F.col(n) / F.lit(reach)).alias(m) for n, m in zip(names, coarse, strict=True)])
    around = F.array(*[F.struct(*[(F.floor(F.col(f"q_{n}") / F.lit(reach)) + F.lit(o)).alias(m) for n, m, o in zip(names, coarse, offsets, strict=True)]) for offsets in product((-1, 0, 1), repeat=len(names))])
    one = one.withColumn("at", F.explode(around)).select("*", *[F.col(f"at.{m}").alias(m) for m in coarse]).drop("at")
    lo, hi = (lambda x: [F.col(f"{x}_lo_{c}") for c in space.coords]), (lambda x: [F.col(f"{x}_hi_{c}") for c in space.coords])
    near = one.join(two, coarse)
    near = near.withColumn("least", box_min(lo("q"), hi("q"), lo("n"), hi("n"), space)).withColumn("most", box_max(lo("q"), hi("q"), lo("n"), hi("n"), space))
    near = cut(near.where(F.col("least") < d_c).select(*[f"q_{n}" for n in names], *[f"n_{n}" for n in names], "nc", "most"))
    full = near.where(F.col("most") < d_c).groupBy(*[f"q_{n}" for n in names]).agg(F.sum("nc").alias("full"))
    full = full.select("full", *[F.col(f"q_{n}").alias(n) for n in names])
    part = near.where(F.col("most") >= d_c).select(*[F.col(f"q_{n}").alias(n) for n in names], *[f"n_{n}" for n in names])
    other = p.select(*[F.col(n).alias(f"n_{n}") for n in names], *[F.col(c).alias(f"n_{c}") for c in space.coords])
    edge = part.join(p, names).join(other, [f"n_{n}" for n in names]).where(dist(space.of(), space.of("n_"), space) < d_c).groupBy("id").agg(F.count(F.lit(1)).alias("edge"))
    total = F.coalesce("full", F.lit(0)) + F.coalesce("edge", F.lit(0)) - F.lit(0 if count_self else 1)
    return p.join(full, names, "left").join(edge, "id", "left").select("id", total.cast("long").alias("rho"))
