"""Neighbour lists cut at a radius: the approximate solution, and its exact repair."""

from __future__ import annotations

from itertools import product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from density_peaks import grid
from density_peaks.index import nlist
from density_peaks.schemas import PLANE, Space, points


def from_nlist(idx: DataFrame, tau: float) -> DataFrame:
    """Full lists cut to entries strictly closer than tau."""
    n = nlist.bisect("dists", f"{float(tau)!r}D")
    return idx.withColumn("n", n).select("id", F.slice("nbrs", F.lit(1), F.col("n")).alias("nbrs"), F.slice("dists", F.lit(1), F.col("n")).alias("dists"))


def longest(pts: DataFrame, tau: float, space: Space = PLANE) -> int:
    """A length that no cut list exceeds: the most points in a cell and those around it."""
    side, names = tau * grid.SLACK, [f"cell_{c}" for c in space.coords]
    per = points(pts, space).groupBy(*[c.alias(n) for c, n in zip(grid.cells(space, side), names, strict=True)]).agg(F.count(F.lit(1)).alias("n"))
    around = F.array(*[F.struct(*[(F.col(n) + F.lit(o)).alias(n) for n, o in zip(names, offsets, strict=True)]) for offsets in product((-1, 0, 1), repeat=len(names))])
    return per.select("n", F.explode(around).alias("at")).groupBy("at").agg(F.sum("n").alias("n")).agg(F.max("n")).first()[0] or 0


def long(pts: DataFrame, tau: float, space: Space = PLANE) -> DataFrame:
    """id, nbr, dist of cut lists in long form, for lists of any length; nlist.rho_long and nlist.delta_long read it."""
    if space.vector or space.metric == "haversine":
        from density_peaks.exact import pairs

        return pairs(pts, space).where(F.col("dist") < tau)
    return grid.eps_join(pts, pts, tau, space)


def build(pts: DataFrame, tau: float, space: Space = PLANE) -> DataFrame:
    """The same lists straight from the points by a distance join, without full lists.

    Raises ValueError where a list may be longer than nlist.MOST_PACKED; long() has no such limit.
    """
    if not space.vector and space.metric != "haversine" and longest(pts, tau, space) > nlist.MOST_PACKED:
        raise ValueError(f"lists cut at {tau} may be too long to pack; use long()")
    return nlist.pack(long(pts, tau, space), pts)


def rho(idx: DataFrame, d_c: float, tau: float, count_self: bool = False) -> DataFrame:
    """id, rho, is_exact: exact up to tau; beyond it the length of the list."""
    if d_c <= tau:
        return nlist.rho(idx, d_c, count_self).withColumn("is_exact", F.lit(True))
    return idx.select("id", (F.size("dists") + F.lit(int(count_self))).cast("long").alias("rho"), F.lit(False).alias("is_exact"))


def diagonal(pts: DataFrame, space: Space = PLANE) -> float:
    """A distance that no pair exceeds: the diagonal of the bounding box."""
    import math

    box = pts.agg(*[f(c) for c in space.coords for f in (F.min, F.max)]).first()
    gaps = [(box[2 * i + 1] or 0.0) - (box[2 * i] or 0.0) for i in range(len(space.coords))]
    return sum(gaps) if space.metric == "manhattan" else max(gaps) if space.metric == "chebyshev" else math.sqrt(sum(g * g for g in gaps))


def delta(idx: DataFrame, rho_table: DataFrame, cap: float, tie: str = "strict") -> DataFrame:
    """The dependent table; a point whose list holds no denser one gets cap."""
    return nlist.delta(idx, rho_table, tie, cap)


def from_dependent(dep: DataFrame, tau: float, cap: float) -> DataFrame:
    """What lists cut at tau answer, from the exact dependent table of their densities: no parent at tau or beyond."""
    lost = F.col("mu").isNull() | F.col("delta").isNull() | (F.col("delta") >= float(tau))
    return dep.select("id", "rho", F.when(lost, F.lit(float(cap))).otherwise(F.col("delta")).alias("delta"), F.when(~lost, F.col("mu")).alias("mu"), lost.alias("is_top"), lost.alias("is_capped"))


def repair(dep: DataFrame, tree, tie: str = "strict") -> DataFrame:
    """The dependent table with capped points settled exactly by a tree search for them alone."""
    from density_peaks.index import tree_query

    rho_table = dep.select("id", "rho")
    exact = tree_query.delta(tree, rho_table, tie, only=dep.where("is_capped").select("id"))
    return dep.where("not is_capped").unionByName(exact)
