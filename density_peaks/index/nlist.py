"""Neighbour lists: for each point all others by distance, and the queries over them.

Packed form: id, nbrs, dists, two parallel arrays ordered by (dist, nbr), so density reads
only distances. Long form: id, pos, nbr, dist. Lists cut at a radius have the same form.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from density_peaks.dependent import denser, finish
from density_peaks.exact import pairs
from density_peaks.iterate import cut
from density_peaks.schemas import PLANE, Space

#: Longest list that is packed into one row; longer ones stay in long form. Most points of full lists, which are quadratic.
MOST_PACKED, MOST_POINTS = 1_000_000, 100_000


def pack(long: DataFrame, ids: DataFrame | None = None) -> DataFrame:
    """Packed lists from id, nbr, dist; with ids, points without neighbours get empty lists."""
    lists = long.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("dist", "nbr"))).alias("l"))
    lists = lists.select("id", F.col("l.nbr").alias("nbrs"), F.col("l.dist").alias("dists"))
    if ids is None:
        return lists
    empty = F.array().cast("array<long>"), F.array().cast("array<double>")
    return ids.select("id").join(lists, "id", "left").select("id", F.coalesce("nbrs", empty[0]).alias("nbrs"), F.coalesce("dists", empty[1]).alias("dists"))


def build(pts: DataFrame, space: Space = PLANE) -> DataFrame:
    """Full lists of all points, packed: quadratic in points, for sets whose lists fit."""
    n = pts.count()
    if n > MOST_POINTS:
        raise ValueError(f"full lists of {n} points are quadratic; cut them at a radius")
    return pack(pairs(pts, space), pts)


def long_form(idx: DataFrame) -> DataFrame:
    """id, pos (0-based), nbr, dist of packed lists."""
    return idx.select("id", F.posexplode(F.arrays_zip("nbrs", "dists")).alias("pos", "e")).select("id", "pos", F.col("e.nbrs").alias("nbr"), F.col("e.dists").alias("dist"))


def bisect_sql(values: str, limit: str, lo: str = "0", hi: str | None = None) -> str:
    """SQL for the place of the first entry of an ascending array, from lo to hi, that is not below a limit."""
    hi = hi or f"size({values})"
    mid = "CAST((s.lo + s.hi) DIV 2 AS INT)"
    return (
        f"aggregate(sequence(1, CAST(ceil(log2({hi} - {lo} + 1)) AS INT) + 1), named_struct('lo', {lo}, 'hi', {hi}), "
        f"(s, i) -> CASE WHEN s.lo >= s.hi THEN s WHEN get({values}, {mid}) < {limit} THEN named_struct('lo', {mid} + 1, 'hi', s.hi) "
        f"ELSE named_struct('lo', s.lo, 'hi', {mid}) END, s -> s.lo)"
    )


def bisect(dists: str, d_c: str) -> Column:
    """How many entries of an ascending array are strictly below a value, by binary search in the JVM.

    dists and d_c are SQL expressions.
    """
    return F.expr(bisect_sql(dists, d_c))


def rho(idx: DataFrame, d_c: float, count_self: bool = False) -> DataFrame:
    """id, rho by binary search in each list."""
    return idx.select("id", (bisect("dists", f"{d_c!r}D") + F.lit(int(count_self))).cast("long").alias("rho"))


def rho_sweep(idx: DataFrame, d_cs: list[float]) -> DataFrame:
    """d_c, id, rho for many cutoffs in one pass over the index."""
    several = F.array(*[F.struct(F.lit(float(d)).alias("d_c"), bisect("dists", f"{float(d)!r}D").cast("long").alias("rho")) for d in d_cs])
    return idx.select("id", F.explode(several).alias("e")).select("e.d_c", "id", "e.rho")


def delta(idx: DataFrame, rho_table: DataFrame, tie: str = "strict", cap: float | None = None, first: int = 8, grow: int = 4) -> DataFrame:
    """The dependent table: lists are read from near to far in growing prefixes until each point has met a denser one.

    With cap, lists are cut short: a point that meets none gets cap as delta.
    """
    other = rho_table.select(F.col("id").alias("nbr"), F.col("rho").alias("nbr_rho"))
    longest = idx.agg(F.max(F.size("dists"))).first()[0] or 0
    rest, found, start, size = idx.join(rho_table.select("id", "rho"), "id"), None, 0, first
    while start < longest:
        part = rest.where(F.size("dists") > start).select("id", "rho", F.explode(F.arrays_zip(F.slice("dists", start + 1, size).alias("d"), F.slice("nbrs", start + 1, size).alias("n"))).alias("e"))
        part = part.select("id", "rho", F.col("e.d").alias("dist"), F.col("e.n").alias("nbr")).join(other, "nbr")
        hit = part.where(denser("nbr_rho", "nbr", "rho", "id", tie)).groupBy("id").agg(F.min(F.struct("dist", "nbr")).alias("b"))
        hit = cut(hit.select("id", F.col("b.dist").alias("delta"), F.col("b.nbr").alias("mu")))
        found = hit if found is None else found.unionByName(hit)
        start, size = start + size, size * grow
        if start < longest:
            rest = cut(rest.join(hit, "id", "left_anti"))
            if rest.where(F.size("dists") > start).isEmpty():
                break
    far = idx.select("id", F.when(F.size("dists") > 0, F.element_at("dists", -1)).alias("far"))
    if found is None:
        return finish(rho_table, far.select("id", F.lit(None).cast("double").alias("delta"), F.lit(None).cast("long").alias("mu"), "far"), cap)
    return finish(rho_table, far.join(found, "id", "left"), cap)


def peak_delta(idx: DataFrame) -> DataFrame:
    """id, far: the last entry of each list."""
    return idx.select("id", F.when(F.size("dists") > 0, F.element_at("dists", -1)).alias("far"))


def probes(idx: DataFrame, dep: DataFrame) -> DataFrame:
    """id, probes, entries: entries read from near to far until the parent, all of them where there is none."""
    both = idx.join(dep.select("id", "mu"), "id")
    read = F.when(F.col("mu").isNull(), F.size("nbrs")).otherwise(F.array_position("nbrs", F.col("mu")))
    return both.select("id", read.cast("long").alias("probes"), F.size("nbrs").cast("long").alias("entries"))


def rho_long(long: DataFrame, ids: DataFrame, d_c: float, count_self: bool = False) -> DataFrame:
    """id, rho of all ids from lists in long form (id, nbr, dist), of any length."""
    n = long.where(F.col("dist") < float(d_c)).groupBy("id").agg(F.count(F.lit(1)).alias("n"))
    return ids.select("id").join(n, "id", "left").select("id", (F.coalesce("n", F.lit(0)) + F.lit(int(count_self))).cast("long").alias("rho"))


def delta_long(long: DataFrame, rho_table: DataFrame, tie: str = "strict", cap: float | None = None) -> DataFrame:
    """The dependent table from lists in long form, of any length; cap as in delta()."""
    other = rho_table.select(F.col("id").alias("nbr"), F.col("rho").alias("nbr_rho"))
    both = long.join(rho_table.select("id", "rho"), "id").join(other, "nbr")
    up = F.when(denser("nbr_rho", "nbr", "rho", "id", tie), F.struct("dist", "nbr"))
    found = both.groupBy("id").agg(F.min(up).alias("best"), F.max("dist").alias("far"))
    return finish(rho_table, found.select("id", F.col("best.dist").alias("delta"), F.col("best.nbr").alias("mu"), "far"), cap)
