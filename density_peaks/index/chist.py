"""Cumulative histograms over neighbour lists: density from counts, with at most one bin read.

Packed form: an array beside each list, cum[k] the entries in bins up to k, so a query is a
projection without a join: the list itself tells the least and largest distance of a bin.
Sparse form: id, bin, cum, min_dist, max_dist for bins that hold entries. Bins and cutoffs
use one formula, floor(value / width), which is monotone in floating point; a bin's least
and largest distance tell whether any of it has to be read.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from density_peaks.index import nlist


def packed(idx: DataFrame, w: float) -> DataFrame:
    """id, nbrs, dists, cum: packed lists (full or cut) with their histogram, made without a shuffle."""
    own = idx.withColumn("bins", F.expr(f"transform(dists, d -> CAST(floor(d / {float(w)!r}D) AS BIGINT))"))
    cum = f"transform(sequence(0L, element_at(bins, -1)), k -> {nlist.bisect_sql('bins', 'k + 1')})"
    return own.select("id", "nbrs", "dists", F.expr(f"CASE WHEN size(dists) > 0 THEN {cum} ELSE CAST(array() AS ARRAY<INT>) END").alias("cum"))


def rho_packed(hist: DataFrame, d_c: float, w: float, count_self: bool = False) -> DataFrame:
    """id, rho from packed histograms: a count, or a search of the one bin that straddles the cutoff."""
    d, t = f"{float(d_c)!r}D", min(math.floor(float(d_c) / float(w)), (1 << 31) - 2)
    before = "0" if t <= 0 else f"coalesce(get(cum, {t - 1}), size(dists))"
    at = hist.select("id", "dists", F.expr(before).alias("before"), F.expr(f"coalesce(get(cum, {max(t, 0)}), size(dists))").alias("upto"))
    search = nlist.bisect_sql("dists", d, "before", "upto")
    found = f"CASE WHEN before >= upto OR {d} <= get(dists, before) THEN before WHEN get(dists, upto - 1) < {d} THEN upto ELSE {search} END"
    return at.select("id", (F.expr(found) + F.lit(int(count_self))).cast("long").alias("rho"))


def build(idx: DataFrame, w: float) -> DataFrame:
    """The sparse histogram of packed lists (full or cut) with bins of width w."""
    long = idx.select("id", F.explode("dists").alias("dist"))
    bins = long.groupBy("id", F.floor(F.col("dist") / F.lit(float(w))).cast("long").alias("bin")).agg(F.count(F.lit(1)).alias("n"), F.min("dist").alias("min_dist"), F.max("dist").alias("max_dist"))
    up = Window.partitionBy("id").orderBy("bin").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    return bins.select("id", "bin", F.sum("n").over(up).alias("cum"), "min_dist", "max_dist")


def dense(hist: DataFrame) -> DataFrame:
    """id, cum: an array over all bins up to the last, empty bins repeating the count before."""
    cells = hist.groupBy("id").agg(F.array_sort(F.collect_list(F.struct("bin", "cum"))).alias("b"))
    fill = F.expr(
        "aggregate(b, CAST(array() AS ARRAY<BIGINT>), (a, e) -> concat(a, array_repeat(coalesce(get(a, size(a) - 1), 0L), CAST(e.bin AS INT) - size(a)), array(e.cum)))"
    )
    return cells.select("id", fill.alias("cum"))


def target(hist: DataFrame, d_c: float, w: float) -> DataFrame:
    """id, before, cum, min_dist, max_dist: the count of bins below the cutoff's, and the cutoff's own bin if it holds entries."""
    t = F.floor(F.lit(float(d_c)) / F.lit(float(w))).cast("long")
    own = F.col("bin") == t
    return hist.where(F.col("bin") <= t).groupBy("id").agg(
        F.coalesce(F.max(F.when(~own, F.col("cum"))), F.lit(0)).alias("before"), F.max(F.when(own, F.col("cum"))).alias("cum"), F.max(F.when(own, F.col("min_dist"))).alias("min_dist"), F.max(F.when(own, F.col("max_dist"))).alias("max_dist")
    )


def rho(hist: DataFrame, idx: DataFrame, d_c: float, w: float, count_self: bool = False) -> DataFrame:
    """id, rho from the histogram; only points whose target bin straddles the cutoff read that bin of their list."""
    d = F.lit(float(d_c))
    at = idx.select("id").join(target(hist, d_c, w), "id", "left").withColumn("before", F.coalesce("before", F.lit(0)))
    at = at.withColumn("known", F.when(F.col("cum").isNull() | (d <= F.col("min_dist")), F.col("before")).when(F.col("max_dist") < d, F.col("cum")))
    sure = at.where("known is not null").select("id", F.col("known").alias("rho"))
    part = at.where("known is null").join(idx.select("id", "dists"), "id")
    inside = part.withColumn("section", F.slice("dists", (F.col("before") + 1).cast("int"), (F.col("cum") - F.col("before")).cast("int")))
    read = inside.select("id", (F.col("before") + nlist.bisect("section", f"{float(d_c)!r}D")).alias("rho"))
    return sure.unionByName(read).select("id", (F.col("rho") + F.lit(int(count_self))).cast("long").alias("rho"))


def list_reads(hist: DataFrame, d_c: float, w: float) -> DataFrame:
    """id, entries: list entries that rho has to look among; none where the cutoff is a bin's edge."""
    d = F.lit(float(d_c))
    at = target(hist, d_c, w)
    none = F.col("cum").isNull() | (d <= F.col("min_dist")) | (F.col("max_dist") < d)
    return at.select("id", F.when(none, 0).otherwise(F.col("cum") - F.col("before")).cast("long").alias("entries"))


def size_report(idx: DataFrame, widths: list[float]) -> DataFrame:
    """w, bins, dense_bins: bins that hold entries, and all bins up to each list's last, for several widths."""
    one = None
    for w in widths:
        b = F.expr(f"transform(dists, d -> floor(d / {float(w)!r}D))")
        row = idx.agg(F.sum(F.size(F.array_distinct(b))).cast("long").alias("bins"), F.sum(F.coalesce(F.array_max(b) + 1, F.lit(0))).cast("long").alias("dense_bins"))
        row = row.select(F.lit(float(w)).alias("w"), "bins", "dense_bins")
        one = row if one is None else one.unionByName(row)
    return one


def suggest_w(idx: DataFrame, target_entries: int = 8) -> float:
    """A width whose bins hold about so many entries in the median list."""
    gap = F.when(F.size("dists") > 0, F.element_at("dists", -1) / F.size("dists"))
    return float((idx.agg(F.percentile_approx(gap, 0.5)).first()[0] or 1.0) * target_entries)
