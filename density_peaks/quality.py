"""Agreement of two clusterings over pairs of points, from counts of shared clusters."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def contingency(reference: DataFrame, found: DataFrame) -> DataFrame:
    """g, c, n: points in cluster g of the reference and c of the found. Both: id, cluster."""
    g = reference.select("id", F.col("cluster").alias("g"))
    return g.join(found.select("id", F.col("cluster").alias("c")), "id").groupBy("g", "c").agg(F.count(F.lit(1)).alias("n"))


def scores(table: DataFrame) -> DataFrame:
    """tp, fp, fn, precision, recall, f1 of a contingency table; a measure without pairs is null.

    Pairs are counted in DECIMAL, as the square of many points exceeds 64 bits, and are
    never listed.
    """
    two = lambda c: (F.col(c).cast("decimal(19,0)") * (F.col(c) - 1).cast("decimal(19,0)") / 2).cast("decimal(38,0)")
    by_g = table.groupBy("g").agg(F.sum("n").alias("n")).agg(F.sum(two("n")).alias("g_pairs"))
    by_c = table.groupBy("c").agg(F.sum("n").alias("n")).agg(F.sum(two("n")).alias("c_pairs"))
    one = table.agg(F.sum(two("n")).alias("tp")).join(by_g).join(by_c)
    zero = F.lit(0).cast("decimal(38,0)")
    one = one.select(*[F.coalesce(c, zero).cast("decimal(38,0)").alias(c) for c in ("tp", "g_pairs", "c_pairs")])
    tp, found, truth = (F.col(c).cast("double") for c in ("tp", "c_pairs", "g_pairs"))
    p, r = F.when(found > 0, tp / found), F.when(truth > 0, tp / truth)
    return one.select("tp", (F.col("c_pairs") - F.col("tp")).cast("decimal(38,0)").alias("fp"), (F.col("g_pairs") - F.col("tp")).cast("decimal(38,0)").alias("fn"), p.alias("precision"), r.alias("recall"), F.when(p + r > 0, 2 * p * r / (p + r)).alias("f1"))


def pair_scores(reference: DataFrame, found: DataFrame) -> DataFrame:
    """Scores of a found clustering against a reference; both have id, cluster."""
    return scores(contingency(reference, found))
