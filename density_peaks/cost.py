"""Cost measures: time, size of an index, probes, nodes and distances, and what a plan does."""

from __future__ import annotations

import time
from collections.abc import Callable
from pathlib import PurePosixPath
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def force(df: DataFrame) -> None:
    """Runs a plan whole and drops its rows."""
    df.write.format("noop").mode("overwrite").save()


def timed(fn: Callable[[], Any]) -> tuple[Any, float]:
    """The result of fn, run whole if it is a DataFrame, and the seconds taken."""
    t = time.perf_counter()
    out = fn()
    if isinstance(out, DataFrame):
        force(out)
    return out, time.perf_counter() - t


def list_bytes(idx: DataFrame) -> DataFrame:
    """entries, bytes: an id and a distance of eight bytes each for every entry of packed lists."""
    return idx.agg(F.coalesce(F.sum(F.size("dists")), F.lit(0)).cast("long").alias("entries")).withColumn("bytes", F.col("entries") * 16)


def hist_bytes(hist: DataFrame) -> DataFrame:
    """bins, bytes of a sparse histogram: five values of eight bytes a bin."""
    return hist.agg(F.count(F.lit(1)).alias("bins")).withColumn("bytes", F.col("bins") * 40)


def packed_hist_bytes(hist: DataFrame) -> DataFrame:
    """bins, bytes of packed histograms: a count of four bytes a bin, empty ones too."""
    return hist.agg(F.coalesce(F.sum(F.size("cum")), F.lit(0)).cast("long").alias("bins")).withColumn("bytes", F.col("bins") * 4)


def tree_bytes(tree) -> DataFrame:
    """nodes, bytes: number, parent, level, count, maxrho and a box of eight bytes a value, and a leaf number a point."""
    width = 8 * (5 + 2 * len(tree.space.coords))
    p = tree.leaf_points.agg(F.count(F.lit(1)).alias("points"))
    return tree.nodes.agg(F.count(F.lit(1)).alias("nodes")).join(p).select("nodes", (F.col("nodes") * width + F.col("points") * 8).alias("bytes"))


def stored_bytes(spark, path: str) -> int:
    """Bytes of the files below a path, asked of the store that holds them."""
    jvm, p = spark._jvm, spark._jvm.org.apache.hadoop.fs.Path(str(PurePosixPath(path)) if "://" not in path else path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(p).getLength() if jvm else 0


def probe_fraction(probes: DataFrame) -> DataFrame:
    """probes, entries, fraction: share of list entries that a search for dependent points reads."""
    return probes.agg(F.sum("probes").alias("probes"), F.sum("entries").alias("entries")).withColumn("fraction", F.col("probes") / F.col("entries"))


def gain(base_s: float, other_s: float) -> float:
    """Share of the time of base that other saves."""
    return (base_s - other_s) / base_s if base_s else 0.0


def plan_facts(df: DataFrame) -> dict[str, int]:
    """Operators of a physical plan that move or combine rows, by number."""
    text = df._jdf.queryExecution().executedPlan().toString()
    names = ("Exchange hashpartitioning", "Exchange rangepartitioning", "Exchange SinglePartition", "BroadcastExchange", "SortMergeJoin", "BroadcastHashJoin", "BroadcastNestedLoopJoin", "CartesianProduct", "Window", "InPandas")
    return {n: text.count(n) for n in names}
