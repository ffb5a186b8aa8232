"""Iteration: lineage is cut in the shared checkpoint folder, and loops end on a condition."""

from __future__ import annotations

import gc
import os
import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share.

    Where none is set, a local master takes a temporary folder, as all of it runs on one
    machine; a cluster raises RuntimeError, as executors would not see such a folder.
    """
    sc = spark.sparkContext
    set_dir = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if set_dir is None and not sc.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    return set_dir or os.path.join(tempfile.gettempdir(), "density_peaks_checkpoints")


def cut(df: DataFrame) -> DataFrame:
    """Writes df to the shared checkpoint folder and goes on from there."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(shared_dir(df.sparkSession))
    return df.checkpoint(eager=True)


def parked(df: DataFrame) -> DataFrame:
    """df written as compressed Parquet in the shared folder, for tables whose checkpoint, of whole uncompressed rows, would be several times as large.

    The files go when the driver ends.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/parked-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    jvm = spark.sparkContext._jvm
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).deleteOnExit(at)
    return spark.read.parquet(path)


def released(spark: SparkSession) -> None:
    """Has the shuffles of tables that nothing refers to any more removed now, not when the driver happens to collect its garbage."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def settled(df: DataFrame) -> DataFrame:
    """df itself where its plan is a bare scan already, else df cut, so that a nested loop does not evaluate its columns for each pair."""
    kind = df._jdf.queryExecution().optimizedPlan().getClass().getSimpleName()
    return df if kind in ("LogicalRDD", "LocalRelation") else cut(df)


def fixpoint(state: DataFrame, step: Callable[[DataFrame], DataFrame], changed: str = "changed", rounds: int = 64) -> DataFrame:
    """Applies step until no row has its boolean column `changed` set; that column is dropped in the end."""
    for _ in range(rounds):
        state = cut(step(state))
        if state.where(F.col(changed)).isEmpty():
            return state.drop(changed)
    raise RuntimeError(f"no fixpoint after {rounds} rounds")


def components(links: DataFrame, nodes: DataFrame) -> DataFrame:
    """id, label: the smallest id that each of nodes reaches over links (a, b), itself included.

    Each node points to a node of its component that is no larger. In a round a node, and
    the node it points to, take the least of what its neighbours' targets point to, and
    paths are halved; trees hook onto each other as wholes, so rounds grow with the
    logarithm of a chain's length, in whatever order its ids are.
    """
    both = cut(links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct())
    start = nodes.select("id", F.col("id").alias("label"))

    def step(s: DataFrame) -> DataFrame:
        s = s.select("id", "label")
        top = s.join(s.select(F.col("id").alias("label"), F.col("label").alias("top")), "label")
        beside = both.join(top.select(F.col("id").alias("b"), "top"), "b").groupBy("a").agg(F.min("top").alias("least"))
        near = top.join(beside, top["id"] == beside["a"], "left").select("id", "label", F.least("top", F.coalesce("least", "top")).alias("to"))
        # what a node hears goes to itself and to the node that it points to
        heard = near.select("id", "to").unionByName(near.select(F.col("label").alias("id"), "to")).groupBy("id").agg(F.min("to").alias("to"))
        return s.join(heard, "id").select("id", F.least("label", "to").alias("label"), (F.col("to") < F.col("label")).alias("changed"))

    return fixpoint(start, step)
