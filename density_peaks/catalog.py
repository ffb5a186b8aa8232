"""Indices kept as tables: built once, reloaded for any cutoff."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from density_peaks.index.tree import Tree
from density_peaks.schemas import Space


def _note(spark: SparkSession, path: str, meta: dict) -> None:
    spark.createDataFrame([(json.dumps(meta, sort_keys=True),)], "meta string").coalesce(1).write.mode("overwrite").json(f"{path}/meta")


def meta(spark: SparkSession, path: str) -> dict:
    return json.loads(spark.read.json(f"{path}/meta").first()["meta"])


def save_list(idx: DataFrame, path: str, **about) -> None:
    """Packed lists as Parquet, rows of near ids together."""
    idx.repartitionByRange(F.col("id")).sortWithinPartitions("id").write.mode("overwrite").parquet(f"{path}/lists")
    _note(idx.sparkSession, path, {"kind": "list", **about})


def save_hist(hist: DataFrame, path: str, **about) -> None:
    """A histogram sorted by bin and id, so that a query for one bin reads few row groups."""
    hist.repartitionByRange(F.col("bin")).sortWithinPartitions("bin", "id").write.mode("overwrite").parquet(f"{path}/hist")
    _note(hist.sparkSession, path, {"kind": "hist", **about})


def save_bucketed(idx: DataFrame, table: str, buckets: int = 8) -> None:
    """An index as a table bucketed by id, whose joins by id move no rows."""
    idx.write.mode("overwrite").bucketBy(buckets, "id").sortBy("id").saveAsTable(table)


def save_tree(tree: Tree, path: str) -> None:
    """Nodes, and points sorted by leaf."""
    tree.nodes.write.mode("overwrite").parquet(f"{path}/nodes")
    tree.leaf_points.repartitionByRange(F.col("leaf")).sortWithinPartitions("leaf", "id").write.mode("overwrite").parquet(f"{path}/leaf_points")
    about = {"coords": list(tree.space.coords), "metric": tree.space.metric, "n_nodes": tree.n_nodes, "height": tree.height, "meta": tree.meta}
    _note(tree.nodes.sparkSession, path, {"kind": "tree", **about})


def load_list(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(f"{path}/lists")


def load_hist(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(f"{path}/hist")


def load_tree(spark: SparkSession, path: str) -> Tree:
    m = meta(spark, path)
    space = Space(tuple(m["coords"]), m["metric"])
    about = {k: tuple(v) if isinstance(v, list) else v for k, v in m["meta"].items()}
    leaf_points = spark.read.parquet(f"{path}/leaf_points")
    return Tree(spark.read.parquet(f"{path}/nodes"), leaf_points, space, m["n_nodes"], m["height"], about, "weight" in leaf_points.columns)
