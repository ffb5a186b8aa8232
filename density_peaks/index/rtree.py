"""Packed R-tree: points sorted into slices and leaves of equal size, then nodes grouped upward."""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from density_peaks.index import descent
from density_peaks.index import tree as shared
from density_peaks.index.tree import Tree, boxes, merged
from density_peaks.iterate import cut
from density_peaks.rank import global_rank
from density_peaks.schemas import PLANE, Space, points

#: Level and place make a node number: place + level * STRIDE, leaves at level 0.
STRIDE = 1 << 44


def build(pts: DataFrame, capacity: int = 32, fanout: int = 4, space: Space = PLANE, weight: str | None = None) -> Tree:
    """Sorts by the first axis, cuts slices, sorts each by the next axis, and cuts leaves of at most capacity.

    With L leaves, each axis but the last is cut into about L ** (1 / axes) slices. Upper
    levels take fanout nodes in packing order until one is left; they are made on the
    driver from the boxes of at most descent.MOST_NODES / 2 leaves, else level by level.
    No points give a tree without nodes. With weight, a column of pts, nc is its sum;
    capacity is of rows all the same.
    """
    p, own = points(pts, space, keep=weight), [weight] if weight else []
    n = p.count()
    leaves = max(1, math.ceil(n / capacity))
    axes = list(space.coords)
    across = math.ceil(leaves ** (1 / len(axes)) - 1e-9)
    width = capacity * across ** (len(axes) - 1)
    ranked = global_rank(p, [F.col(axes[0]), F.col("id")], "r").withColumn("slice", F.floor(F.col("r") / F.lit(width)).cast("long"))
    for i, axis in enumerate(axes[1:], 1):
        width = capacity * across ** (len(axes) - 1 - i)
        inside = F.row_number().over(Window.partitionBy("slice").orderBy(axis, "id")) - 1
        ranked = ranked.withColumn("slice", F.col("slice") * F.lit(across) + F.floor(inside / F.lit(width)).cast("long"))
    # every slice but the last is full, so leaves are numbered without gaps and the levels above are full
    leaf_points = cut(ranked.select(F.col("slice").alias("leaf"), "id", *space.coords, *own))
    level = leaf_points.groupBy(F.col("leaf").alias("place")).agg((F.sum(weight) if weight else F.count(F.lit(1))).alias("nc"), *boxes(space))
    level = level.select("place", "nc", *[f"{e}_{c}" for e in ("lo", "hi") for c in space.coords])
    about = {"kind": "rtree", "capacity": capacity, "fanout": fanout}
    if 2 * leaves <= descent.MOST_NODES:
        nodes, up = _grouped(level.toArrow(), fanout)
        return Tree(p.sparkSession.createDataFrame(nodes), leaf_points, space, nodes.num_rows, up, about, bool(weight))
    level, count, up, levels = cut(level), leaves, 0, []
    while True:
        parent = F.lit(None).cast("long") if count <= 1 else F.floor(F.col("place") / F.lit(fanout)).cast("long") + F.lit((up + 1) * STRIDE)
        levels.append(level.select((F.col("place") + F.lit(up * STRIDE)).alias("node"), parent.alias("parent"), F.lit(up).alias("up"), *level.columns[1:]))
        if count <= 1:
            break
        level = cut(level.groupBy(F.floor(F.col("place") / F.lit(fanout)).cast("long").alias("place")).agg(F.sum("nc").cast("long").alias("nc"), *merged(space)))
        level = level.select("place", "nc", *[f"{e}_{c}" for e in ("lo", "hi") for c in space.coords])
        count, up = math.ceil(count / fanout), up + 1
    nodes = levels[0]
    for x in levels[1:]:
        nodes = nodes.unionByName(x)
    nodes = nodes.withColumn("level", (F.lit(up) - F.col("up")).cast("int")).withColumn("is_leaf", F.col("up") == 0).withColumn("nc", F.col("nc").cast("long")).drop("up")
    nodes = cut(nodes)
    return Tree(nodes, leaf_points, space, nodes.count(), up, about, bool(weight))


def _grouped(leaves: pa.Table, fanout: int) -> tuple[pa.Table, int]:
    """The node table over leaves (place, nc, boxes) that the driver holds, and its height."""
    names = leaves.column_names[1:]
    order = np.argsort(leaves.column("place").to_numpy(), kind="stable")
    level = {c: leaves.column(c).to_numpy()[order] for c in names}
    made: list[dict[str, np.ndarray]] = []
    fold = {"nc": np.add, "lo": np.minimum, "hi": np.maximum}
    while n := len(level["nc"]):
        up, place = len(made), np.arange(n)
        made.append({"node": place + up * STRIDE, "parent": np.where(n > 1, place // fanout + (up + 1) * STRIDE, -1), "up": np.full(n, up), **level})
        if n == 1:
            break
        level = {c: fold[c[:2]].reduceat(v, np.arange(0, n, fanout)) for c, v in level.items()}
    whole = {c: np.concatenate([m[c] for m in made]) if made else np.empty(0) for c in ("node", "parent", "up", *names)}
    height = max(0, len(made) - 1)
    parent = pa.array(whole["parent"].astype(np.int64), mask=whole["parent"] < 0)
    columns = {"node": pa.array(whole["node"].astype(np.int64)), "parent": parent, "nc": pa.array(whole["nc"].astype(np.int64))}
    columns |= {c: pa.array(whole[c].astype(np.float64)) for c in names[1:]}
    columns |= {"level": pa.array((height - whole["up"]).astype(np.int32)), "is_leaf": pa.array(whole["up"] == 0)}
    return pa.table(columns), height


def report(tree: Tree) -> DataFrame:
    """Height, coverage and overlap by level."""
    return shared.report(tree)
