"""Quadtree of the plane: a square split into four while it holds more than its capacity.

A point's quadrant at each level is a prefix of its Morton key, so counts of all nodes are
sums over key prefixes, and a prefix is a node where its parent holds too many points.
Node numbers are prefixes behind a leading 1: the root is 1 and a parent is the number
shifted right by two bits.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from density_peaks.index.tree import Tree, boxes, merged
from density_peaks.iterate import cut, parked, released
from density_peaks.schemas import PLANE, points


#: Up to so many points, the driver splits the tree from their distinct keys, of 56 bytes each.
MOST_KEYS = 250_000
#: Of more points, the driver splits the upper levels down to this one, and tasks split what is below.
UPPER = 9
#: Points that a task splits, about.
SPLIT_AT_ONCE = 250_000


def morton(pts: DataFrame, region: tuple[float, float, float], depth: int) -> DataFrame:
    """pts with key: depth bit pairs of the point's cell in the square region (x0, y0, side)."""
    x0, y0, side = region
    most = (1 << depth) - 1
    cell = lambda c, o: F.greatest(F.lit(0), F.least(F.lit(most), F.floor((F.col(c) - F.lit(o)) / F.lit(side) * F.lit(float(1 << depth))))).cast("long")
    bits = [F.shiftright(v, b).bitwiseAND(F.lit(1)) * F.lit(1 << (2 * b + s)) for v, s in ((F.col("cx"), 0), (F.col("cy"), 1)) for b in range(depth)]
    out = pts.withColumn("cx", cell("x", x0)).withColumn("cy", cell("y", y0))
    return out.withColumn("key", reduce(lambda a, b: a + b, bits).cast("long")).drop("cx", "cy")


def _number(depth: int) -> Column:
    """The node at column level that column key lies under."""
    return F.expr(f"shiftleft(1L, 2 * level) + shiftright(key, 2 * ({depth} - level))")


def square(pts: DataFrame) -> tuple[float, float, float]:
    b = pts.agg(F.min("x"), F.min("y"), F.max("x"), F.max("y")).first()
    if b[0] is None:
        return 0.0, 0.0, 1.0
    return b[0], b[1], max(b[2] - b[0], b[3] - b[1], 1e-300)


def build(pts: DataFrame, capacity: int = 32, max_depth: int = 16, weight: str | None = None) -> Tree:
    """Builds the tree; a leaf at max_depth may hold more than capacity, as with many equal points.

    With weight, a column of pts, nc is its sum; capacity is of rows all the same.
    """
    p = points(pts, keep=weight)
    keyed = morton(p, region := square(p), max_depth)
    # spots are held already, and their keys are made faster than read
    return _tree(keyed if weight else cut(keyed), capacity, max_depth, region, weight)


def _tree(keyed: DataFrame, capacity: int, depth: int, region: tuple[float, float, float], weight: str | None = None) -> Tree:
    about = {"kind": "quadtree", "capacity": capacity, "depth": depth, "region": region}
    size = [F.count(F.lit(1)).alias("rows"), (F.sum(weight) if weight else F.count(F.lit(1))).alias("nc")]
    own = [weight] if weight else []
    n = keyed.count()
    if n <= MOST_KEYS:
        cells = keyed.groupBy("key").agg(*size, *boxes(PLANE)).toArrow()
        nodes, height, starts, numbers = _split(cells, capacity, depth)
        spark = keyed.sparkSession
        leaf_points = cut(_routed(keyed, spark.sparkContext.broadcast((starts, numbers)), weight))
        return Tree(spark.createDataFrame(nodes), leaf_points, PLANE, nodes.num_rows, height, about, bool(weight))
    leaf_points = parked(_split_below(keyed, capacity, depth, n, weight))
    released(keyed.sparkSession)
    leaves = leaf_points.groupBy(F.col("leaf").alias("node")).agg(size[1], *boxes(PLANE))
    # each node on the way from a leaf to the root, counted from all leaves below it
    level = (F.length(F.bin("node")) - 1) / 2
    up = leaves.withColumn("back", F.explode(F.sequence(F.lit(0), level.cast("int")))).withColumn("node", F.expr("shiftright(node, 2 * back)"))
    nodes = up.groupBy("node").agg(F.sum("nc").cast("long").alias("nc"), *merged(PLANE), F.max(F.col("back") == 0).alias("is_leaf"))
    nodes = nodes.withColumn("level", level.cast("int")).withColumn("parent", F.when(F.col("node") > 1, F.shiftright("node", 2)))
    nodes = cut(nodes.select("node", "parent", "level", "lo_x", "lo_y", "hi_x", "hi_y", "nc", "is_leaf"))
    count, height = nodes.agg(F.count(F.lit(1)), F.coalesce(F.max("level"), F.lit(0))).first()
    return Tree(nodes, leaf_points, PLANE, count, height, about, bool(weight))


def _split_below(keyed: DataFrame, capacity: int, depth: int, n: int, weight: str | None) -> DataFrame:
    """leaf, id, x, y and weight of many points: cells of the level UPPER meet in a task each, which splits those that are too full."""
    spark, upper = keyed.sparkSession, min(UPPER, depth)
    cell = F.shiftright("key", 2 * (depth - upper)).alias("key")
    counts = keyed.groupBy(cell).agg(F.count(F.lit(1)).alias("rows"), F.lit(0).cast("long").alias("nc"), *boxes(PLANE)).toArrow()
    _, _, starts, numbers = _split(counts, capacity, upper)
    full = np.sort(counts.column("key").to_numpy()[counts.column("rows").to_numpy() > capacity])
    sent = spark.sparkContext.broadcast((starts, numbers, full))
    own = ["id", "x", "y", *([weight] if weight else [])]
    parts = max(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-n // SPLIT_AT_ONCE))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        starts, numbers, full = sent.value
        batches = list(batches)
        if not batches:
            return
        t = pa.Table.from_batches(batches)
        key = t.column("key").to_numpy().astype(np.int64)
        at = key >> (2 * (depth - upper))
        leaf = numbers[np.searchsorted(starts, at, side="right") - 1]
        deep = np.flatnonzero(np.isin(at, full)) if upper < depth else np.empty(0, dtype=np.int64)
        if len(deep):
            x, y = (t.column(c).to_numpy()[deep] for c in ("x", "y"))
            one = np.ones(len(deep), dtype=np.int64)
            cells = pa.table({"key": key[deep], "rows": one, "nc": one, "lo_x": x, "hi_x": x, "lo_y": y, "hi_y": y})
            _, _, below, named = _split(cells, capacity, depth, upper)
            leaf[deep] = named[np.searchsorted(below, key[deep], side="right") - 1]
        for b in pa.table([pa.array(leaf, pa.int64()), *(t.column(c) for c in own)], names=["leaf", *own]).to_batches(1 << 16):
            yield b

    dealt = keyed.select("key", *own).repartition(parts, F.shiftright("key", 2 * (depth - upper)))
    return dealt.mapInArrow(run, "leaf long, id long, x double, y double" + (f", {weight} long" if weight else ""))


def _split(cells: pa.Table, capacity: int, depth: int, opened: int = -1) -> tuple[pa.Table, int, np.ndarray, np.ndarray]:
    """The node table over keyed cells that the driver holds, its height, and the first key and number of each leaf in key order. Nodes down to the level opened are split whatever they hold."""
    key = cells.column("key").to_numpy().astype(np.int64)
    order = np.argsort(key, kind="stable")
    key, names = key[order], ["lo_x", "lo_y", "hi_x", "hi_y"]
    held = {c: cells.column(c).to_numpy()[order] for c in ("rows", "nc", *names)}
    fold = {"ro": np.add, "nc": np.add, "lo": np.minimum, "hi": np.maximum}
    made, starts, numbers, open_ = [], [], [], np.arange(len(key))
    for level in range(depth + 1):
        if not len(open_):
            break
        prefix = key[open_] >> (2 * (depth - level))
        at = np.flatnonzero(np.diff(prefix, prepend=-1))
        level_of = {c: fold[c[:2]].reduceat(v[open_], at) for c, v in held.items()}
        node = (1 << (2 * level)) + prefix[at]
        leaf = (level > opened) & ((level_of.pop("rows") <= capacity) | (level == depth))
        made.append({"node": node, "parent": np.where(level > 0, node >> 2, -1), "level": np.full(len(node), level), "is_leaf": leaf, **level_of})
        starts.append(prefix[at][leaf] << (2 * (depth - level)))
        numbers.append(node[leaf])
        open_ = open_[~np.repeat(leaf, np.diff(np.append(at, len(open_))))]
    whole = {c: np.concatenate([m[c] for m in made]) if made else np.empty(0) for c in ("node", "parent", "level", *names, "nc", "is_leaf")}
    kinds = {"node": np.int64, "parent": np.int64, "level": np.int32, "nc": np.int64, "is_leaf": bool}
    columns = {c: pa.array(v.astype(kinds.get(c, np.float64)), mask=v < 0 if c == "parent" else None) for c, v in whole.items()}
    first, number = (np.concatenate([np.empty(0, dtype=np.int64), *x]) for x in (starts, numbers))
    order = np.argsort(first, kind="stable")
    return pa.table(columns), max(0, len(made) - 1), first[order], number[order]


def _routed(keyed: DataFrame, leaves, weight: str | None = None) -> DataFrame:
    """leaf, id, x, y and weight: a point's leaf is the last that starts at or before its key."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        starts, numbers = leaves.value
        for b in batches:
            leaf = numbers[np.searchsorted(starts, b.column("key").to_numpy(), side="right") - 1]
            yield pa.RecordBatch.from_arrays([pa.array(leaf, pa.int64()), *(b.column(c) for c in own)], names=["leaf", *own])

    own = ["id", "x", "y", *([weight] if weight else [])]
    return keyed.select("key", *own).mapInArrow(run, "leaf long, id long, x double, y double" + (f", {weight} long" if weight else ""))


def insert(tree: Tree, new: DataFrame) -> Tree:
    """The tree after a batch of new points: each goes down to its leaf, counts on its path grow, and overfull leaves split.

    Points outside the region are counted in its border cells. Node boxes are of members,
    so searches stay exact. maxrho has to be computed again.
    """
    capacity, depth, region = (tree.meta[k] for k in ("capacity", "depth", "region"))
    fresh = morton(points(new), region, depth)
    level = F.explode(F.sequence(F.lit(0), F.lit(depth))).alias("level")
    paths = fresh.select("*", level).withColumn("node", _number(depth))
    leaves = tree.nodes.where("is_leaf").select(F.col("node").alias("leaf"))
    routed = cut(paths.join(leaves, paths["node"] == leaves["leaf"]).select("leaf", "id", "x", "y"))
    # quadrants that were empty have no node yet: they become leaves of their deepest known ancestor
    lost = fresh.join(routed.select("id"), "id", "left_anti")
    known = tree.nodes.select("node", F.col("level").alias("known_level"))
    deep = lost.select("*", level).withColumn("node", _number(depth)).join(known, "node").groupBy("id", "key", "x", "y").agg(F.max("known_level").alias("l"))
    made = deep.withColumn("level", F.col("l") + 1).withColumn("leaf", _number(depth)).select("leaf", "id", "x", "y")
    all_points = cut(tree.leaf_points.unionByName(routed).unionByName(made))
    sizes = all_points.groupBy("leaf").count()
    over = cut(sizes.where(F.col("count") > capacity).select("leaf"))
    # only points of overfull leaves are keyed again and split further
    keyed = morton(all_points.join(over, "leaf", "left_semi"), region, depth)
    per_key = keyed.groupBy("leaf", "key").agg(F.count(F.lit(1)).alias("nc"))
    below = per_key.select("*", level).withColumn("node", _number(depth)).where(F.length(F.bin("node")) > F.length(F.bin("leaf")))
    counts = cut(below.groupBy("leaf", "node", "level").agg(F.sum("nc").alias("nc")))
    full = counts.where((F.col("nc") > capacity) & (F.col("level") < depth)).select(F.col("node").alias("up")).unionByName(over.select(F.col("leaf").alias("up")))
    split = counts.withColumn("up", F.shiftright("node", 2)).join(full, "up", "left_semi").where((F.col("nc") <= capacity) | (F.col("level") == depth))
    new_leaf = keyed.select("*", level).withColumn("node", _number(depth)).join(split.select("node"), "node").select("id", F.col("node").alias("leaf"), "x", "y")
    at_bottom = over.where(F.length(F.bin("leaf")) == 2 * depth + 1)
    stay = all_points.join(over, "leaf", "left_anti").unionByName(all_points.join(at_bottom, "leaf", "left_semi"))
    moved = cut(stay.select("leaf", "id", "x", "y").unionByName(new_leaf.join(stay.select("id"), "id", "left_anti").select("leaf", "id", "x", "y")))
    leaf_boxes = moved.groupBy(F.col("leaf").alias("node")).agg(F.count(F.lit(1)).alias("nc"), *boxes(PLANE))
    up = leaf_boxes.withColumn("back", F.explode(F.sequence(F.lit(0), ((F.length(F.bin("node")) - 1) / 2).cast("int"))))
    up = up.withColumn("leaf", F.col("node")).withColumn("node", F.expr("shiftright(node, 2 * back)"))
    nodes = up.groupBy("node").agg(F.sum("nc").cast("long").alias("nc"), *merged(PLANE), F.max(F.col("back") == 0).alias("is_leaf"))
    nodes = nodes.withColumn("level", ((F.length(F.bin("node")) - 1) / 2).cast("int")).withColumn("parent", F.when(F.col("node") > 1, F.shiftright("node", 2)))
    nodes = cut(nodes.select("node", "parent", "level", "lo_x", "lo_y", "hi_x", "hi_y", "nc", "is_leaf"))
    n, height = nodes.agg(F.count(F.lit(1)), F.coalesce(F.max("level"), F.lit(0))).first()
    return Tree(nodes, moved, PLANE, n, height, tree.meta)
