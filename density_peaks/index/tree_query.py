"""Density and dependent distance by descent of either tree.

Both distributed forms move a frontier of (query leaf, node) pairs down: in vectors over all
levels at once where the node table can be sent to tasks (see descent), else as a table that
goes down a level a job. One pair stands for all points of a leaf, whose box is tested against the node's. A node wholly
within the cutoff adds its count to the whole leaf, one wholly outside is dropped, others
give way to their children; only pairs of leaves come down to points. For dependent
distances a node is kept where its greatest density exceeds the leaf's least and it is no
farther than the leaf's bound, which falls as nodes that surely hold a denser point for
all of the leaf are met. The local form descends for one point at a time, nearest first.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from density_peaks.dependent import denser, finish, key
from density_peaks.index import descent
from density_peaks.index.tree import Tree
from density_peaks.iterate import cut
from density_peaks.metrics import box_max, box_min, d_max, d_min, dist

INFINITE = float("inf")


def classify(least: Column, most: Column, d_c: float) -> Column:
    """contained, discarded or explored, from a node's least and largest distance."""
    return F.when(most < d_c, "contained").when(least >= d_c, "discarded").otherwise("explored")


def _leaves(tree: Tree, prefix: str = "q_") -> DataFrame:
    return tree.nodes.where("is_leaf").select(F.col("node").alias(f"{prefix}leaf"), *[F.col(b).alias(f"{prefix}{b}") for b in tree.bounds])


def _ranges(tree: Tree) -> tuple[Column, Column]:
    four = tree.lo("q_"), tree.hi("q_"), tree.lo(), tree.hi()
    return box_min(*four, tree.space), box_max(*four, tree.space)


def _points(tree: Tree, prefix: str = "") -> DataFrame:
    return tree.leaf_points.select(*[F.col(c).alias(f"{prefix}{c}") for c in ("leaf", "id", *tree.space.coords, *(["weight"] if tree.weighted else []))])


def rho(tree: Tree, d_c: float, count_self: bool = False, contain: bool = True, stats: dict | None = None) -> DataFrame:
    """id, rho of all points of the tree.

    contain=False is the plain range search, which opens contained nodes too. stats, if
    given, gets the numbers of node pairs, contained ones, leaf pairs and distances.
    """
    p = _points(tree)
    if d_c <= 0:
        return p.select("id", F.lit(int(count_self)).cast("long").alias("rho"))
    if tree.arrays() is not None and stats is None:
        if tree.rows() > descent.MOST_COUNTED:
            return descent.counted(tree, p, d_c, contain).select("id", (F.col("n") - F.lit(0 if count_self else 1)).alias("rho"))
        nodes = tree.arrays()
        work = descent.Count(nodes, descent.Held.of(nodes, p, tree.space), d_c, contain)
        return descent.over_leaves(tree, np.flatnonzero(nodes.leaf), work, descent.COUNT).select("id", (F.col("n") - F.lit(0 if count_self else 1)).alias("rho"))
    full, pair = _range(tree, d_c, contain, stats) if tree.arrays() is not None else _range_frontier(tree, d_c, contain, stats)
    met = pair.join(_points(tree, "q_"), "q_leaf").join(_points(tree, "n_"), "n_leaf")
    near = met.where(dist(tree.space.of("q_"), tree.space.of("n_"), tree.space) < d_c).groupBy(F.col("q_id").alias("id")).agg((F.sum("n_weight") if tree.weighted else F.count(F.lit(1))).alias("near"))
    if stats is not None:
        stats["leaf_pairs"] = pair.count()
        stats["distances"] = met.count()
    # the point itself is among those found
    total = F.coalesce("full", F.lit(0)) + F.coalesce("near", F.lit(0)) - F.lit(0 if count_self else 1)
    return p.withColumnRenamed("leaf", "q_leaf").join(full, "q_leaf", "left").join(near, "id", "left").select("id", total.cast("long").alias("rho"))


def _range(tree: Tree, d_c: float, contain: bool, stats: dict | None) -> tuple[DataFrame, DataFrame]:
    """q_leaf, full and q_leaf, n_leaf: points within the cutoff by whole nodes, and pairs of leaves to look into. All levels in one pass."""
    nodes = tree.arrays()
    out = cut(descent.over_leaves(tree, np.flatnonzero(nodes.leaf), descent.Range(nodes, d_c, contain), descent.RANGE))
    if stats is not None:
        seen = out.agg(F.sum("node_pairs"), F.sum("contained")).first()
        stats["node_pairs"], stats["contained"] = seen[0], seen[1]
    return out.where("n_leaf < 0").select("q_leaf", "full"), out.where("n_leaf >= 0").select("q_leaf", "n_leaf")


def _range_frontier(tree: Tree, d_c: float, contain: bool, stats: dict | None) -> tuple[DataFrame, DataFrame]:
    """The same by a frontier table that goes down a level a job, for node tables of any size."""
    nodes = tree.small(tree.nodes)
    front = _leaves(tree).join(F.broadcast(tree.nodes.where("parent is null")))
    whole, edges, seen = [], [], []
    for _ in range(tree.height + 1):
        least, most = _ranges(tree)
        front = cut(front.withColumn("least", least).withColumn("most", most).withColumn("test", classify(F.col("least"), F.col("most"), d_c) if contain else F.when(F.col("least") >= d_c, "discarded").otherwise("explored")))
        seen.append(front)
        whole.append(front.where("test = 'contained'").select("q_leaf", "nc"))
        edges.append(front.where("test = 'explored' and is_leaf").select("q_leaf", F.col("node").alias("n_leaf")))
        opened = front.where("test = 'explored' and not is_leaf").select("q_leaf", *[f"q_{b}" for b in tree.bounds], F.col("node").alias("parent"))
        front = opened.join(nodes, "parent")
    both = lambda dfs: reduce(lambda a, b: a.unionByName(b), dfs)
    if stats is not None:
        stats["node_pairs"] = sum(f.count() for f in seen)
        stats["contained"] = sum(f.count() for f in whole)
    return both(whole).groupBy("q_leaf").agg(F.sum("nc").alias("full")), cut(both(edges))


def with_maxrho(tree: Tree, rho_table: DataFrame, tie: str = "strict") -> tuple[DataFrame, DataFrame]:
    """Nodes with maxkey, the greatest density key below each, and points with their own key."""
    own = _points(tree).join(rho_table.select("id", "rho"), "id").withColumn("key", key(F.col("rho"), F.col("id"), tie))
    own = cut(own)
    level = own.groupBy(F.col("leaf").alias("node")).agg(F.max("key").alias("maxkey"))
    found = [level]
    links = tree.small(tree.nodes.select("node", "parent", "level"))
    for at in range(tree.height, 0, -1):
        here = reduce(lambda a, b: a.unionByName(b), found).join(links, "node").where(F.col("level") == at)
        found.append(here.groupBy(F.col("parent").alias("node")).agg(F.max("maxkey").alias("maxkey")))
        found = [cut(reduce(lambda a, b: a.unionByName(b), found).groupBy("node").agg(F.max("maxkey").alias("maxkey")))]
    return cut(tree.nodes.join(found[0], "node")), own


def delta(tree: Tree, rho_table: DataFrame, tie: str = "strict", density_prune: bool = True, distance_prune: bool = True, only: DataFrame | None = None, stats: dict | None = None) -> DataFrame:
    """The dependent table of all points of the tree, or of the ids in only.

    The prune switches turn off density or distance pruning for comparison; answers stay.
    """
    if tree.arrays() is not None:
        own = cut(_points(tree).join(rho_table.select("id", "rho"), "id"))
        asked = own if only is None else own.join(only.select("id"), "id", "left_semi")
        if only is None and stats is None and tree.rows() <= descent.MOST_SENT:
            found = _search_sent(tree, own, tie, density_prune, distance_prune)
        else:
            found = _search_arrays(tree, own, asked, tie, density_prune, distance_prune, stats)
    else:
        nodes, own = with_maxrho(tree, rho_table, tie)
        asked = own if only is None else own.join(only.select("id"), "id", "left_semi")
        found = _search(tree, nodes, own, asked, density_prune, distance_prune, stats)
    tops = found.where("mu is null").select("id")
    far = farthest(tree, tops)
    table = rho_table if only is None else rho_table.join(only.select("id"), "id", "left_semi")
    return finish(table, found.join(far, "id", "left"))


def _search_sent(tree: Tree, own: DataFrame, tie: str, density_prune: bool, distance_prune: bool) -> DataFrame:
    """id, delta, mu of all points, measured in the tasks that descend."""
    nodes = tree.arrays()
    work = descent.Parents(nodes, descent.Held.of(nodes, own, tree.space, tie), density_prune, distance_prune)
    some = descent.over_leaves(tree, np.flatnonzero(nodes.leaf), work, descent.PARENTS)
    return cut(own.select("id").join(some.where(F.col("delta") < INFINITE), "id", "left"))


def _search_arrays(tree: Tree, own: DataFrame, asked: DataFrame, tie: str, density_prune: bool, distance_prune: bool, stats: dict | None) -> DataFrame:
    """id, delta, mu: the nearest denser point of each point asked for. own: leaf, id, coordinates, rho.

    The driver holds a few values a leaf; the tasks descend with them in one pass.
    """
    space, nodes = tree.space, tree.arrays()
    named = lambda df, p: df.select(*[F.col(c).alias(f"{p}{c}") for c in ("leaf", "id", "rho", *space.coords)])
    gap = dist(space.of("q_"), space.of("n_"), space)
    up = denser("n_rho", "n_id", "q_rho", "q_id", tie)
    mine, theirs = named(asked, "q_"), named(own, "n_")
    # a first bound from the point's own leaf; least distances alone stay in hashed aggregation
    seed = mine.join(theirs, F.col("q_leaf") == F.col("n_leaf")).where(up).groupBy("q_id").agg(F.min(gap).alias("seed"))
    mine = cut(mine.join(seed, "q_id", "left"))
    bound = F.coalesce("seed", F.lit(INFINITE))
    turn = -F.col("id") if tie == "by_id" else F.lit(0).cast("long")
    ends = own.groupBy("leaf").agg(F.max(F.struct("rho", turn.alias("turn"))).alias("k")).select("leaf", "k.rho", "k.turn").toArrow()
    q_turn = -F.col("q_id") if tie == "by_id" else F.lit(0).cast("long")
    q_key = F.struct(F.col("q_rho").alias("rho"), q_turn.alias("turn"))
    # what nothing exceeds has no bound and is not searched for
    peak_rho = max(ends.column("rho").to_pylist(), default=0)
    peak_id = -max((t for r, t in zip(ends.column("rho").to_pylist(), ends.column("turn").to_pylist(), strict=True) if r == peak_rho), default=0)
    mine = mine.where(F.col("q_rho") < peak_rho if tie == "strict" else ~((F.col("q_rho") == peak_rho) & (F.col("q_id") == peak_id)))
    q = mine.groupBy("q_leaf").agg(F.min(q_key).alias("lo"), F.max(q_key).alias("hi"), F.max(bound).alias("bound"))
    q = q.select("q_leaf", "lo.rho", "lo.turn", F.col("hi.rho").alias("rho2"), F.col("hi.turn").alias("turn2"), "bound").toArrow()
    get = lambda t, c: t.column(c).to_numpy()
    # density keys of leaves by rank, so that one number a node compares them
    pairs_of = [np.stack((get(t, a), get(t, b)), axis=1).astype(np.int64) for t, a, b in ((ends, "rho", "turn"), (q, "rho", "turn"), (q, "rho2", "turn2"))]
    _, rank = np.unique(np.concatenate(pairs_of), axis=0, return_inverse=True)
    top, low, high = np.split(rank.ravel().astype(np.int64), np.cumsum([len(x) for x in pairs_of])[:-1])
    maxkey = np.full(len(nodes), -1, dtype=np.int64)
    maxkey[nodes.at(get(ends, "leaf"))] = top
    places = nodes.at(get(q, "q_leaf"))
    minkey, topkey, limit = (np.zeros(len(nodes), dtype=np.int64), np.zeros(len(nodes), dtype=np.int64), np.full(len(nodes), INFINITE))
    minkey[places], topkey[places], limit[places] = low, high, get(q, "bound")
    work = descent.Denser(nodes, minkey, topkey, nodes.rolled(maxkey), limit, density_prune, distance_prune)
    out = descent.over_leaves(tree, places, work, descent.DENSER)
    if stats is not None:
        out = cut(out)
        stats["node_pairs"] = out.agg(F.sum("node_pairs")).first()[0]
    leaf = tree.nodes.where("is_leaf").select(F.col("node").alias("n_leaf"), *tree.bounds)
    peak = own.groupBy(F.col("leaf").alias("n_leaf")).agg(F.max("rho").alias("peak"))
    met = out.where("n_leaf >= 0").select("q_leaf", "n_leaf", "last").join(tree.small(leaf), "n_leaf").join(tree.small(peak), "n_leaf").join(mine, "q_leaf")
    if density_prune:
        met = met.where(F.col("peak") > F.col("q_rho") if tie == "strict" else F.col("peak") >= F.col("q_rho"))
    if distance_prune:
        met = met.where(d_min(space.of("q_"), tree.lo(), tree.hi(), space) <= F.least(bound, F.col("last")))
    met = met.select("q_id", "q_rho", "n_leaf", *[f"q_{c}" for c in space.coords])
    if stats is not None:
        met = cut(met)
        stats["leaf_rows"] = met.count()
        stats["distances"] = met.join(theirs, "n_leaf").count()
    near = met.join(theirs, "n_leaf").where(up)
    least = near.groupBy("q_id").agg(F.min(gap).alias("delta"))
    # then the smallest id at that distance
    at = met.join(least, "q_id").join(theirs, "n_leaf").where(up & (gap == F.col("delta"))).groupBy("q_id").agg(F.min("delta").alias("delta"), F.min("n_id").alias("mu"))
    return cut(asked.select("id").join(at.withColumnRenamed("q_id", "id"), "id", "left").select("id", "delta", "mu"))


def _search(tree: Tree, nodes: DataFrame, own: DataFrame, asked: DataFrame, density_prune: bool, distance_prune: bool, stats: dict | None) -> DataFrame:
    """id, delta, mu: the nearest point of a greater key of each point asked for."""
    space = tree.space
    mine = asked.select(*[F.col(c).alias(f"q_{c}") for c in ("leaf", "id", "key", *space.coords)])
    theirs = own.select(*[F.col(c).alias(f"n_{c}") for c in ("leaf", "id", "key", *space.coords)])
    gap = dist(space.of("q_"), space.of("n_"), space)
    best = lambda met: met.where(F.col("n_key") > F.col("q_key")).groupBy("q_id").agg(F.min(F.struct(gap.alias("dist"), F.col("n_id").alias("id"))).alias("best"))
    # a first bound from the point's own leaf
    seed = cut(best(mine.join(theirs, F.col("q_leaf") == F.col("n_leaf"))))
    mine = cut(mine.join(seed, "q_id", "left"))
    bound = F.coalesce(F.col("best.dist"), F.lit(INFINITE))
    q = mine.groupBy("q_leaf").agg(F.min("q_key").alias("minkey"), F.max("q_key").alias("topkey"), F.max(bound).alias("bound"))
    q = q.join(tree.small(_leaves(tree)), "q_leaf")
    front = q.join(F.broadcast(nodes.where("parent is null")))
    carried = ["q_leaf", "minkey", "topkey", *[f"q_{b}" for b in tree.bounds]]
    edges, seen = [], []
    down = tree.small(nodes)
    for _ in range(tree.height + 1):
        least, most = _ranges(tree)
        front = front.withColumn("least", least)
        if density_prune:
            front = front.where(F.col("maxkey") > F.col("minkey"))
        # a node whose greatest key exceeds every key of the leaf bounds the distance of all its points
        front = cut(front.withColumn("sure", F.when(F.col("maxkey") > F.col("topkey"), most)))
        seen.append(front)
        if distance_prune:
            limit = front.groupBy("q_leaf").agg(F.least(F.min("bound"), F.min("sure")).alias("limit"))
            front = front.join(limit, "q_leaf").where(F.col("least") <= F.col("limit")).withColumn("bound", F.col("limit")).drop("limit")
        front = cut(front)
        edges.append(front.where("is_leaf").select("q_leaf", F.col("node").alias("n_leaf"), "bound", F.col("maxkey"), *tree.bounds))
        front = front.where("not is_leaf").select(*carried, "bound", F.col("node").alias("parent")).join(down, "parent")
    pairs = reduce(lambda a, b: a.unionByName(b), edges)
    if distance_prune:  # bounds have fallen since the upper leaves were kept
        last = pairs.groupBy("q_leaf").agg(F.min("bound").alias("last"))
        pairs = pairs.drop("bound").join(last, "q_leaf")
    met = pairs.join(mine, "q_leaf")
    if density_prune:
        met = met.where(F.col("maxkey") > F.col("q_key"))
    if distance_prune:
        met = met.where(d_min(space.of("q_"), tree.lo(), tree.hi(), space) <= F.least(bound, F.col("last")))
    met = cut(met.select("q_id", "q_key", "n_leaf", *[f"q_{c}" for c in space.coords]))
    found = best(met.join(theirs, "n_leaf"))
    if stats is not None:
        stats["node_pairs"] = sum(f.count() for f in seen)
        stats["leaf_rows"] = met.count()
        stats["distances"] = met.join(theirs, "n_leaf").count()
    both = asked.select("id").join(found.select(F.col("q_id").alias("id"), "best"), "id", "left")
    return cut(both.select("id", F.col("best.dist").alias("delta"), F.col("best.id").alias("mu")))


def farthest(tree: Tree, tops: DataFrame) -> DataFrame:
    """id, far: the largest distance of each of a few points, from the leaves that can hold it."""
    space = tree.space
    t = _points(tree).join(tops.select("id"), "id", "left_semi").select(*[F.col(c).alias(f"t_{c}") for c in ("leaf", "id", *space.coords)])
    leaves = tree.nodes.where("is_leaf").select(F.col("node").alias("n_leaf"), *tree.bounds)
    nodes = tree.arrays()
    if nodes is not None:
        t = cut(t)
        held = t.select("t_leaf").distinct().toArrow().column(0).to_numpy()
        pair = descent.over_leaves(tree, nodes.at(held), descent.Farthest(nodes), descent.PAIRS)
        met = t.join(pair, F.col("t_leaf") == F.col("q_leaf")).join(tree.small(leaves), "n_leaf")
    else:
        met = leaves.join(t)
    met = met.withColumn("least", d_min(space.of("t_"), tree.lo(), tree.hi(), space)).withColumn("most", d_max(space.of("t_"), tree.lo(), tree.hi(), space))
    reach = met.groupBy("t_id").agg(F.max("least").alias("reach"))
    kept = met.join(reach, "t_id").where(F.col("most") >= F.col("reach")).select("t_id", *[f"t_{c}" for c in space.coords], F.col("n_leaf").alias("leaf"))
    return kept.join(_points(tree), "leaf").groupBy(F.col("t_id").alias("id")).agg(F.max(dist(space.of("t_"), space.of(), space)).alias("far"))


def nearest(tree: Tree, k: int = 1) -> DataFrame:
    """id, nbr, dist, pos: the k nearest others of each point, whatever their density.

    Nodes that together hold more than k points bound the k-th neighbour of all points of a
    leaf by their largest distances; the bound falls from level to level.
    """
    space, nodes = tree.space, tree.arrays()
    if nodes is not None:
        kept = descent.over_leaves(tree, np.flatnonzero(nodes.leaf), descent.Nearest(nodes, k), descent.PAIRS)
    else:
        other = tree.nodes.where("is_leaf").select(F.col("node").alias("n_leaf"), "nc", *tree.bounds)
        least, most = _ranges(tree)
        met = _leaves(tree).join(tree.small(other)).withColumn("least", least).withColumn("most", most)
        near = Window.partitionBy("q_leaf").orderBy("most", "n_leaf").rowsBetween(Window.unboundedPreceding, Window.currentRow)
        held = met.withColumn("sum_nc", F.sum("nc").over(near))
        reach = held.where(F.col("sum_nc") > k).groupBy("q_leaf").agg(F.min("most").alias("reach"))
        kept = met.join(reach, "q_leaf", "left").where(F.col("reach").isNull() | (F.col("least") <= F.col("reach"))).select("q_leaf", "n_leaf")
    pair = kept.join(_points(tree, "q_"), "q_leaf").join(_points(tree, "n_"), "n_leaf").where("q_id <> n_id")
    pair = pair.select(F.col("q_id").alias("id"), F.col("n_id").alias("nbr"), dist(space.of("q_"), space.of("n_"), space).alias("dist"))
    pos = F.row_number().over(Window.partitionBy("id").orderBy("dist", "nbr"))
    return pair.withColumn("pos", pos).where(F.col("pos") <= k).select("id", "nbr", "dist", "pos")


def delta_local(tree: Tree, rho_table: DataFrame, tie: str = "strict", order: str = "stack") -> DataFrame:
    """id, delta, mu, visited, distances by descent for one point at a time, in tasks that hold nodes and points as arrays.

    order="stack" opens the nearest child of a node first; order="heap" the nearest node of
    all. Both give the same answers. Only for trees whose nodes and points fit one task.
    """
    if order not in ("stack", "heap"):
        raise ValueError("order is stack or heap")
    if tree.n_nodes > descent.MOST_NODES or tree.rows() > descent.MOST_SENT:
        raise ValueError(f"the local form is for trees of at most {descent.MOST_NODES} nodes and {descent.MOST_SENT} points")
    if tree.space.metric not in ("euclidean", "chord"):
        raise ValueError("the local form knows the euclidean metric only")
    nodes, own = tree.arrays(), _points(tree).join(rho_table.select("id", "rho"), "id")
    work = descent.Local(nodes, descent.Held.of(nodes, own, tree.space, tie), order)
    found = descent.over_leaves(tree, np.flatnonzero(nodes.leaf), work, descent.LOCAL)
    known = F.col("mu") >= 0
    return found.select("id", F.when(known, F.col("delta")).alias("delta"), F.when(known, F.col("mu")).alias("mu"), "visited", "distances")
