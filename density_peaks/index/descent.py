"""Descent of a tree's node table as arrays: all levels in one pass for many query leaves.

A node table of at most MOST_NODES rows is sent whole to the tasks; each takes a share of
the query leaves and moves their frontier of (leaf, node) pairs down in vectors. Boxes are
measured with the same operations in the same order as the column expressions of metrics,
so both forms decide alike. Larger trees take the frontier of tree_query instead. Where the
points fit too, they are sent along, and tasks measure them against each other in blocks of
vectors, so that pairs of points are never rows of a table.
"""

from __future__ import annotations

import heapq
import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from density_peaks.index.tree import Tree
from density_peaks.schemas import Space

#: Node tables of at most so many rows, of under 100 bytes each, are sent to tasks as arrays.
MOST_NODES = 500_000
#: Query leaves that are taken down at once.
AT_ONCE = 2048
#: Points (or spots) of a tree, of under 50 bytes each, are sent to tasks up to so many.
MOST_SENT = 2_000_000
#: Density sends its points up to so many; of more, the driver holds none and tasks count by tiles.
MOST_COUNTED = 500_000
#: Points of a tile at most, besides those of other tiles that it needs.
TILE = 400_000
#: Query leaves whose points are measured at once, and distances in a block of vectors.
LEAVES, BLOCK = 256, 1 << 18


def norm(gaps: list[np.ndarray], metric: str) -> np.ndarray:
    """Length of differences by axis, added from left to right."""
    if metric in ("euclidean", "chord"):
        total = gaps[0] * gaps[0]
        for g in gaps[1:]:
            total = total + g * g
        return np.sqrt(total)
    if metric == "manhattan":
        total = np.abs(gaps[0])
        for g in gaps[1:]:
            total = total + np.abs(g)
        return total
    if metric == "chebyshev":
        return np.max(np.abs(gaps), axis=0)
    raise ValueError(f"no bounds for metric {metric}")


@dataclass
class Nodes:
    """A node table as arrays: numbers, boxes, counts, leaf marks, and the children of node i at order[first[i] : first[i + 1]]."""

    node: np.ndarray
    lo: np.ndarray
    hi: np.ndarray
    nc: np.ndarray
    leaf: np.ndarray
    level: np.ndarray
    up: np.ndarray
    first: np.ndarray
    order: np.ndarray
    metric: str

    @classmethod
    def of(cls, tree: Tree) -> Nodes:
        space: Space = tree.space
        n = tree.nodes.select("node", "parent", "level", "nc", "is_leaf", *tree.bounds).toArrow()
        col = lambda c: n.column(c).to_numpy()
        node = col("node").astype(np.int64)
        by = np.argsort(node, kind="stable")
        node = node[by]
        parent = n.column("parent").fill_null(-1).to_numpy().astype(np.int64)[by]
        up = np.where(parent >= 0, np.searchsorted(node, parent), -1)
        up[parent < 0] = -1
        order = np.argsort(up, kind="stable")
        first = np.searchsorted(up[order], np.arange(len(node) + 1))
        lo, hi = (np.stack([col(f"{e}_{c}") for c in space.coords]).astype(np.float64)[:, by] for e in ("lo", "hi"))
        return cls(node, lo, hi, col("nc").astype(np.int64)[by], col("is_leaf").astype(bool)[by], col("level").astype(np.int64)[by], up, first, order, space.metric)

    def __len__(self) -> int:
        return len(self.node)

    @property
    def root(self) -> int:
        return int(np.flatnonzero(self.up < 0)[0])

    def at(self, numbers: np.ndarray) -> np.ndarray:
        """Places of node numbers."""
        return np.searchsorted(self.node, numbers)

    def least(self, q: np.ndarray, n: np.ndarray) -> np.ndarray:
        """Least distance between the boxes of nodes q and n."""
        return norm([np.maximum(np.maximum(self.lo[a][n] - self.hi[a][q], self.lo[a][q] - self.hi[a][n]), 0.0) for a in range(len(self.lo))], self.metric)

    def most(self, q: np.ndarray, n: np.ndarray) -> np.ndarray:
        """Largest distance between the boxes of nodes q and n."""
        return norm([np.maximum(np.abs(self.hi[a][n] - self.lo[a][q]), np.abs(self.hi[a][q] - self.lo[a][n])) for a in range(len(self.lo))], self.metric)

    def children(self, q: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """The pairs of q with the children of n, and the place in n that each came from."""
        count = self.first[n + 1] - self.first[n]
        came = np.repeat(np.arange(len(n)), count)
        inside = np.arange(len(came)) - np.repeat(np.cumsum(count) - count, count)
        return q[came], self.order[self.first[n][came] + inside], came

    def rolled(self, values: np.ndarray) -> np.ndarray:
        """The greatest value at or below each node, given values of leaves (others least)."""
        out = values.copy()
        for level in range(int(self.level.max(initial=0)), 0, -1):
            here = np.flatnonzero(self.level == level)
            np.maximum.at(out, self.up[here], out[here])
        return out


def least_by(group: np.ndarray, values: np.ndarray, n: int) -> np.ndarray:
    """The least of values in each of n groups, infinite where a group has none."""
    out = np.full(n, np.inf)
    np.minimum.at(out, group, values)
    return out


@dataclass
class Held:
    """Points of a tree in order of their leaves as arrays; those of node i are at start[i] : end[i]."""

    id: np.ndarray
    axes: list[np.ndarray]
    weight: np.ndarray | None
    key: np.ndarray | None
    start: np.ndarray
    end: np.ndarray
    metric: str

    @classmethod
    def of(cls, nodes: Nodes, rows: DataFrame, space: Space, tie: str | None = None) -> Held:
        """rows: leaf, id, coordinates, weight if there is one, and rho if a tie rule is given; key is then the rank of density."""
        return cls.at(nodes, rows.toArrow(), space, tie)

    @classmethod
    def at(cls, nodes: Nodes, t: pa.Table, space: Space, tie: str | None = None) -> Held:
        """The same of rows that are here."""
        place = nodes.at(t.column("leaf").to_numpy())
        order = np.argsort(place, kind="stable")
        col = lambda c: t.column(c).to_numpy()[order]
        edges = np.arange(len(nodes))
        start, end = (np.searchsorted(place[order], edges, side=s) for s in ("left", "right"))
        number, weight, key = col("id"), col("weight") if "weight" in t.column_names else None, None
        if tie == "by_id":
            key = np.empty(len(number), dtype=np.int64)
            key[np.lexsort((-number, col("rho")))] = np.arange(len(number))
        elif tie is not None:
            key = np.unique(col("rho"), return_inverse=True)[1].ravel().astype(np.int64)
        return cls(number, [col(c).astype(np.float64) for c in space.coords], weight, key, start, end, space.metric)

    def among(self, places: np.ndarray) -> np.ndarray:
        """Where the points of leaves are."""
        count = self.end[places] - self.start[places]
        inside = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
        return np.repeat(self.start[places], count) + inside

    def gaps(self, q: np.ndarray, n: np.ndarray) -> np.ndarray:
        """Distances of points q (rows) to points n (columns)."""
        return norm([x[q][:, None] - x[n][None, :] for x in self.axes], self.metric)

    def over_nodes(self, fold: np.ufunc, values: np.ndarray, none: int) -> np.ndarray:
        """values of points folded for each leaf, none elsewhere."""
        out, full = np.full(len(self.start), none, dtype=np.int64), np.flatnonzero(self.end > self.start)
        full = full[np.argsort(self.start[full])]
        if len(full):
            out[full] = fold.reduceat(values, self.start[full])
        return out


def over_leaves(tree: Tree, leaves: np.ndarray, work: Callable[[np.ndarray], dict[str, np.ndarray]], schema: str) -> DataFrame:
    """Rows that work gives for shares of the places of query leaves, spread over the tasks of the cluster.

    work and all arrays it holds are sent to the tasks once each.
    """
    spark = tree.nodes.sparkSession
    sent = spark.sparkContext.broadcast(work)
    tasks = max(1, min(int(spark.conf.get("spark.sql.shuffle.partitions")), -(-len(leaves) // 64)))
    places = spark.createDataFrame(pa.table({"place": pa.array(leaves, pa.int64())})).repartition(tasks)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            own = b.column("place").to_numpy()
            for at in range(0, len(own), AT_ONCE):
                out = sent.value(own[at : at + AT_ONCE])
                yield pa.RecordBatch.from_arrays([pa.array(v) for v in out.values()], names=list(out))

    return places.mapInArrow(run, schema)


class Range:
    """Density: nodes wholly within the cutoff are counted, leaves that cross it come out as pairs."""

    def __init__(self, nodes: Nodes, d_c: float, contain: bool):
        self.nodes, self.d_c, self.contain = nodes, d_c, contain

    def descend(self, places: np.ndarray) -> tuple[np.ndarray, ...]:
        """Weight in whole nodes, nodes seen and whole ones of each of places, and the pairs (index in places, place of a leaf) that are left."""
        t, full = self.nodes, np.zeros(len(places), dtype=np.int64)
        seen = np.zeros(len(places), dtype=np.int64)
        held = np.zeros(len(places), dtype=np.int64)
        at, n = np.arange(len(places)), np.full(len(places), t.root)
        pairs: list[tuple[np.ndarray, np.ndarray]] = []
        while len(at):
            np.add.at(seen, at, 1)
            near = t.least(places[at], n) < self.d_c
            inside = near & (t.most(places[at], n) < self.d_c) if self.contain else np.zeros(len(at), dtype=bool)
            np.add.at(full, at[inside], t.nc[n[inside]])
            np.add.at(held, at[inside], 1)
            open_ = near & ~inside
            pairs.append((at[open_ & t.leaf[n]], n[open_ & t.leaf[n]]))
            go = open_ & ~t.leaf[n]
            at, n, _ = t.children(at[go], n[go])
        q, n = (np.concatenate(x) for x in zip(*pairs, strict=True))
        return full, seen, held, q, n

    def __call__(self, places: np.ndarray) -> dict[str, np.ndarray]:
        t = self.nodes
        full, seen, held, q, n = self.descend(places)
        # a first row for each query leaf carries its counts, further rows its leaf pairs
        none = np.full(len(places), -1, dtype=np.int64)
        return {
            "q_leaf": np.concatenate((t.node[places], t.node[places[q]])),
            "n_leaf": np.concatenate((none, t.node[n])),
            "full": np.concatenate((full, np.zeros(len(q), dtype=np.int64))),
            "node_pairs": np.concatenate((seen, np.zeros(len(q), dtype=np.int64))),
            "contained": np.concatenate((held, np.zeros(len(q), dtype=np.int64))),
        }


RANGE = "q_leaf long, n_leaf long, full long, node_pairs long, contained long"


class Count:
    """Density of the points themselves: the weight within the cutoff, their own included."""

    def __init__(self, nodes: Nodes, held: Held, d_c: float, contain: bool):
        self.range, self.held, self.d_c = Range(nodes, d_c, contain), held, d_c

    def __call__(self, places: np.ndarray) -> dict[str, np.ndarray]:
        h, out = self.held, [np.empty((2, 0), dtype=np.int64)]
        for at in range(0, len(places), LEAVES):
            some = places[at : at + LEAVES]
            full, _, _, q, n = self.range.descend(some)
            order = np.argsort(q, kind="stable")
            edge, n = np.searchsorted(q[order], np.arange(len(some) + 1)), n[order]
            for i, leaf in enumerate(some):
                others = h.among(n[edge[i] : edge[i + 1]])
                for first in range(h.start[leaf], h.end[leaf], BLOCK):
                    own = np.arange(first, min(first + BLOCK, h.end[leaf]))
                    found, step = np.full(len(own), full[i]), max(1, BLOCK // len(own))
                    for b in range(0, len(others), step):
                        near = h.gaps(own, others[b : b + step]) < self.d_c
                        found += np.count_nonzero(near, axis=1) if h.weight is None else (near @ h.weight[others[b : b + step]].astype(np.float64)).astype(np.int64)
                    out.append(np.stack((h.id[own], found)))
        ids, found = np.concatenate(out, axis=1)
        return {"id": ids, "n": found}


COUNT = "id long, n long"


class Tiles:
    """Parts of a tree: the highest nodes of at most so many rows, and the leaves that each needs for density.

    tile is that of each leaf's place; needs are the places of leaves (sorted) and the tiles
    that need them. A node wholly within or beyond the cutoff of a tile's box is so for all
    of its leaves, so none of them opens it.
    """

    def __init__(self, nodes: Nodes, rows: np.ndarray, d_c: float, contain: bool, most: int):
        own, tile = rows.copy(), np.full(len(nodes), -1, dtype=np.int64)
        for level in range(int(nodes.level.max(initial=0)), 0, -1):
            here = np.flatnonzero(nodes.level == level)
            np.add.at(own, nodes.up[here], own[here])
        for level in range(int(nodes.level.max(initial=0)) + 1):
            here = np.flatnonzero(nodes.level == level)
            above = np.where(nodes.up[here] >= 0, tile[nodes.up[here]], -1)
            tile[here] = np.where(above >= 0, above, np.where((own[here] <= most) | nodes.leaf[here], here, -1))
        _, _, _, q, n = Range(nodes, d_c, contain).descend(tops := np.unique(tile[nodes.leaf]))
        leaves = np.flatnonzero(nodes.leaf)
        pairs = np.unique(np.stack((np.concatenate((n, leaves)), np.concatenate((tops[q], tile[leaves])))), axis=1)
        self.tile, self.place, self.needs = tile, pairs[0], pairs[1]


def counted(tree: Tree, points: DataFrame, d_c: float, contain: bool) -> DataFrame:
    """id, n: what Count gives, from tiles whose points and needed neighbours meet in a task each. points: leaf, id, coordinates, weight if there is one."""
    nodes, space, sc = tree.arrays(), tree.space, points.sparkSession.sparkContext
    size = points.groupBy("leaf").count().toArrow()
    rows = np.zeros(len(nodes), dtype=np.int64)
    rows[nodes.at(size.column("leaf").to_numpy())] = size.column("count").to_numpy()
    sent = sc.broadcast((nodes, Tiles(nodes, rows, d_c, contain, TILE)))
    columns = points.columns

    def dealt(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        nodes, tiles = sent.value
        for b in batches:
            place = nodes.at(b.column("leaf").to_numpy())
            first, end = (np.searchsorted(tiles.place, place, side=s) for s in ("left", "right"))
            came = np.repeat(np.arange(len(place)), end - first)
            inside = np.arange(len(came)) - np.repeat(np.cumsum(end - first) - (end - first), end - first)
            tile = pa.array(tiles.needs[first[came] + inside])
            for at in range(0, len(came), 1 << 16):
                some = b.take(pa.array(came[at : at + (1 << 16)]))
                yield pa.RecordBatch.from_arrays([tile[at : at + (1 << 16)], *some.columns], names=["tile", *columns])

    def count(key: tuple, t: pa.Table) -> pa.Table:
        nodes, tiles = sent.value
        held = Held.at(nodes, t, space)
        own = np.unique(nodes.at(t.column("leaf").to_numpy()))
        found = Count(nodes, held, d_c, contain)(own[tiles.tile[own] == key[0].as_py()])
        return pa.table({c: pa.array(v, pa.int64()) for c, v in found.items()})

    kinds = ", ".join(f"{c} {k}" for c, k in points.dtypes)
    return points.mapInArrow(dealt, f"tile long, {kinds}").groupBy("tile").applyInArrow(count, COUNT)


class Denser:
    """Dependent distance: leaves that may hold the nearest denser point of a query leaf's points.

    minkey and topkey are the least and greatest density ranks of a leaf's points that are
    asked for, maxkey the greatest rank below each node, bound a distance that none of the
    leaf's points needs to exceed. A node that holds a rank above topkey bounds all points.
    """

    def __init__(self, nodes: Nodes, minkey: np.ndarray, topkey: np.ndarray, maxkey: np.ndarray, bound: np.ndarray, density_prune: bool, distance_prune: bool):
        self.nodes, self.minkey, self.topkey, self.maxkey, self.bound = nodes, minkey, topkey, maxkey, bound
        self.density_prune, self.distance_prune = density_prune, distance_prune

    def descend(self, places: np.ndarray) -> tuple[np.ndarray, ...]:
        """Nodes seen and the bound of each of places, and the pairs (index in places, place of a leaf) that are left, with their least distances."""
        t = self.nodes
        seen, limit = np.zeros(len(places), dtype=np.int64), self.bound[places].copy()
        at, n = np.arange(len(places)), np.full(len(places), t.root)
        kept: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        while len(at):
            if self.density_prune:
                dense = self.maxkey[n] > self.minkey[places[at]]
                at, n = at[dense], n[dense]
            np.add.at(seen, at, 1)
            least = t.least(places[at], n)
            if self.distance_prune:
                sure = self.maxkey[n] > self.topkey[places[at]]
                np.minimum.at(limit, at[sure], t.most(places[at[sure]], n[sure]))
                close = least <= limit[at]
                at, n, least = at[close], n[close], least[close]
            leaf = t.leaf[n]
            kept.append((at[leaf], n[leaf], least[leaf]))
            at, n, _ = t.children(at[~leaf], n[~leaf])
        q, n, least = (np.concatenate(x) for x in zip(*kept, strict=True))
        if self.distance_prune:  # bounds have fallen since the upper leaves were kept
            close = least <= limit[q]
            q, n, least = q[close], n[close], least[close]
        return seen, limit, q, n, least

    def __call__(self, places: np.ndarray) -> dict[str, np.ndarray]:
        t = self.nodes
        seen, limit, q, n, _ = self.descend(places)
        none = np.full(len(places), -1, dtype=np.int64)
        zero, own = np.zeros(len(q), dtype=np.int64), np.concatenate((np.arange(len(places)), q))
        return {
            "q_leaf": t.node[places[own]],
            "n_leaf": np.concatenate((none, t.node[n])),
            "last": limit[own],
            "node_pairs": np.concatenate((seen, zero)),
        }


DENSER = "q_leaf long, n_leaf long, last double, node_pairs long"


class Parents:
    """Dependent distance of the points themselves: the nearest denser point, the smaller id among equally near ones.

    Points of the greatest key have none. A leaf meets others from near to far, each for
    those of its points that a nearer one than the leaf is not known of.
    """

    def __init__(self, nodes: Nodes, held: Held, density_prune: bool, distance_prune: bool):
        self.nodes, self.held, self.density_prune, self.distance_prune = nodes, held, density_prune, distance_prune
        self.peak = held.key.max(initial=0)
        low = held.over_nodes(np.minimum, held.key, np.iinfo(np.int64).max)
        high = held.over_nodes(np.maximum, held.key, -1)
        asked = held.over_nodes(np.maximum, np.where(held.key < self.peak, held.key, -1), -1)
        self.low, self.asked, self.maxkey = low, asked, nodes.rolled(high)

    def nearer(self, own: np.ndarray, others: np.ndarray, best: np.ndarray, mu: np.ndarray, rows: np.ndarray) -> None:
        """Lowers best and mu of own[rows] by what others hold."""
        h = self.held
        step = max(1, BLOCK // max(1, len(rows)))
        for b in range(0, len(others), step):
            n, q = others[b : b + step], own[rows]
            gap = np.where(h.key[n][None, :] > h.key[q][:, None], h.gaps(q, n), np.inf)
            least = gap.min(axis=1)
            ids = np.where(gap == least[:, None], h.id[n][None, :], np.iinfo(np.int64).max).min(axis=1)
            better = (least < best[rows]) | ((least == best[rows]) & (ids < mu[rows]) & np.isfinite(least))
            best[rows[better]], mu[rows[better]] = least[better], ids[better]

    def __call__(self, places: np.ndarray) -> dict[str, np.ndarray]:
        t, h = self.nodes, self.held
        out: list[tuple[np.ndarray, ...]] = [(np.empty(0, dtype=np.int64), np.empty(0), np.empty(0, dtype=np.int64))]
        for begin in range(0, len(places), LEAVES):
            some = places[begin : begin + LEAVES]
            some = some[self.asked[some] >= 0]
            state, bound = [], np.full(len(t), np.inf)
            for leaf in some:
                own = np.arange(h.start[leaf], h.end[leaf])
                own = own[h.key[own] < self.peak]
                best, mu = np.full(len(own), np.inf), np.full(len(own), np.iinfo(np.int64).max)
                for b in range(0, len(own), BLOCK):
                    self.nearer(own, np.arange(h.start[leaf], h.end[leaf]), best, mu, np.arange(b, min(b + BLOCK, len(own))))
                bound[leaf] = best.max(initial=0.0)
                state.append((own, best, mu))
            if not len(some):
                continue
            q, n, least = Denser(t, self.low, self.asked, self.maxkey, bound, self.density_prune, self.distance_prune).descend(some)[2:]
            order = np.lexsort((least, q))
            edge, n, least = np.searchsorted(q[order], np.arange(len(some) + 1)), n[order], least[order]
            for i, (own, best, mu) in enumerate(state):
                at, step = edge[i], 8
                while at < edge[i + 1]:
                    rows = np.flatnonzero(best >= least[at]) if self.distance_prune else np.arange(len(own))
                    if not len(rows):
                        break
                    to = min(at + step, edge[i + 1])
                    others = h.among(n[at:to][n[at:to] != some[i]])
                    for b in range(0, len(rows), BLOCK):
                        self.nearer(own, others, best, mu, rows[b : b + BLOCK])
                    at, step = to, step * 2
                out.append((h.id[own], best, mu))
        ids, best, mu = (np.concatenate(x) for x in zip(*out, strict=True))
        return {"id": ids, "delta": best, "mu": mu}


PARENTS = "id long, delta double, mu long"


class Local:
    """Dependent distance by descent for one point at a time, with the numbers of nodes visited and of denser points measured; mu is -1 where there is none."""

    def __init__(self, nodes: Nodes, held: Held, order: str):
        self.nodes, self.held, self.order = nodes, held, order
        self.maxkey = nodes.rolled(held.over_nodes(np.maximum, held.key, -1))
        self.boxes: list | None = None

    def unpacked(self) -> None:
        """Boxes, keys and children as lists, which are faster to read one by one."""
        t = self.nodes
        self.boxes = list(zip(*[list(zip(a.tolist(), b.tolist(), strict=True)) for a, b in zip(t.lo, t.hi, strict=True)], strict=True))
        self.keys, self.is_leaf = self.maxkey.tolist(), t.leaf.tolist()
        first, order = t.first.tolist(), t.order.tolist()
        self.below = [order[first[i] : first[i + 1]] for i in range(len(t))]

    def least(self, p: tuple[float, ...], i: int) -> float:
        total = 0.0
        for x, (lo, hi) in zip(p, self.boxes[i], strict=True):
            gap = lo - x if x < lo else x - hi if x > hi else 0.0
            total += gap * gap
        return math.sqrt(total)

    def one(self, p: tuple[float, ...], mine: int) -> tuple[float, int, int, int]:
        h, keys, heap = self.held, self.keys, self.order == "heap"
        best, mu, visited, measured = math.inf, -1, 0, 0
        root = self.nodes.root
        todo = [(self.least(p, root), root)]
        while todo:
            d, i = heapq.heappop(todo) if heap else todo.pop()
            if d > best or keys[i] <= mine:
                continue
            visited += 1
            if self.is_leaf[i]:
                at = slice(h.start[i], h.end[i])
                up = h.key[at] > mine
                gap = norm([x - a[at][up] for x, a in zip(p, h.axes, strict=True)], h.metric)
                measured += len(gap)
                near = float(gap.min())
                who = int(h.id[at][up][gap == near].min())
                if (near, who) < (best, mu):
                    best, mu = near, who
                continue
            for x in sorted(((self.least(p, c), c) for c in self.below[i] if keys[c] > mine), reverse=True):
                if x[0] <= best:
                    heapq.heappush(todo, x) if heap else todo.append(x)
        return best, mu, visited, measured

    def __call__(self, places: np.ndarray) -> dict[str, np.ndarray]:
        if self.boxes is None:
            self.unpacked()
        h = self.held
        at = h.among(places)
        rows = [self.one(p, k) for *p, k in zip(*[x[at].tolist() for x in h.axes], h.key[at].tolist(), strict=True)]
        columns = list(zip(*rows, strict=True)) or [()] * 4
        kinds = {"delta": np.float64, "mu": np.int64, "visited": np.int64, "distances": np.int64}
        return {"id": h.id[at], **{c: np.array(v, dtype=k) for (c, k), v in zip(kinds.items(), columns, strict=True)}}


LOCAL = "id long, delta double, mu long, visited long, distances long"


class Farthest:
    """Leaves that may hold the farthest point of any point of a query leaf."""

    def __init__(self, nodes: Nodes):
        self.nodes = nodes

    def __call__(self, places: np.ndarray) -> dict[str, np.ndarray]:
        t, reach = self.nodes, np.zeros(len(places))
        at, n = np.arange(len(places)), np.full(len(places), t.root)
        kept: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []
        while len(at):
            most = t.most(places[at], n)
            np.maximum.at(reach, at, t.least(places[at], n))
            far = most >= reach[at]
            at, n, most = at[far], n[far], most[far]
            leaf = t.leaf[n]
            kept.append((at[leaf], n[leaf], most[leaf]))
            at, n, _ = t.children(at[~leaf], n[~leaf])
        q, n, most = (np.concatenate(x) for x in zip(*kept, strict=True))
        far = most >= reach[q]
        return {"q_leaf": t.node[places[q[far]]], "n_leaf": t.node[n[far]]}


class Nearest:
    """Leaves that may hold one of the k nearest others of any point of a query leaf."""

    def __init__(self, nodes: Nodes, k: int):
        self.nodes, self.k = nodes, k

    def __call__(self, places: np.ndarray) -> dict[str, np.ndarray]:
        t, limit = self.nodes, np.full(len(places), np.inf)
        at, n = np.arange(len(places)), np.full(len(places), t.root)
        kept_q, kept_n = np.empty(0, dtype=np.int64), np.empty(0, dtype=np.int64)
        while len(at):
            # nodes that together surely hold more than k points within a distance; leaves met before count too
            every_q, every_n = np.concatenate((kept_q, at)), np.concatenate((kept_n, n))
            most = t.most(places[every_q], every_n)
            order = np.lexsort((most, every_q))
            held = np.cumsum(t.nc[every_n[order]])
            start = np.searchsorted(every_q[order], every_q[order], side="left")
            held = held - np.where(start > 0, held[start - 1], 0)
            enough = held > self.k
            limit = np.minimum(limit, least_by(every_q[order][enough], most[order][enough], len(places)))
            near = t.least(places[at], n) <= limit[at]
            at, n = at[near], n[near]
            leaf = t.leaf[n]
            kept_q, kept_n = np.concatenate((kept_q, at[leaf])), np.concatenate((kept_n, n[leaf]))
            at, n, _ = t.children(at[~leaf], n[~leaf])
        near = t.least(places[kept_q], kept_n) <= limit[kept_q]
        return {"q_leaf": t.node[places[kept_q[near]]], "n_leaf": t.node[kept_n[near]]}


PAIRS = "q_leaf long, n_leaf long"
