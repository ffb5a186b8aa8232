"""From points to clusters by any index, for one cutoff or for many."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass

from pyspark.sql import DataFrame

from density_peaks import assign, decide, exact, spots
from density_peaks.index import chist, nlist, quadtree, rnlist, rtree, tree_query
from density_peaks.index.tree import Tree
from density_peaks.iterate import cut
from density_peaks.schemas import PLANE, Space, points

INDICES = ("brute", "list", "ch", "rn", "rn_ch", "quadtree", "rtree")


@dataclass
class Index:
    """A built index that answers rho for any cutoff and the dependent table for any rho."""

    kind: str
    rho: Callable[[float], DataFrame]
    delta: Callable[[DataFrame, str], DataFrame]
    parts: dict


def build(pts: DataFrame, kind: str = "rtree", space: Space = PLANE, w: float | None = None, tau: float | None = None, capacity: int = 32) -> Index:
    """Builds an index of a kind. ch and rn_ch need a width w (suggested if none); rn and rn_ch a radius tau."""
    p = cut(points(pts, space))
    if kind == "brute":
        pairs = exact.PairMatrix(p, space).pairs
        return Index(kind, lambda d: exact.rho(p, d, space, pair_table=pairs), lambda r, tie: exact.delta(p, r, space, tie, pairs), {"pairs": pairs})
    if kind in ("list", "ch"):
        lists = cut(nlist.build(p, space))
        if kind == "list":
            return Index(kind, lambda d: nlist.rho(lists, d), lambda r, tie: nlist.delta(lists, r, tie), {"lists": lists})
        width = w or chist.suggest_w(lists)
        hist = cut(chist.packed(lists, width))
        return Index(kind, lambda d: chist.rho_packed(hist, d, width), lambda r, tie: nlist.delta(lists, r, tie), {"lists": lists, "hist": hist, "w": width})
    if kind in ("rn", "rn_ch"):
        if tau is None:
            raise ValueError(f"{kind} needs a radius tau")
        lists, cap = cut(rnlist.build(p, tau, space)), rnlist.diagonal(p, space)
        if kind == "rn":
            return Index(kind, lambda d: rnlist.rho(lists, d, tau).drop("is_exact"), lambda r, tie: rnlist.delta(lists, r, cap, tie), {"lists": lists, "cap": cap})
        width = w or chist.suggest_w(lists)
        hist = cut(chist.packed(lists, width))
        return Index(kind, lambda d: chist.rho_packed(hist, d, width), lambda r, tie: rnlist.delta(lists, r, cap, tie), {"lists": lists, "hist": hist, "w": width, "cap": cap})
    if kind in ("quadtree", "rtree"):
        same, nowhere = spots.placed(spots.merge(p, space))
        tree = over_spots(same, kind, capacity)
        density = lambda d: same.rho(tree_query.rho(tree, d))
        parents = lambda r, tie: same.dependent(tree_query.delta(tree, cut(same.of_spots(r)), tie), tie)
        if nowhere is None:
            return Index(kind, density, parents, {"tree": tree})
        return Index(kind, lambda d: nowhere.rho(density(d)), lambda r, tie: nowhere.dependent(parents(r, tie), r, tie), {"tree": tree})
    raise ValueError(f"index is one of {INDICES}")


def over_spots(same: spots.Merged, kind: str = "rtree", capacity: int = 32) -> Tree:
    """A weighted tree of spots."""
    if kind == "quadtree":
        return quadtree.build(same.spots, capacity, weight=spots.WEIGHT)
    return rtree.build(same.spots, capacity, space=same.space, weight=spots.WEIGHT)


def tree_rho(pts: DataFrame, d_c: float, kind: str = "rtree", capacity: int = 32, space: Space = PLANE, contain: bool = True) -> DataFrame:
    """id, rho for one cutoff by a tree over spots."""
    same = spots.merge(pts, space)
    return same.rho(tree_query.rho(over_spots(same, kind, capacity), d_c, contain=contain))


def dependent(index: Index, d_c: float, tie: str = "strict") -> DataFrame:
    """The dependent table for one cutoff."""
    return cut(index.delta(cut(index.rho(d_c)), tie))


def label(dep: DataFrame, rho_min: float | None = None, delta_min: float | None = None, k: int | None = None, ids: Sequence[int] | None = None) -> DataFrame:
    """Clusters from the dependent table, with centers by thresholds, by number, or by hand."""
    if ids is not None:
        chosen = decide.centers_by_id(dep, ids)
    elif k is not None:
        chosen = decide.centers_top(dep, k)
    else:
        chosen = decide.centers(dep, rho_min or 0, delta_min or 0.0)
    return assign.assign(dep, chosen)


def cluster(pts: DataFrame, d_c: float, index: str = "rtree", space: Space = PLANE, tie: str = "strict", rho_min: float | None = None, delta_min: float | None = None, k: int | None = None, ids: Sequence[int] | None = None, **how) -> DataFrame:
    """Index, density, dependent distance, centers and assignment in one call: id, cluster, depth, is_center."""
    return label(dependent(build(pts, index, space, **how), d_c, tie), rho_min, delta_min, k, ids)


def sweep(index: Index, d_cs: Sequence[float], tie: str = "strict") -> dict[float, DataFrame]:
    """The dependent table of each cutoff over one index."""
    return {d: dependent(index, d, tie) for d in d_cs}
