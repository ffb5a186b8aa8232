"""Which index suits a set of points."""

from __future__ import annotations

from dataclasses import dataclass


@dataclass(frozen=True)
class Advice:
    index: str
    why: str


def choose(n: int, mean_neighbours: float, memory_bytes: float, exact: bool = True, entry_bytes: int = 16) -> Advice:
    """Full lists with histograms where they fit; cut lists where approximate answers do and they fit; else the packed R-tree.

    n: points; mean_neighbours: list entries a point within the radius of cut lists.
    """
    if n * n * entry_bytes <= memory_bytes:
        return Advice("ch", "full lists fit, and histograms over them answer fastest")
    if not exact and n * mean_neighbours * entry_bytes <= memory_bytes:
        return Advice("rn_ch", "cut lists fit, and answers may be approximate beyond their radius")
    return Advice("rtree", "lists do not fit; the packed tree needs space linear in points and stays exact")
