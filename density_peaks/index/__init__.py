"""Indices over points: neighbour lists, histograms over them, quadtree and packed R-tree."""
