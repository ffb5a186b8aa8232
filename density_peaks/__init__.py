"""Density-peak clustering on Spark: index a set of points once, ask for any cutoff."""
