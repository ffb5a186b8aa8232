"""Decision graph and the choice of centers and outliers."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def decision_graph(dep: DataFrame) -> DataFrame:
    """id, rho, delta and gamma = rho * delta, by which points can be ordered as centers."""
    return dep.select("id", "rho", "delta", (F.col("rho") * F.col("delta")).alias("gamma"))


def centers(dep: DataFrame, rho_min: float, delta_min: float) -> DataFrame:
    """Points of at least both thresholds."""
    return dep.where((F.col("rho") >= rho_min) & (F.col("delta") >= delta_min)).select("id")


def centers_by_id(dep: DataFrame, ids: Sequence[int]) -> DataFrame:
    """Points picked by a person from the graph."""
    return dep.where(F.col("id").isin(list(ids))).select("id")


def centers_top(dep: DataFrame, k: int) -> DataFrame:
    """The k points of greatest gamma, the smaller id first among equals."""
    return decision_graph(dep).orderBy(F.desc("gamma"), "id").limit(k).select("id")


def thresholds_of_top(dep: DataFrame, k: int) -> tuple[float, float]:
    """The least rho and the least delta among the k points of greatest gamma."""
    top = decision_graph(dep).orderBy(F.desc("gamma"), "id").limit(k).agg(F.min("rho"), F.min("delta")).first()
    return float(top[0] or 0), float(top[1] or 0.0)


def outliers(dep: DataFrame, rho_max: float, delta_min: float) -> DataFrame:
    """Points of low density far from any denser one."""
    return dep.where((F.col("rho") <= rho_max) & (F.col("delta") >= delta_min)).select("id", "rho", "delta")
