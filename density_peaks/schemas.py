"""Schemas of the tables that pass between steps, and the checks at the boundary."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

RHO = T.StructType([T.StructField("id", T.LongType()), T.StructField("rho", T.LongType())])
DEPENDENT = T.StructType(
    [
        T.StructField("id", T.LongType()),
        T.StructField("rho", T.LongType()),
        T.StructField("delta", T.DoubleType()),
        T.StructField("mu", T.LongType()),
        T.StructField("is_top", T.BooleanType()),
        T.StructField("is_capped", T.BooleanType()),
    ]
)
PACKED = T.StructType([T.StructField("id", T.LongType()), T.StructField("nbrs", T.ArrayType(T.LongType())), T.StructField("dists", T.ArrayType(T.DoubleType()))])
LONG = T.StructType([T.StructField("id", T.LongType()), T.StructField("pos", T.IntegerType()), T.StructField("nbr", T.LongType()), T.StructField("dist", T.DoubleType())])
HIST = T.StructType([T.StructField("id", T.LongType()), T.StructField("bin", T.LongType()), T.StructField("cum", T.LongType()), T.StructField("min_dist", T.DoubleType()), T.StructField("max_dist", T.DoubleType())])
LABELS = T.StructType([T.StructField("id", T.LongType()), T.StructField("cluster", T.LongType()), T.StructField("depth", T.IntegerType()), T.StructField("is_center", T.BooleanType())])


@dataclass(frozen=True)
class Space:
    """Coordinate columns of a point table and the metric over them.

    One column of array type is a vector; several columns are the axes of a plane or box.
    """

    coords: tuple[str, ...] = ("x", "y")
    metric: str = "euclidean"
    vector: bool = False

    def of(self, prefix: str = "") -> list[Column]:
        return [F.col(f"{prefix}{c}") for c in self.coords]


PLANE = Space()
VECTOR = Space(("vec",), "euclidean", True)


class InvalidPoints(ValueError):
    """Points with a null or NaN id or coordinate."""


def points(df: DataFrame, space: Space = PLANE, check: bool = False, keep: str | None = None) -> DataFrame:
    """id and coordinates as LONG and DOUBLE; with check, null or NaN values raise InvalidPoints that names the column. keep names one more column."""
    kind = "array<double>" if space.vector else "double"
    out = df.select(F.col("id").cast("long").alias("id"), *[F.col(c).cast(kind).alias(c) for c in space.coords], *([keep] if keep else []))
    if check:
        reject_bad(out, space.coords if not space.vector else ())
    return out


def reject_bad(df: DataFrame, coords: Sequence[str]) -> None:
    bad = df.agg(F.count_if(F.col("id").isNull()).alias("id"), *[F.count_if(F.col(c).isNull() | F.isnan(c)).alias(c) for c in coords]).first()
    for name, n in bad.asDict().items():
        if n:
            raise InvalidPoints(f"{n} rows have no usable value in column {name}")
