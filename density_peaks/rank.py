"""Ranks over all rows without sorting them in one task."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from density_peaks.iterate import cut, parked, released


def global_rank(df: DataFrame, order: list[Column], name: str = "rank", partitions: int | None = None, keep: list[str] | None = None) -> DataFrame:
    """df with its 0-based rank in the given order: range partitions, sorted inside, shifted by the counts before.

    keep names the columns that go on behind the sort, all by default; a table cut down to
    few columns is a long one, and is held as Parquet.
    """
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    inside = df.repartitionByRange(n, *order).sortWithinPartitions(*order)
    inside = inside if keep is None else inside.select(*keep)
    hold = cut if keep is None else parked
    inside = hold(inside.withColumn("rank_part", F.spark_partition_id()).withColumn("rank_row", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1))))
    if keep is not None:
        released(df.sparkSession)
    before = Window.orderBy("rank_part").rowsBetween(Window.unboundedPreceding, -1)  # one row a partition
    shift = inside.groupBy("rank_part").count().withColumn("rank_shift", F.coalesce(F.sum("count").over(before), F.lit(0))).drop("count")
    return inside.join(F.broadcast(shift), "rank_part").withColumn(name, F.col("rank_row") + F.col("rank_shift")).drop("rank_part", "rank_row", "rank_shift")
