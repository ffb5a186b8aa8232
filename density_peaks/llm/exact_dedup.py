"""Exact dedup against immutable snapshots that keep static binary-fuse filters.

A snapshot is saved once: its digests are dealt into shards, each shard keeps one static
filter of about nine bits a key, and the digests that it holds more than once are noted.
Digests of any later batch are dealt the same way and screened there: only the positives,
and the digests that a batch itself repeats, are joined with the documents, whose whole
normalised texts then meet in exact buckets. No filter is broadcast and no digest set is
collected; the filters are a table that grows with the snapshot and is joined by shard.
"""

from __future__ import annotations

import math
import uuid
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from density_peaks.llm.common import cut, finished, lowered, mix64, shared_dir

#: Keys that one filter shard is sized for.
SHARD_KEYS = 500_000


class FuseFilter:
    """Binary fuse filter of three-way hashing and one-byte fingerprints; no key is ever missed."""

    def __init__(self, seed: int, segment: int, segments: int, table: np.ndarray):
        self.seed, self.segment, self.segments, self.table = seed, segment, segments, table

    @staticmethod
    def _places(keys: np.ndarray, seed: int, segment: int, segments: int) -> tuple[np.ndarray, np.ndarray]:
        h = mix64(keys, seed)
        block = ((h >> np.uint64(32)) * np.uint64(segments) >> np.uint64(32)).astype(np.int64)
        mask = np.uint64(segment - 1)
        g = mix64(h, 7)
        inside = [(g >> np.uint64(s) & mask).astype(np.int64) for s in (0, 20, 40)]
        places = np.stack([(block + i) * segment + x for i, x in enumerate(inside)], axis=1)
        return places, (h & np.uint64(255)).astype(np.uint8)

    @classmethod
    def build(cls, keys: np.ndarray) -> FuseFilter:
        """keys: distinct uint64, any number of them."""
        n = max(2, len(keys))
        segment = 1 << min(18, max(2, int(math.log(n) / math.log(3.33) + 2.25)))
        slots = n * max(1.125, 0.875 + 0.25 * math.log(1e6) / math.log(n)) if n < 1_000_000 else n * 1.125
        segments = max(1, math.ceil(slots / segment) - 2)
        for seed in range(1, 200):
            if seed % 20 == 0:  # tiny or unlucky sets get more room
                segments += 1 + segments // 8
            places, prints = cls._places(keys, seed, segment, segments)
            table = cls._peel(places, prints, (segments + 2) * segment)
            if table is not None:
                return cls(seed, segment, segments, table)
        raise ValueError("the keys of a filter must be distinct")

    @staticmethod
    def _peel(places: np.ndarray, prints: np.ndarray, slots: int) -> np.ndarray | None:
        n = len(places)
        count = np.bincount(places.ravel(), minlength=slots)
        held = np.zeros(slots, dtype=np.int64)
        np.bitwise_xor.at(held, places.ravel(), np.repeat(np.arange(n), 3))
        free, rounds, done = np.flatnonzero(count == 1), [], 0
        while len(free):
            key, at = np.unique(held[free], return_index=True)
            rounds.append((key, free[at]))
            done += len(key)
            touched = places[key].ravel()
            np.subtract.at(count, touched, 1)
            np.bitwise_xor.at(held, touched, np.repeat(key, 3))
            free = np.unique(touched)
            free = free[count[free] == 1]
        if done < n:
            return None
        table = np.zeros(slots, dtype=np.uint8)
        for key, slot in reversed(rounds):
            three = table[places[key]]
            table[slot] = prints[key] ^ three[:, 0] ^ three[:, 1] ^ three[:, 2]
        return table

    def contains(self, keys: np.ndarray) -> np.ndarray:
        if not len(keys):
            return np.zeros(0, dtype=bool)
        places, prints = self._places(keys, self.seed, self.segment, self.segments)
        three = self.table[places]
        return prints == three[:, 0] ^ three[:, 1] ^ three[:, 2]


def digests(docs: DataFrame) -> DataFrame:
    """doc_id, digest (64 bits, for filters and buckets), text_sha256 of the normalised text."""
    text = lowered(F.col("text"))
    return docs.select("doc_id", text.alias("norm")).select("doc_id", F.xxhash64("norm").alias("digest"), F.sha2("norm", 256).alias("text_sha256"))


def build_filters(snapshot: DataFrame, shards: int) -> DataFrame:
    """One static filter for each shard of a snapshot's digests: shard, seed, segment, segments, table."""

    def build(pdf: pd.DataFrame) -> pd.DataFrame:
        f = FuseFilter.build(pdf["digest"].to_numpy().astype(np.int64).view(np.uint64))
        return pd.DataFrame({"shard": [pdf["shard"].iloc[0]], "seed": [f.seed], "segment": [f.segment], "segments": [f.segments], "table": [f.table.tobytes()]})

    keys = snapshot.select("digest").distinct().withColumn("shard", F.pmod("digest", F.lit(shards)).cast("int"))
    return keys.groupBy("shard").applyInPandas(build, "shard int, seed int, segment int, segments int, table binary")


def screen(incoming: DataFrame, filters: DataFrame, shards: int) -> DataFrame:
    """The distinct digests of a batch that a snapshot's filters do not rule out."""

    def probe(keys: pd.DataFrame, one: pd.DataFrame) -> pd.DataFrame:
        if keys.empty or one.empty:
            return pd.DataFrame({"digest": pd.Series(dtype="int64")})
        f = one.iloc[0]
        values = keys["digest"].to_numpy().astype(np.int64)
        found = FuseFilter(int(f.seed), int(f.segment), int(f.segments), np.frombuffer(f.table, dtype=np.uint8)).contains(values.view(np.uint64))
        return pd.DataFrame({"digest": values[found]})

    keys = incoming.select("digest").distinct().withColumn("shard", F.pmod("digest", F.lit(shards)).cast("int"))
    return keys.groupBy("shard").cogroup(filters.groupBy("shard")).applyInPandas(probe, "digest long")


def repeated(batch: DataFrame) -> DataFrame:
    """Digests that one batch holds more than once."""
    return batch.groupBy("digest").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("digest")


def classes(docs: DataFrame, suspects: DataFrame) -> DataFrame:
    """Exact buckets: the documents under suspect digests grouped by their whole normalised bytes."""
    text = lowered(F.col("text"))
    held = docs.select("doc_id", text.alias("norm")).withColumn("digest", F.xxhash64("norm")).join(suspects, "digest", "left_semi")
    groups = held.groupBy("digest", "norm").agg(F.max("doc_id").alias("keep_id"), F.count(F.lit(1)).alias("group_size"))
    return groups.select("digest", F.sha2("norm", 256).alias("text_sha256"), "keep_id", "group_size")


@dataclass
class Snapshot:
    """An immutable table with what was saved of it: digests, filters by shard, and repeats."""

    docs: DataFrame
    digests: DataFrame
    filters: DataFrame
    repeats: DataFrame
    shards: int


def save_snapshot(docs: DataFrame, path: str) -> Snapshot:
    """Saves digests, filters and repeated digests of docs below path, once for all batches to come."""
    digests(docs).write.parquet(f"{path}/digests")
    held = docs.sparkSession.read.parquet(f"{path}/digests")
    shards = max(8, math.ceil(held.count() / SHARD_KEYS))
    build_filters(held, shards).write.parquet(f"{path}/filters")
    repeated(held).write.parquet(f"{path}/repeats")
    docs.sparkSession.createDataFrame([(shards,)], "shards int").coalesce(1).write.parquet(f"{path}/meta")
    return load_snapshot(docs, path)


def load_snapshot(docs: DataFrame, path: str) -> Snapshot:
    """A saved snapshot of docs. Raises ValueError where path holds none that was saved to its end."""
    spark = docs.sparkSession
    if not finished(spark, f"{path}/meta"):
        raise ValueError(f"no snapshot at {path}")
    part = lambda name: spark.read.parquet(f"{path}/{name}")
    return Snapshot(docs, part("digests"), part("filters"), part("repeats"), part("meta").first()["shards"])


def exact_dedup(snapshot: Snapshot, incoming: DataFrame) -> DataFrame:
    """Marks the equal texts among a snapshot and a new batch, with the snapshot's filters as saved.

    The tables of both need doc_id and text; other columns are ignored. Texts are equal when
    they are identical after lower-casing A-Z; null counts as empty. Returns one row for
    each row of both: doc_id, keep_id (largest doc_id of the equal texts), group_size, kept,
    text_sha256. Rows repeated whole count singly in group_size and are all kept if their
    doc_id is the largest; a null doc_id is kept only where all of its group are null.
    Empty inputs give no rows.
    """
    new = cut(digests(incoming))
    positives = screen(new, snapshot.filters, snapshot.shards)
    suspects = cut(positives.unionByName(repeated(new)).unionByName(snapshot.repeats).distinct())
    docs = snapshot.docs.select("doc_id", "text").unionByName(incoming.select("doc_id", "text"))
    found = snapshot.digests.unionByName(new).join(classes(docs, suspects), ["digest", "text_sha256"], "left")
    keep = F.when(F.col("group_size").isNull(), F.col("doc_id")).otherwise(F.col("keep_id"))
    return found.select(
        "doc_id",
        keep.alias("keep_id"),
        F.coalesce("group_size", F.lit(1)).cast("long").alias("group_size"),
        F.col("doc_id").eqNullSafe(keep).alias("kept"),
        "text_sha256",
    )


def dedup(docs: DataFrame, path: str | None = None) -> DataFrame:
    """exact_dedup over one table: by a hash of the id, half of it is the snapshot, saved below path, and half the new batch."""
    path = path or f"{shared_dir(docs.sparkSession).rstrip('/')}/snapshot-{uuid.uuid4().hex}"
    fresh = F.pmod(F.xxhash64("doc_id"), F.lit(2)) == 1
    return exact_dedup(save_snapshot(docs.where(~fresh), path), docs.where(fresh))


SQL = """
WITH d AS (
  SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS norm FROM documents
), g AS (
  SELECT norm, max(doc_id) AS keep_id, count(*) AS group_size FROM d GROUP BY norm
)
SELECT d.doc_id, g.keep_id, g.group_size, d.doc_id = g.keep_id AS kept, sha256(d.norm) AS text_sha256
FROM d JOIN g ON d.norm = g.norm
"""
