"""Helpers that the training-data operators share."""

from __future__ import annotations

import os
import tempfile

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Words are maximal runs of bytes other than these: space and tab to carriage return.
WORD = r"[^\x20\x09-\x0D]+"
UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"

_IS_SPACE = np.zeros(256, dtype=bool)
_IS_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True
_POWERS = np.cumprod(np.full(64, 0x9E3779B97F4A7C15 | 1, dtype=np.uint64))
_OTHER_POWERS = np.cumprod(np.full(64, 0xC2B2AE3D27D4EB4F, dtype=np.uint64))


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share.

    Where none is set, a local master takes a temporary folder, as all of it runs on one
    machine; a cluster raises RuntimeError, as executors would not see such a folder.
    """
    sc = spark.sparkContext
    set_dir = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if set_dir is None and not sc.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
    return set_dir or os.path.join(tempfile.gettempdir(), "density_peaks_checkpoints")


def remove(spark: SparkSession, path: str) -> None:
    """Deletes a folder of the shared store, if it is there."""
    folder = spark._jvm.org.apache.hadoop.fs.Path(path)
    folder.getFileSystem(spark._jsc.hadoopConfiguration()).delete(folder, True)


def finished(spark: SparkSession, path: str) -> bool:
    """Whether a write to path has ended."""
    mark = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/_SUCCESS")
    return mark.getFileSystem(spark._jsc.hadoopConfiguration()).exists(mark)


def cut(df: DataFrame) -> DataFrame:
    """Writes df to the shared checkpoint folder and reads it back, so that no lineage is left."""
    sc = df.sparkSession.sparkContext
    if sc.getCheckpointDir() is None:
        sc.setCheckpointDir(shared_dir(df.sparkSession))
    return df.checkpoint(eager=True)


def width(spark: SparkSession) -> int:
    """Shuffle partitions of the session."""
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def whole(text: Column) -> Column:
    """A text, empty where it is null."""
    return F.coalesce(text.cast("string"), F.lit(""))


def lowered(text: Column) -> Column:
    """A text with A-Z lower-cased and nothing else changed."""
    return F.translate(whole(text), UPPER, UPPER.lower())


def word_count(text: Column) -> Column:
    """Words of a text, in the JVM."""
    return F.regexp_count(whole(text), F.lit(WORD)).cast("long")


def mix64(x: np.ndarray, seed: int = 0) -> np.ndarray:
    """A bijective finaliser over 64-bit integers; another seed gives another order."""
    with np.errstate(over="ignore"):
        x = x.astype(np.uint64) + np.uint64((seed * 0x9E3779B97F4A7C15 + 0x632BE59BD9B4E019) & 0xFFFFFFFFFFFFFFFF)
        x ^= x >> np.uint64(30)
        x *= np.uint64(0xBF58476D1CE4E5B9)
        x ^= x >> np.uint64(27)
        x *= np.uint64(0x94D049BB133111EB)
        x ^= x >> np.uint64(31)
    return x


class Words:
    """The words of many texts at once: byte ranges, a 64-bit hash each, and the words of each text.

    texts are bytes. start[i] and end[i] are the byte range of word i in data; first[d]
    and first[d + 1] are the range of words of text d. check, if asked for, is a second
    hash that tells words of equal hash apart.
    """

    def __init__(self, texts: list[bytes], hashes: bool = True, check: bool = False):
        self.data = b"\n".join(texts) + b"\n"
        raw = np.frombuffer(self.data, dtype=np.uint8)
        space = _IS_SPACE[raw]
        edge = np.flatnonzero(space[1:] != space[:-1]) + 1
        if not space[0]:
            edge = np.concatenate(([0], edge))
        self.start, self.end = edge[0::2], edge[1::2]
        ends = np.cumsum(np.fromiter((len(t) + 1 for t in texts), dtype=np.int64, count=len(texts)))
        self.first = np.concatenate(([0], np.searchsorted(self.start, ends)))
        self.hash = self._hash(raw, space, _POWERS) if hashes else None
        self.check = self._hash(raw, space, _OTHER_POWERS) if check else None

    def _hash(self, raw: np.ndarray, space: np.ndarray, powers: np.ndarray) -> np.ndarray:
        if not len(self.start):
            return np.empty(0, dtype=np.uint64)
        length = self.end - self.start
        keep = np.flatnonzero(~space)
        at = np.concatenate(([0], np.cumsum(length)[:-1]))
        place = np.arange(len(keep)) - np.repeat(at, length)
        with np.errstate(over="ignore"):
            code = (raw[keep].astype(np.uint64) + np.uint64(1)) * powers[place & 63]
            code ^= (place >> 6).astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)
            total = np.add.reduceat(code, at)
        return mix64(total ^ length.astype(np.uint64))


def encoded(values) -> list[bytes]:
    """UTF-8 of the texts of an Arrow column, empty where null."""
    import pyarrow as pa

    return [v or b"" for v in values.cast(pa.large_binary()).to_pylist()]


def portions(texts: list[bytes], most: int = 1_000_000):
    """Ranges of texts of about so many bytes; a longer text goes alone and whole."""
    begin = size = 0
    for i, t in enumerate(texts):
        if size and size + len(t) > most:
            yield begin, i
            begin, size = i, 0
        size += len(t) + 1
    if begin < len(texts):
        yield begin, len(texts)


def released(batches):
    """The batches of a task; when they end, Arrow gives back the memory that its pool keeps."""
    import pyarrow as pa

    yield from batches
    pa.default_memory_pool().release_unused()
