"""Substring dedup by super-k-mer partitioning.

A window is `window` consecutive words. Each window belongs to the smallest hash among its
`gram`-word grams, its minimiser. Consecutive windows that share a minimiser travel as one
packed string, a super-k-mer, to the minimiser's part; equal windows have equal
minimisers and so meet. Within a part the windows are sorted by a 64-bit hash and each run
of equal hashes is verified word by word; the first occurrence stays. Strings that a batch
holds again are settled before the shuffle, so copies do not travel. A first pass sums the
words under each slot of minimisers; where a slot would outgrow its share of a part, its
windows travel one by one to the part of their own hash, so no passage fills one task.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from density_peaks.llm.common import Words, cut, encoded, mix64, portions, width

#: Words of a window and of a gram; parts a shuffle partition at least, and words of a part at most on average.
WINDOW, GRAM, PARTS, PART_WORDS = 20, 4, 3, 3_000_000
#: Slots by which minimisers are weighed: one for each MiB of input, as a power of two between these.
LEAST_SLOTS, MOST_SLOTS = 1 << 16, 1 << 20
#: A slot is hot above this multiple of a part's mean words, where it is also above three times the mean of slots.
HOT = 1.0
#: Bytes of text that are cut into super-k-mers at once.
PORTION = 4_000_000
NO_ID = -(1 << 63)

_STRIDE = np.uint64(0x9FB21C651E98DF25)


def minimisers(words: Words, window: int, gram: int) -> tuple[np.ndarray, np.ndarray]:
    """Starts of all windows, as word numbers, and their minimisers' hashes."""
    n = len(words.hash)
    if n < window:
        return np.empty(0, dtype=np.int64), np.empty(0, dtype=np.uint64)
    with np.errstate(over="ignore"):
        h = words.hash[: n - gram + 1].copy()
        for k in range(1, gram):
            h *= _STRIDE
            h += words.hash[k : n - gram + 1 + k]
    h = mix64(h, 5)
    span, covered = window - gram + 1, 1
    low = h
    while covered < span:
        step = min(covered, span - covered)
        low = np.minimum(low[:-step], low[step:])
        covered += step
    last = np.repeat(words.first[1:], np.diff(words.first))[: n - window + 1]
    starts = np.flatnonzero(np.arange(n - window + 1) + window <= last)
    return starts, low[starts]


def window_hashes(codes: np.ndarray, window: int) -> np.ndarray:
    """A hash of each window over a row of 64-bit word codes."""
    n = len(codes) - window + 1
    with np.errstate(over="ignore"):
        h = codes[:n].copy()
        for k in range(1, window):
            h *= _STRIDE
            h += codes[k : n + k]
    return mix64(h, 11)


def runs(starts: np.ndarray, low: np.ndarray, alone: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Begin and end, as places in starts, of runs of adjacent windows of one minimiser; windows marked alone are runs of one."""
    if not len(starts):
        return np.empty(0, dtype=np.int64), np.empty(0, dtype=np.int64)
    new = np.ones(len(starts), dtype=bool)
    new[1:] = (np.diff(starts) != 1) | (low[1:] != low[:-1]) | alone[1:] | alone[:-1]
    begin = np.flatnonzero(new)
    return begin, np.append(begin[1:], len(starts))


def slots_for(docs: DataFrame) -> int:
    """Slots by the planner's estimate of the size of docs; where it knows none, the most."""
    size = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
    return min(MOST_SLOTS, max(LEAST_SLOTS, 1 << (size >> 20).bit_length()))


def slot_loads(docs: DataFrame, window: int, gram: int, slots: int = LEAST_SLOTS) -> DataFrame:
    """slot, load: words that super-k-mers of each slot of minimisers would carry."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        load = np.zeros(slots, dtype=np.int64)
        for b in batches:
            texts = encoded(b.column("text"))
            for lo, hi in portions(texts, PORTION):
                words = Words(texts[lo:hi])
                starts, low = minimisers(words, window, gram)
                begin, end = runs(starts, low, np.zeros(len(starts), dtype=bool))
                if len(begin):
                    # copies within a portion do not travel, so they do not count
                    at = starts[begin]
                    _, one = np.unique(window_hashes(words.hash, window)[at] + (end - begin).astype(np.uint64), return_index=True)
                    load += np.bincount((low[begin[one]] & np.uint64(slots - 1)).astype(np.int64), weights=end[one] - begin[one] + window - 1, minlength=slots).astype(np.int64)
        at = np.flatnonzero(load)
        yield pa.RecordBatch.from_arrays([pa.array(at, pa.int32()), pa.array(load[at], pa.int64())], names=["slot", "load"])

    return docs.select("text").mapInArrow(run, "slot int, load long").groupBy("slot").agg(F.sum("load").alias("load"))


def merged(begin: np.ndarray, end: np.ndarray) -> bytes:
    """Ranges of words as pairs of little-endian 32-bit integers, touching ones joined."""
    order = np.argsort(begin, kind="stable")
    begin, end = begin[order], np.maximum.accumulate(end[order])
    new = np.ones(len(begin), dtype=bool)
    new[1:] = begin[1:] > end[:-1]
    at = np.flatnonzero(new)
    return np.stack([begin[at], end[np.append(at[1:], len(begin)) - 1]], axis=1).astype("<i4").tobytes()


def packed(strings: list[bytes], ids: np.ndarray, tags: np.ndarray, place: np.ndarray) -> bytes:
    size = np.fromiter(map(len, strings), dtype="<i4", count=len(strings))
    head = np.array([len(strings)], dtype="<i8").tobytes()
    return zstandard.ZstdCompressor(level=3).compress(b"".join([head, ids.astype("<i8").tobytes(), tags.astype("<i8").tobytes(), place.astype("<i4").tobytes(), size.tobytes(), *strings]))


def unpacked(blob: bytes) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, bytes]:
    raw = zstandard.ZstdDecompressor().decompress(blob)
    n = int(np.frombuffer(raw, dtype="<i8", count=1)[0])
    ids, tags = np.frombuffer(raw, "<i8", n, 8), np.frombuffer(raw, "<i8", n, 8 + 8 * n)
    place, size = np.frombuffer(raw, "<i4", n, 8 + 16 * n), np.frombuffer(raw, "<i4", n, 8 + 20 * n)
    return ids, tags, place, size, raw[8 + 24 * n :]


def super_kmers(docs: DataFrame, window: int, gram: int, parts: int, hot: np.ndarray) -> DataFrame:
    """part, doc_id, tag, payload: packed strings for a part, or (part below 0) ranges of a document settled here."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            ids = np.array([NO_ID if i is None else i for i in b.column("doc_id").to_pylist()], dtype=np.int64)
            tags = np.array(b.column("tag").to_pylist(), dtype=np.int64)
            texts = encoded(b.column("text"))
            for lo, hi in portions(texts, PORTION):
                order = lo + np.lexsort((tags[lo:hi], ids[lo:hi]))
                # rows repeated whole are one document
                fresh = np.ones(len(order), dtype=bool)
                fresh[1:] = (ids[order][1:] != ids[order][:-1]) | (tags[order][1:] != tags[order][:-1])
                order = order[fresh]
                yield from portion([texts[i] for i in order], ids[order], tags[order])

    def portion(texts: list[bytes], ids: np.ndarray, tags: np.ndarray) -> Iterator[pa.RecordBatch]:
        words = Words(texts)
        starts, low = minimisers(words, window, gram)
        alone = hot[(low & np.uint64(len(hot) - 1)).astype(np.int64)]
        begin, end = runs(starts, low, alone)
        if not len(begin):
            return
        key = low[begin]
        if alone.any():
            own = alone[begin]
            key = np.where(own, window_hashes(words.hash, window)[starts[begin]], key)
        where = (mix64(key, 23) % np.uint64(parts)).astype(np.int64)
        head, tail = starts[begin], starts[end - 1] + window - 1
        doc = np.searchsorted(words.first, head, side="right") - 1
        place = head - words.first[doc]
        # every word is followed by white space; one space stands for it
        raw = np.frombuffer(words.data, dtype=np.uint8)
        size = words.end - words.start + 1
        to = np.concatenate(([0], np.cumsum(size)))
        line = raw[np.repeat(words.start - to[:-1], size) + np.arange(to[-1])].copy()
        line[to[1:] - 1] = 32
        line = line.tobytes()
        strings = [line[a:z] for a, z in zip(to[head].tolist(), (to[tail + 1] - 1).tolist(), strict=True)]
        seen: dict[bytes, int] = {}
        first = np.fromiter((seen.setdefault(s, i) == i for i, s in enumerate(strings)), dtype=bool, count=len(strings))
        again = np.flatnonzero(~first)
        out: tuple[list, list, list, list] = ([], [], [], [])

        def put(part, i, t, payload) -> None:
            for column, v in zip(out, (part, i, t, payload), strict=True):
                column.append(v)

        if len(again):
            cuts = np.flatnonzero(np.diff(doc[again])) + 1
            for at in np.split(again, cuts):
                d = doc[at[0]]
                put(-1 - int(tags[d] ^ ids[d]) % parts, int(ids[d]), int(tags[d]), merged(place[at], place[at] + (end - begin)[at] + window - 1))
        once = np.flatnonzero(first)
        # strings of one minimiser lie side by side, which packs them tighter
        once = once[np.lexsort((key[once], where[once]))]
        for at in np.split(once, np.flatnonzero(np.diff(where[once])) + 1):
            if len(at):
                put(int(where[at[0]]), None, None, packed([strings[i] for i in at], ids[doc[at]], tags[doc[at]], place[at]))
        yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int32()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.int64()), pa.array(out[3], pa.binary())], names=["part", "doc_id", "tag", "payload"])

    return docs.select("doc_id", "tag", "text").mapInArrow(run, "part int, doc_id long, tag long, payload binary")


def repeated_windows(codes: np.ndarray, starts: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """For windows in order of occurrence, the first equal one of each that has one before it.

    codes: exact word numbers. Returns places in starts of the later windows and of their firsts.
    """
    h = window_hashes(mix64(codes.astype(np.uint64), 41), window)[starts]
    order = np.argsort(h, kind="stable")
    same = h[order][1:] == h[order][:-1]
    run = np.concatenate(([0], np.flatnonzero(~same) + 1))
    first = np.repeat(order[run], np.diff(np.append(run, len(order))))
    later = order != first
    a, b = order[later], first[later]
    ok = np.ones(len(a), dtype=bool)
    for k in range(window):
        ok &= codes[starts[a] + k] == codes[starts[b] + k]
    if ok.all():
        return a, b
    # two different windows share a hash: settle the windows of this part by their words alone
    rows = np.stack([codes[starts + k] for k in range(window)], axis=1)
    _, at, which = np.unique(rows, axis=0, return_index=True, return_inverse=True)
    first = at[which.ravel()]
    later = np.flatnonzero(first != np.arange(len(starts)))
    return later, first[later]


def settle(window: int):
    """For a part's packed strings: the ranges that each document loses."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        if pdf["part"].iloc[0] < 0:
            return pdf[["doc_id", "tag", "payload"]]
        ids, tags, place, size, text = (list(x) for x in zip(*map(unpacked, pdf["payload"]), strict=True))
        ids, tags, place, size = map(np.concatenate, (ids, tags, place, size))
        offsets = np.concatenate(([0], np.cumsum(size, dtype=np.int64)))
        strings = pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(size), [None, pa.py_buffer(offsets.astype("<i8").tobytes()), pa.py_buffer(b"".join(text))]).view(pa.large_string())
        order = np.lexsort((place, tags, ids))
        ids, tags, place = ids[order], tags[order], place[order]
        lists = pc.split_pattern(strings.take(pa.array(order)), " ")
        codes = pc.dictionary_encode(lists.flatten()).indices.to_numpy()
        ends = np.cumsum(pc.list_value_length(lists).to_numpy())
        begins = np.concatenate(([0], ends[:-1]))
        count = ends - begins - window + 1
        string = np.repeat(np.arange(len(count)), count)
        inside = np.arange(len(string)) - np.repeat(np.cumsum(count) - count, count)
        later, first = repeated_windows(codes, begins[string] + inside, window)
        # one occurrence may come twice where a row is repeated whole; it is not its own copy
        s, f = string[later], string[first]
        real = (ids[s] != ids[f]) | (tags[s] != tags[f]) | (place[s] + inside[later] != place[f] + inside[first])
        later = np.sort(later[real])
        s, at = string[later], place[string[later]] + inside[later]
        out = []
        if len(later):
            edge = np.flatnonzero((np.diff(ids[s]) != 0) | (np.diff(tags[s]) != 0)) + 1
            for a in np.split(np.arange(len(s)), edge):
                out.append((ids[s[a[0]]], tags[s[a[0]]], merged(at[a], at[a] + window)))
        return pd.DataFrame(out, columns=["doc_id", "tag", "payload"])

    return run


def substring_dedup(docs: DataFrame, window: int = WINDOW, gram: int = GRAM, parts: int | None = None) -> DataFrame:
    """Removes each word that lies in a window which also starts earlier.

    docs needs doc_id and text; other columns are ignored. Earlier is a smaller doc_id
    (null before all), then a smaller hash of the text where an id is repeated, then an
    earlier start. Rows repeated whole are one document and get one result each. Returns
    doc_id, n_words, n_removed, kept_text (kept words joined by one space). A null or empty
    text has no words; a text shorter than a window loses none. No rows give none.
    """
    spark = docs.sparkSession
    keyed = docs.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).withColumn("tag", F.xxhash64("text"))
    slots = slots_for(docs)
    loads = cut(slot_loads(keyed, window, gram, slots))
    total = loads.agg(F.sum("load")).first()[0] or 0
    parts = parts or max(PARTS * width(spark), math.ceil(total / PART_WORDS))
    hot = np.zeros(slots, dtype=bool)
    # at most a third of the slots, and at most parts / HOT of them, can be above the limit
    hot[[r.slot for r in loads.where(F.col("load") > max(HOT * total / parts, 3 * total / slots, 50_000)).collect()]] = True
    # one shuffle takes the packed strings to their parts, and what is settled already along
    lost = super_kmers(keyed, window, gram, parts, hot).groupBy("part").applyInPandas(settle(window), "doc_id long, tag long, payload binary")
    lost = lost.groupBy(F.col("doc_id").alias("id"), F.col("tag").alias("t")).agg(F.collect_list("payload").alias("ranges"))
    found = keyed.join(lost, (F.coalesce("doc_id", F.lit(NO_ID)) == F.col("id")) & (F.col("tag") == F.col("t")), "left").select("doc_id", "text", "ranges")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            total, removed, kept = [], [], []
            for text, ranges in zip(encoded(b.column("text")), b.column("ranges").to_pylist(), strict=True):
                words = text.split()
                total.append(len(words))
                if ranges:
                    r = np.concatenate([np.frombuffer(x, dtype="<i4").reshape(-1, 2) for x in ranges])
                    edge = np.zeros(len(words) + 1, dtype=np.int64)
                    np.add.at(edge, r[:, 0], 1)
                    np.add.at(edge, r[:, 1], -1)
                    keep = np.cumsum(edge[:-1]) == 0
                    words = [w for w, k in zip(words, keep.tolist(), strict=True) if k]
                removed.append(total[-1] - len(words))
                kept.append(b" ".join(words))
            yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), pa.array(total, pa.int64()), pa.array(removed, pa.int64()), pa.array(kept, pa.binary()).cast(pa.string())], names=["doc_id", "n_words", "n_removed", "kept_text"])

    return found.mapInArrow(run, "doc_id long, n_words long, n_removed long, kept_text string")


SQL = r"""
WITH d AS (
  SELECT row_number() OVER () AS row, doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents
), g AS (
  SELECT row, doc_id, i, array_to_string(w[i : i + 19], ' ') AS s FROM (SELECT *, unnest(range(1, len(w) - 18)) AS i FROM d)
), f AS (
  SELECT row, i FROM (SELECT row, i, row_number() OVER (PARTITION BY s ORDER BY doc_id, i) AS k FROM g) WHERE k > 1
), r AS (
  SELECT row, list(DISTINCT j) AS j FROM (SELECT row, unnest(range(i, i + 20)) AS j FROM f) GROUP BY row
)
SELECT d.doc_id, len(d.w)::BIGINT AS n_words, coalesce(len(r.j), 0)::BIGINT AS n_removed,
  sha256(array_to_string(CASE WHEN r.j IS NULL THEN d.w ELSE list_filter(d.w, lambda x, k: NOT list_contains(r.j, k)) END, ' ')) AS kept_sha256
FROM d LEFT JOIN r USING (row)
"""
