"""MinHash near-dedup with sequential Bayesian verification of banded candidates.

Texts with equal shingle sets form one class, so copies meet once. Bands of the classes'
signatures put them into buckets; a bucket proposes links to two pivots and not all its
pairs. A proposed pair's signatures are compared batch by batch; it is dropped as
soon as the posterior probability of enough similarity falls under a chosen bound, and
survivors are verified on their whole shingle sets. Buckets whose members then hang
together are done. In the others, members of different parts meet: one by one in small
buckets, and in blocks of bounded size, which list no pairs, in large ones.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from density_peaks.llm.common import Words, cut, encoded, mix64, portions, released, whole

#: Shingle words, similarity in percent, bands and rows; a pair at the threshold is missed by all bands with probability (1 - 0.8 ** 5) ** 30 < 1e-5.
SHINGLE, PERCENT, BANDS, ROWS = 4, 80, 30, 5
#: Hashes compared at once, and the posterior probability under which a pair is dropped.
STEP, MISS = 30, 1e-5
#: Buckets of at most so many members pair them one by one; larger ones meet in blocks of at most so many members and shingles.
SMALL, BLOCK, BLOCK_SHINGLES = 6, 1024, 2_000_000
#: Up to so many ids of 8 bytes are broadcast to the scan that makes whole sets; more are joined by a shuffle.
MOST_BROADCAST = 2_000_000

SETS = "doc_id long, text_hash long, n_shingles long, digest binary, signature binary"
_rng = np.random.default_rng(20240229)
_A = _rng.integers(1, 1 << 63, BANDS * ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_B = _rng.integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64)


def shingle_sets(texts: list[bytes], size: int) -> list[np.ndarray]:
    """Sorted distinct 64-bit shingle hashes of lower-cased texts; fewer words are one shingle."""
    words = Words([t.lower() for t in texts])
    h, first = words.hash, words.first
    n = len(h)
    code = mix64(np.zeros(max(0, n - size + 1), dtype=np.uint64), size)
    with np.errstate(over="ignore"):
        for k in range(size):
            code = mix64(code + h[k : n - size + 1 + k]) if n >= size else code
    out = []
    for lo, hi in zip(first[:-1], first[1:], strict=True):
        if hi - lo >= size:
            out.append(np.unique(code[lo : hi - size + 1]))
        elif hi > lo:
            short = np.uint64(hi - lo)
            with np.errstate(over="ignore"):
                for x in h[lo:hi]:
                    short = mix64(np.array([short + x], dtype=np.uint64), 99)[0]
            out.append(np.array([short], dtype=np.uint64))
        else:
            out.append(np.empty(0, dtype=np.uint64))
    return out


def signatures(sets: list[np.ndarray]) -> np.ndarray:
    """Low 16 bits of the minimum of each hash function over each set; empty sets get no meaning.

    Two different minima agree in these bits once in 65536 times, which only keeps a pair.
    """
    sizes = np.array([max(1, len(s)) for s in sets])
    values = np.concatenate([s if len(s) else np.zeros(1, dtype=np.uint64) for s in sets])
    at = np.concatenate(([0], np.cumsum(sizes)[:-1]))
    out = np.empty((len(sets), BANDS * ROWS), dtype="<u2")
    work = np.empty_like(values)
    with np.errstate(over="ignore"):
        for k in range(BANDS * ROWS):
            np.multiply(values, _A[k], out=work)
            work += _B[k]
            out[:, k] = np.minimum.reduceat(work, at) >> np.uint64(32) & np.uint64(0xFFFF)
    return out


def described(docs: DataFrame, size: int) -> DataFrame:
    """doc_id, n_shingles, digest of the set, signature of each row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in released(batches):
            texts = encoded(b.column("text"))
            counts, digests, signs = [], [], []
            for lo, hi in portions(texts, 500_000):
                sets = shingle_sets(texts[lo:hi], size)
                counts += map(len, sets)
                digests += [hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets]
                signs += [row.tobytes() for row in signatures(sets)]
            yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), b.column("text_hash"), pa.array(counts, pa.int64()), pa.array(digests, pa.binary()), pa.array(signs, pa.binary())], names=["doc_id", "text_hash", "n_shingles", "digest", "signature"])

    return docs.select("doc_id", whole(F.col("text")).alias("text")).withColumn("text_hash", F.xxhash64("text")).mapInArrow(run, SETS)


def fewest_matches(percent: int = PERCENT, miss: float = MISS, step: int = STEP) -> dict[int, int]:
    """For each number of compared hashes, the fewest matches that keep a pair.

    With a uniform prior, similarity given m matches of n is Beta(m + 1, n - m + 1); its
    mass over the threshold t equals the chance of at most m successes in n + 1 draws at t.
    """
    t, out = percent / 100, {}
    for n in range(step, BANDS * ROWS + 1, step):
        below, m = 0.0, 0
        while m <= n:
            below += math.comb(n + 1, m) * t**m * (1 - t) ** (n + 1 - m)
            if below >= miss:
                break
            m += 1
        out[n] = m
    return out


def prune(pairs: DataFrame, percent: int) -> DataFrame:
    """Pairs (a, b, sa, sb) that sequential comparison of their signatures leaves: a, b."""
    need = fewest_matches(percent)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            one, two = (np.frombuffer(b"".join(b.column(c).to_pylist()), dtype="<u2").reshape(b.num_rows, -1) for c in ("sa", "sb"))
            alive, matches = np.arange(b.num_rows), np.zeros(b.num_rows, dtype=np.int64)
            for n, m in need.items():
                matches[alive] += (one[alive, n - STEP : n] == two[alive, n - STEP : n]).sum(axis=1)
                alive = alive[matches[alive] >= m]
            yield pa.RecordBatch.from_arrays([b.column("a").take(pa.array(alive)), b.column("b").take(pa.array(alive))], names=["a", "b"])

    return pairs.select("a", "b", "sa", "sb").mapInArrow(run, "a long, b long")


def meet(members: DataFrame, sets: DataFrame, classes: DataFrame, percent: int) -> DataFrame:
    """Links (a, b) that join different labels within buckets, without a row for each pair.

    members: key, cls, label, n, blocks. A bucket's members are dealt into blocks, and each
    two blocks meet in a task of their own, so a task holds a bounded number of members. A
    member is compared with all that do not hang together with it yet: signatures step by
    step, then whole sets from the likeliest on. Every two members meet, so no link that
    would join two parts is lost; links within a part are not needed.
    """
    need = fewest_matches(percent)

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.drop_duplicates("cls").sort_values("cls")
        cls, n = pdf["cls"].to_numpy(), pdf["n"].to_numpy()
        sign = np.frombuffer(b"".join(pdf["signature"]), dtype="<u2").reshape(len(pdf), -1)
        held = [np.asarray(x) for x in pdf["set"]]
        root, size = np.unique(pdf["label"].to_numpy(), return_inverse=True, return_counts=True)[1:]
        order = np.argsort(size[root], kind="stable")  # those that hang together with few come first
        open_ = np.ones(len(pdf), dtype=bool)
        found = []
        for a in order:
            open_[a] = False
            b = np.flatnonzero(open_ & (root != root[a]) & (100 * np.minimum(n, n[a]) >= percent * np.maximum(n, n[a])))
            matches = np.zeros(len(b), dtype=np.int64)
            for k, least in need.items():
                matches += (sign[b, k - STEP : k] == sign[a, k - STEP : k]).sum(axis=1)
                b, matches = b[matches >= least], matches[matches >= least]
            for x in b[np.argsort(-matches, kind="stable")]:
                if root[x] != root[a]:
                    both = len(np.intersect1d(held[a], held[x], assume_unique=True))
                    if 100 * both >= percent * (n[a] + n[x] - both):
                        found.append((min(cls[a], cls[x]), max(cls[a], cls[x])))
                        root[root == root[x]] = root[a]
        return pd.DataFrame(found, columns=["a", "b"], dtype="int64")

    dealt = members.withColumn("own", F.pmod(F.xxhash64("cls"), F.col("blocks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), (F.col("blocks") - 1).cast("int"))))
    dealt = dealt.select("key", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "cls", "label", "n")
    rows = dealt.join(classes.select("cls", "signature"), "cls").join(sets, "cls")
    return rows.groupBy("key", "i", "j").applyInPandas(run, "a long, b long")


def whole_sets(docs: DataFrame, wanted: DataFrame, size: int) -> DataFrame:
    """cls, set: the whole shingle sets of the wanted classes (cls, first_doc, digest), one row each."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in released(batches):
            texts = encoded(b.column("text"))
            for lo, hi in portions(texts, 500_000):  # small batches out, as sets are larger than texts
                sets = shingle_sets(texts[lo:hi], size)
                digests = [hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets]
                ends = np.concatenate(([0], np.cumsum([len(s) for s in sets]))).astype(np.int32)
                values = pa.array(np.concatenate(sets).view(np.int64), pa.int64())
                yield pa.RecordBatch.from_arrays([pa.array(digests, pa.binary()), pa.ListArray.from_arrays(pa.array(ends), values)], names=["digest", "set"])

    ids = wanted.select(F.col("first_doc").alias("id")).distinct()
    if wanted.count() <= MOST_BROADCAST:
        ids = F.broadcast(ids)
    own = docs.select("doc_id", "text").join(ids, F.col("doc_id").eqNullSafe(F.col("id")), "left_semi")
    sets = own.select("text").mapInArrow(run, "digest binary, set array<long>").dropDuplicates(["digest"])
    return wanted.select("cls", "digest").join(sets, "digest").select("cls", "set")


def verify(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """Pairs whose whole sets are similar enough: a, b. Sets are intersected in the JVM."""
    one = sets.select(F.col("cls").alias("a"), F.col("set").alias("ta"))
    two = sets.select(F.col("cls").alias("b"), F.col("set").alias("tb"))
    met = pairs.join(two, "b").join(one, "a").select("a", "b", F.size(F.array_intersect("ta", "tb")).alias("both"), (F.size("ta") + F.size("tb")).alias("sizes"))
    return met.where(100 * F.col("both") >= percent * (F.col("sizes") - F.col("both"))).select("a", "b")


def components(links: DataFrame, rounds: int = 60) -> DataFrame:
    """cls, label of each class in a link: label is the smallest class that it reaches.

    A round gives each class the smallest label beside it and then that label's own label,
    so rounds grow with the logarithm of a chain's length; stars take two.
    """
    edges = cut(links.select("a", "b").unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    label = cut(edges.groupBy(F.col("a").alias("cls")).agg(F.least(F.min("b"), F.col("a")).alias("label")))
    for _ in range(rounds):
        beside = edges.join(label.select(F.col("cls").alias("b"), "label"), "b").groupBy(F.col("a").alias("at")).agg(F.min("label").alias("least"))
        # labels of labels: what the smallest label beside a class has itself been given
        up = label.select(F.col("cls").alias("least"), F.col("label").alias("top"))
        near = label.join(beside, F.col("cls") == F.col("at")).select("cls", "label", F.least("label", "least").alias("least"))
        label = cut(near.join(up, "least", "left").select("cls", F.least("least", "top").alias("label"), (F.least("least", "top") < F.col("label")).alias("moved")))
        if label.where("moved").isEmpty():
            return label.select("cls", "label")
        label = label.select("cls", "label")
    raise RuntimeError("labels did not settle")


def near_duplicates(docs: DataFrame, size: int = SHINGLE, percent: int = PERCENT) -> DataFrame:
    """The near-duplicate component of each row of docs.

    docs needs doc_id and text; other columns are ignored. Lower-cases A-Z. Returns doc_id,
    n_shingles, component_id (smallest doc_id of the component, null if all are null),
    kept (doc_id = component_id, rows repeated whole alike) and text_hash. A null text, or one without
    words, has no shingles and is a component of its own. No rows give none.
    """
    rows = cut(described(docs, size).withColumn("row", F.monotonically_increasing_id()))
    classes = rows.where("n_shingles > 0").groupBy("digest").agg(F.min("row").alias("cls"), F.min("doc_id").alias("first_doc"))
    classes = cut(classes.join(rows.select(F.col("row").alias("cls"), "signature", F.col("n_shingles").alias("n")), "cls"))

    # bands, then only buckets of two or more classes
    keys = [F.xxhash64(F.lit(k), F.substring(F.col("signature"), 2 * ROWS * k + 1, 2 * ROWS)) for k in range(BANDS)]
    bands = classes.select("cls", "n", F.explode(F.array(*keys)).alias("key"))
    shared = bands.groupBy("key").agg(F.min("cls").alias("low"), F.max("cls").alias("high")).where("low < high").select("key")
    members = cut(bands.join(shared, "key", "left_semi").select("key", "cls", "n"))
    wanted = classes.join(members.select("cls").distinct(), "cls", "left_semi").select("cls", "first_doc", "digest")
    sets = cut(whole_sets(docs, wanted, size))

    def proved(pairs: DataFrame) -> DataFrame:
        sign = classes.select("cls", "signature")
        pairs = pairs.join(sign.select(F.col("cls").alias("b"), F.col("signature").alias("sb")), "b").join(sign.select(F.col("cls").alias("a"), F.col("signature").alias("sa")), "a")
        return verify(prune(pairs, percent), sets, percent)

    fits = lambda x, y: (100 * F.least(x, y) >= percent * F.greatest(x, y))
    # two pivots a bucket, its smallest and largest class, so that proposals grow with members
    ends = members.groupBy("key").agg(F.min(F.struct("cls", "n")).alias("low"), F.max(F.struct("cls", "n")).alias("high"))
    ends = ends.select("key", F.explode(F.array("low", "high")).alias("p")).select("key", F.col("p.cls").alias("a"), F.col("p.n").alias("na"))
    pairs = members.join(ends, "key").where((F.col("cls") != F.col("a")) & fits(F.col("n"), F.col("na")))
    links = cut(proved(pairs.select(F.least("a", "cls").alias("a"), F.greatest("a", "cls").alias("b")).distinct()))
    label = components(links)
    # buckets whose members now hang together are done; in others the parts meet
    held = members.join(label, "cls", "left").withColumn("label", F.coalesce("label", "cls"))
    apart = held.groupBy("key").agg(F.min("label").alias("l"), F.max("label").alias("h"), F.count(F.lit(1)).alias("g"), F.sum("n").alias("s")).where("l < h")
    blocks = F.ceil(F.greatest(F.col("g") / BLOCK, F.col("s") / BLOCK_SHINGLES)).cast("long").alias("blocks")
    held = cut(held.join(apart.select("key", "g", blocks), "key"))
    few = held.where(F.col("g") <= SMALL)
    other = few.select("key", F.col("cls").alias("b"), F.col("label").alias("lb"), F.col("n").alias("nb"))
    pairs = few.select("key", F.col("cls").alias("a"), "label", "n").join(other, "key").where((F.col("a") < F.col("b")) & (F.col("label") != F.col("lb")) & fits(F.col("n"), F.col("nb")))
    more = proved(pairs.select("a", "b").distinct().join(links, ["a", "b"], "left_anti"))
    more = cut(more.unionByName(meet(held.where(F.col("g") > SMALL).select("key", "cls", "label", "n", "blocks"), sets, classes, percent)))
    if not more.isEmpty():
        label = components(links.unionByName(more))

    top = classes.select("cls", "digest", "first_doc").join(label, "cls", "left").withColumn("label", F.coalesce("label", "cls"))
    least = top.groupBy("label").agg(F.min("first_doc").alias("component_id"))
    top = top.join(least, "label").select("digest", "component_id")
    out = rows.select("doc_id", "text_hash", "n_shingles", F.when(F.col("n_shingles") > 0, F.col("digest")).alias("digest")).join(top, "digest", "left")
    out = out.withColumn("component_id", F.when(F.col("n_shingles") > 0, F.col("component_id")).otherwise(F.col("doc_id")))
    return out.select("doc_id", "n_shingles", "component_id", F.col("doc_id").eqNullSafe(F.col("component_id")).alias("kept"), "text_hash")


SQL = r"""
WITH RECURSIVE d AS (
  SELECT row_number() OVER () AS row, doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents
), s AS (
  SELECT row, doc_id, CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 4 THEN [array_to_string(w, ' ')]
    ELSE list_distinct(list_transform(range(1, len(w) - 2), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2] || ' ' || w[i + 3])) END AS s FROM d
), e AS (
  SELECT row, len(s) AS n, unnest(s) AS x FROM s
), p AS (
  SELECT a.row AS a, b.row AS b FROM e a JOIN e b ON a.x = b.x AND a.row <> b.row AND 5 * least(a.n, b.n) >= 4 * greatest(a.n, b.n)
  GROUP BY a.row, b.row, a.n, b.n HAVING 100 * count(*) >= 80 * (a.n + b.n - count(*))
), c AS (
  SELECT row AS a, row AS b FROM s UNION SELECT c.a, p.b FROM c JOIN p ON c.b = p.a
), m AS (
  SELECT c.a AS row, min(s.doc_id) AS component_id FROM c JOIN s ON s.row = c.b GROUP BY c.a
)
SELECT s.doc_id, len(s.s)::BIGINT AS n_shingles, m.component_id, s.doc_id = m.component_id AS kept FROM s JOIN m USING (row)
"""
