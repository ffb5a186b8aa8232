"""Quality rules: cross-document line frequency within a host, and rules on one text.

Normalised lines are hashed; for each host the distinct documents that hold a line are
counted, copies of one text counting once. Lines above the limits are boilerplate of the
host. A document that loses more than half of its words with them is depleted and is
rejected, as one that fails the base rules; from the others these lines are removed.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from density_peaks.llm.common import Words, cut, encoded, mix64, portions, released, whole

#: A line is boilerplate in more than so many documents of its host, and more than this share of them.
LINE_DOCS, LINE_SHARE_PERCENT = 10, 5
#: Base rules: fewest words, and the highest percentage of words in repeated three-word windows.
FEWEST_WORDS, MOST_REPEATED_PERCENT = 50, 50

_SYMBOL = np.zeros(256, dtype=bool)
_SYMBOL[list(b"#*$%&|<>")] = True
_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = True

MEASURES = "doc_id long, host string, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, text_hash long, lines array<long>, line_words array<int>"


def signed(h: int) -> int:
    return h - (1 << 64) if h >> 63 else h


def line_hash(own: list[bytes]) -> int:
    """The hash of a normalised line from its words."""
    return signed(xxhash.xxh3_64_intdigest(b" ".join(own).lower()))


def _sums(flags: np.ndarray, ends: np.ndarray) -> np.ndarray:
    total = np.concatenate(([0], np.cumsum(flags, dtype=np.int64)))[np.concatenate(([0], ends))]
    return np.diff(total)


def _repeated(words: Words) -> np.ndarray:
    """For each text, how many words lie in three-word windows that the text holds twice or more."""
    n, first = len(words.start), words.first
    doc = np.repeat(np.arange(len(first) - 1), np.diff(first))
    inside = np.zeros(n + 2, dtype=bool)
    if n >= 3:
        h = words.hash
        with np.errstate(over="ignore"):
            window = mix64(h[:-2] * np.uint64(0x9E3779B97F4A7C15) + h[1:-1] * np.uint64(0xC2B2AE3D27D4EB4F) + h[2:] + mix64(doc[:-2].astype(np.uint64), 3))
        at = np.flatnonzero(doc[:-2] == doc[2:])
        order = at[np.argsort(window[at], kind="stable")]
        same = window[order][1:] == window[order][:-1]
        twice = np.zeros(len(order), dtype=bool)
        twice[1:] |= same
        twice[:-1] |= same
        hit = order[twice]
        for k in range(3):
            inside[hit + k] = True
    return _sums(inside[:n], first[1:])


def measures(docs: DataFrame, host: str) -> DataFrame:
    """One row a document with the base measures and its distinct normalised lines."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kinds = [pa.int64(), pa.string(), *[pa.int64()] * 6, pa.list_(pa.int64()), pa.list_(pa.int32())]
        names = [c.split()[0] for c in MEASURES.split(", ")]
        for b in released(batches):
            texts = encoded(b.column("text"))
            columns: list[list] = [[] for _ in range(7)]
            for lo, hi in portions(texts):
                part = texts[lo:hi]
                words = Words(part)
                raw = np.frombuffer(words.data, dtype=np.uint8)
                ends = np.cumsum([len(t) + 1 for t in part])
                columns[0] += np.diff(words.first).tolist()
                columns[1] += _sums(((raw & 0xC0) != 0x80) & ~_SPACE[raw], ends).tolist()
                columns[2] += _sums(_SYMBOL[raw], ends).tolist()
                columns[4] += _repeated(words).tolist()
                for t in part:
                    repeats, seen, held = 0, set(), {}
                    for line in t.split(b"\n"):
                        if own := line.split():
                            repeats += line in seen
                            seen.add(line)
                            h = line_hash(own)
                            held[h] = held.get(h, 0) + len(own)
                    columns[3].append(repeats)
                    columns[5].append(list(held))
                    columns[6].append(list(held.values()))
            values = [b.column("doc_id"), b.column("host"), *columns[:5], b.column("text_hash"), *columns[5:]]
            yield pa.RecordBatch.from_arrays([v.cast(k) if isinstance(v, pa.Array) else pa.array(v, k) for v, k in zip(values, kinds, strict=True)], names=names)

    return docs.select("doc_id", F.col(host).cast("string").alias("host"), whole(F.col("text")).alias("text")).withColumn("text_hash", F.xxhash64("text")).mapInArrow(run, MEASURES)


def _named(host: str = "host"):
    """A host's name, and one that no host has where it is null."""
    return F.coalesce(F.concat(F.lit("h"), F.col(host)), F.lit("n"))


def frequent_lines(m: DataFrame, least: int = LINE_DOCS, percent: int = LINE_SHARE_PERCENT) -> DataFrame:
    """host, line of each line above the limits. m: what measures() returns."""
    own = _named()
    # distinct counts take two steps, by line and text, then by line, so a line that a third of all rows share is spread
    held = m.select(own.alias("host"), "text_hash", F.explode("lines").alias("line"))
    counts = held.groupBy("host", "line").agg(F.count_distinct("text_hash").alias("n_docs")).where(F.col("n_docs") > least)
    hosts = m.groupBy(own.alias("host")).agg(F.count_distinct("text_hash").alias("host_docs"))
    return counts.join(hosts, "host").where(100 * F.col("n_docs") > percent * F.col("host_docs")).select("host", "line", "n_docs")


def _verdicts(docs: DataFrame, host: str) -> DataFrame:
    """The columns of judge(), the host, and the hashes of the boilerplate lines that a row holds (null: none)."""
    m = cut(measures(docs, host).withColumn("row", F.monotonically_increasing_id()))
    lines = m.select("row", _named().alias("host"), F.explode(F.arrays_zip("lines", "line_words")).alias("l"))
    lines = lines.select("row", "host", F.col("l.lines").alias("line"), F.col("l.line_words").alias("words"))
    boilerplate = lines.join(frequent_lines(m).select("host", "line"), ["host", "line"], "left_semi")
    removed = boilerplate.groupBy("row").agg(F.sum("words").alias("removed"), F.collect_list("line").alias("removed_lines"))
    out = m.drop("lines", "line_words").join(removed, "row", "left").withColumn("n_removed_words", F.coalesce("removed", F.lit(0)).cast("long"))
    failed = (F.col("n_words") < FEWEST_WORDS) | (100 * F.col("n_repeat_words") > MOST_REPEATED_PERCENT * F.col("n_words"))
    return out.withColumn("base_failed", failed).withColumn("kept", ~failed & (2 * F.col("n_removed_words") <= F.col("n_words")))


def judge(docs: DataFrame, host: str = "source") -> DataFrame:
    """The measures and the verdict of each row of docs.

    docs needs doc_id, text and the host column; other columns are ignored. Returns doc_id,
    n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_removed_words (words of
    boilerplate lines), base_failed, kept. A null or empty text has 0 words and fails the
    base rules; a null host is a host of its own; repeated rows are judged each and count
    once for a line; no rows give none.
    """
    return _verdicts(docs, host).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_removed_words", "base_failed", "kept", "text_hash")


def _without(texts: pd.Series, lines: pd.Series) -> pd.Series:
    """Texts without the lines of the given hashes; null where no lines are given."""

    def rest(t: bytes, gone: set[int]) -> bytes:
        return b"\n".join(x for x in t.split(b"\n") if not ((own := x.split()) and line_hash(own) in gone))

    return pd.Series([None if g is None else rest(bytes(t), set(g)) for t, g in zip(texts, lines, strict=True)], dtype=object)


def clean(docs: DataFrame, host: str = "source") -> DataFrame:
    """The rows of docs that judge() keeps, with the boilerplate lines of their host removed from text.

    Blank lines and all other lines stay as they are and in their order. A column n_chars,
    if there is one, follows the text. Rows without such lines are returned unchanged.
    """
    v = _verdicts(docs, host).where("kept").select(F.col("doc_id").alias("kept_id"), F.col("text_hash").alias("kept_mark"), F.col("host").alias("kept_host"), F.col("removed_lines").alias("without"))
    v = v.dropDuplicates(["kept_id", "kept_mark", "kept_host"])
    # the columns of docs travel as one, so none of them can clash
    own = docs.select(F.struct(*docs.columns).alias("own"), F.col("doc_id").alias("id"), F.xxhash64(whole(F.col("text"))).alias("mark"), F.col(host).cast("string").alias("at"))
    same = F.col("id").eqNullSafe(F.col("kept_id")) & (F.col("mark") == F.col("kept_mark")) & F.col("at").eqNullSafe(F.col("kept_host"))
    out = own.join(v, same)
    # only texts that lose lines travel to Python
    lost, text = F.col("without").isNotNull(), F.col("own.text").cast("string")
    rest = F.pandas_udf(_without, "binary")(F.when(lost, text.cast("binary")), F.col("without")).cast("string")
    out = out.withColumn("cleaned", F.coalesce(rest, text))
    values = {c: F.col("own").getField(c) for c in docs.columns} | {"text": F.when(lost, F.col("cleaned")).otherwise(F.col("own.text"))}
    if "n_chars" in docs.columns:
        kind = docs.schema["n_chars"].dataType
        values["n_chars"] = F.when(lost, F.char_length("cleaned").cast(kind)).otherwise(F.col("own.n_chars"))
    return out.select(*[v.alias(c) for c, v in values.items()])


SQL = r"""
WITH d AS (
  SELECT row_number() OVER () AS row, doc_id, coalesce('h' || source, 'n') AS host, coalesce(text, '') AS text FROM documents
), w AS (
  SELECT row, unnest(regexp_extract_all(text, '[^\x20\x09-\x0D]+')) AS word, generate_subscripts(regexp_extract_all(text, '[^\x20\x09-\x0D]+'), 1) AS i FROM d
), t AS (
  SELECT row, i, word, lead(word) OVER r AS b, lead(word, 2) OVER r AS c FROM w WINDOW r AS (PARTITION BY row ORDER BY i)
), r AS (
  SELECT row, i, (c IS NOT NULL AND count(*) OVER (PARTITION BY row, word, b, c) >= 2)::INT AS twice FROM t
), x AS (
  SELECT row, sum(greatest(twice, coalesce(a, 0), coalesce(b, 0))) AS n_repeat_words
  FROM (SELECT row, twice, lag(twice) OVER r AS a, lag(twice, 2) OVER r AS b FROM r WINDOW r AS (PARTITION BY row ORDER BY i)) GROUP BY row
), l AS (
  SELECT row, host, text, line, trim(regexp_replace(translate(line, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+', ' ', 'g'), ' ') AS norm
  FROM (SELECT row, host, text, unnest(string_split(text, chr(10))) AS line FROM d)
), f AS (
  SELECT host, norm FROM (SELECT host, norm, count(DISTINCT text) AS n FROM l WHERE norm <> '' GROUP BY ALL) JOIN (SELECT host, count(DISTINCT text) AS m FROM d GROUP BY ALL) USING (host)
  WHERE n > 10 AND 100 * n > 5 * m
), k AS (
  SELECT row, count(*) - count(DISTINCT line) AS n_dup_lines FROM l WHERE norm <> '' GROUP BY row
), g AS (
  SELECT row, sum(len(regexp_extract_all(norm, '[^ ]+'))) AS removed FROM l JOIN f USING (host, norm) GROUP BY row
), m AS (
  SELECT d.doc_id, len(regexp_extract_all(text, '[^\x20\x09-\x0D]+'))::BIGINT AS n_words,
    length(regexp_replace(text, '[\x20\x09-\x0D]', '', 'g'))::BIGINT AS word_chars,
    length(regexp_replace(text, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols,
    coalesce(k.n_dup_lines, 0)::BIGINT AS n_dup_lines, coalesce(x.n_repeat_words, 0)::BIGINT AS n_repeat_words, coalesce(g.removed, 0)::BIGINT AS n_removed_words
  FROM d LEFT JOIN x USING (row) LEFT JOIN k USING (row) LEFT JOIN g USING (row)
)
SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed,
  NOT (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AND 2 * n_removed_words <= n_words AS kept
FROM m
"""
