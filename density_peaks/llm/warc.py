"""WARC archives: writing with revisit records, and reading by boundary-chain verification.

Archives are written by Spark's text writer, whose line separator is the record's closing
blank lines, so any store that Spark writes to will do. For reading, the same reader cuts
files at each record magic, in splits of any size; byte offsets come from the lengths of
what lies before, summed by split. Every cut is a candidate: its header says where its
successor starts. Pointer jumping from each file's start keeps the reachable candidates,
so a magic inside a payload is rejected, and that payload is put together again.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from density_peaks.llm.common import cut, shared_dir, whole

# The record magic and separators.
MAGIC = "WARC/1.1\r\n"
BREAK = "\r\n\r\n"
#: Payloads from this size on may be revisits.
LEAST = 1000
#: Bytes of a split: a SPLITS-th of all archives, between these.
SPLITS, LEAST_SPLIT, MOST_SPLIT = 4096, 4 << 20, 128 << 20

#: Tables of at most so many rows, each under 200 bytes, are broadcast; larger ones are joined by a shuffle.
MOST_BROADCAST = 300_000


def _sent(df: DataFrame) -> DataFrame:
    """Marks a table whose counted rows are few enough for broadcast."""
    return F.broadcast(df) if df.count() <= MOST_BROADCAST else df


def _id(page: Column) -> Column:
    h = F.md5(F.concat_ws(":", F.lit("page"), F.coalesce(page.cast("string"), F.lit("null"))))
    return F.concat(F.lit("<urn:uuid:"), F.concat_ws("-", *[F.substring(h, a, n) for a, n in ((1, 8), (9, 4), (13, 4), (17, 4), (21, 12))]), F.lit(">"))


def records(pages: DataFrame) -> DataFrame:
    """page_id, record_type, refers_to, record (header and payload) of each row of pages.

    Of equal payloads of at least LEAST bytes the row with the largest page_id is the
    response and others are revisits without payload; smaller ones are all responses.
    """
    body = whole(F.col("html"))
    p = pages.select(F.col("page_id").cast("long").alias("page_id"), F.regexp_replace(whole(F.col("url")), r"[\r\n]+", "").alias("url"), body.alias("body"))
    p = p.withColumn("size", F.octet_length("body").cast("long")).withColumn("digest", F.sha1(F.col("body").cast("binary"))).withColumn("strong", F.sha2("body", 256))
    groups = p.where(F.col("size") >= LEAST).groupBy("strong").agg(F.max("page_id").alias("first_id"), F.count(F.lit(1)).alias("n")).where("n > 1").select("strong", "first_id")
    p = p.join(_sent(cut(groups)), "strong", "left")
    again = F.col("first_id").isNotNull() & ~F.col("page_id").eqNullSafe(F.col("first_id")) & (F.col("size") >= LEAST)
    p = p.withColumn("record_type", F.when(again, "revisit").otherwise("response")).withColumn("refers_to", F.when(again, F.col("first_id")))
    line = lambda name, value: F.concat(F.lit(f"{name}: "), value, F.lit("\r\n"))
    page = lambda c: F.coalesce(c.cast("string"), F.lit(""))
    header = F.concat(
        F.lit(MAGIC),
        line("WARC-Type", F.col("record_type")),
        line("WARC-Record-ID", _id(F.col("page_id"))),
        line("WARC-Date", F.lit("2024-01-01T00:00:00Z")),
        line("WARC-Target-URI", F.col("url")),
        line("WARC-Payload-Digest", F.concat(F.lit("sha1:"), F.col("digest"))),
        line("X-Page-ID", page(F.col("page_id"))),
        line("X-Payload-Bytes", F.col("size").cast("string")),
        F.when(again, F.concat(line("WARC-Refers-To", _id(F.col("first_id"))), line("X-Refers-To-Page", page(F.col("first_id"))), line("WARC-Profile", F.lit("http://netpreserve.org/warc/1.1/revisit/identical-payload-digest")))).otherwise(F.lit("")),
        line("Content-Type", F.lit("text/html; charset=utf-8")),
        line("Content-Length", F.when(again, F.lit(0)).otherwise(F.col("size")).cast("string")),
        F.lit("\r\n"),
    )
    return p.select("page_id", "record_type", "refers_to", F.concat(header, F.when(again, F.lit("")).otherwise(F.col("body"))).alias("record"))


def write_archives(pages: DataFrame, path: str) -> None:
    """Writes a record for each row of pages below path, one archive a task."""
    records(pages).select("record").write.mode("overwrite").option("lineSep", BREAK).text(path)


def fixed_splits(spark: SparkSession, path: str) -> SparkSession:
    """A session of the same cluster that cuts the files below path into the same splits at every scan.

    Split sizes otherwise follow the number of cores, which changes as executors come and
    go, and a segment is known by its split and its number in it.
    """
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    total = p.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(p).getLength()
    own = spark.newSession()
    own.conf.set("spark.sql.files.minPartitionNum", "1")
    own.conf.set("spark.sql.files.maxPartitionBytes", str(min(MOST_SPLIT, max(LEAST_SPLIT, total // SPLITS))))
    return own


def segments(spark: SparkSession, path: str) -> DataFrame:
    """file, split, seq, body: what lies between magics, in order within each split of a file."""
    raw = spark.read.option("lineSep", MAGIC).option("recursiveFileLookup", "true").text(path)
    cols = [F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("split"), F.monotonically_increasing_id().alias("seq"), F.col("value").alias("body")]
    return raw.select(*cols)


def _field(header: Column, name: str) -> Column:
    return F.regexp_extract(header, rf"(?i)(?:^|\r\n){name}:[ \t]*([^\r\n]*)", 1)


def candidates(segs: DataFrame) -> DataFrame:
    """file, split, seq, length, offset, successor and header of each segment, without payloads.

    offset is the byte at which the segment's magic starts; the first segment of a file has
    none before it. successor is null where the segment is no record header.
    """
    body = F.col("body")
    header = F.substring_index(body, BREAK, 1)
    meta = segs.select("file", "split", "seq", F.octet_length(body).cast("long").alias("length"), F.when(F.contains(body, F.lit(BREAK)), header).alias("header"))
    meta = cut(meta.withColumn("content", F.when(F.col("header").isNotNull(), _field(F.col("header"), "Content-Length"))))
    magic = len(MAGIC)
    # a file's text before its first magic is the first line of its first split, without a magic before it
    sums = meta.groupBy("file", "split").agg(F.sum(F.col("length") + magic).alias("bytes"))
    base = sums.withColumn("base", F.coalesce(F.sum("bytes").over(Window.partitionBy("file").orderBy("split").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("file", "split", "base")
    inner = Window.partitionBy("file", "split").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)
    meta = meta.join(base, ["file", "split"]).withColumn("offset", F.col("base") + F.coalesce(F.sum(F.col("length") + magic).over(inner), F.lit(0)) - magic)
    good = F.col("content").rlike("^[0-9]{1,15}$") & (F.col("offset") >= 0)
    head = F.octet_length("header") + len(BREAK)
    meta = meta.withColumn("head", F.when(good, head)).withColumn("content", F.when(good, F.col("content").cast("long")))
    return meta.withColumn("successor", F.col("offset") + magic + F.col("head") + F.col("content") + len(BREAK)).drop("base")


def reachable(c: DataFrame, rounds: int = 48) -> DataFrame:
    """file, offset of the records on the chain from each file's start.

    Within a split, chains are followed first: each candidate points to the first record
    at or beyond the split's end that it leads to. Pointer jumping then runs over splits,
    doubling the step each round, so its rounds grow with the logarithm of splits a file.
    """
    edges = c.where("successor is not null").select("file", "split", "offset", "successor")

    def exits(pdf):
        import numpy as np
        import pandas as pd

        pdf = pdf.sort_values("offset")
        offset, succ = pdf["offset"].to_numpy(), pdf["successor"].to_numpy()
        at = np.searchsorted(offset, succ)
        at[(at < len(offset)) & (offset[np.minimum(at, len(offset) - 1)] != succ)] = len(offset)
        jump, end = np.append(at, len(offset)), np.append(succ, -1)
        while (jump[:-1] < len(offset)).any():
            inside = jump < len(offset)
            end = np.where(inside, end[jump], end)
            jump = np.where(inside, jump[jump], jump)
        return pd.DataFrame({"file": pdf["file"], "split": pdf["split"], "offset": offset, "successor": succ, "leaves": end[:-1]})

    edges = cut(edges.groupBy("file", "split").applyInPandas(exits, "file string, split long, offset long, successor long, leaves long"))
    # entries: the file's start, and the records that a reached split leaves for
    reach = edges.where("offset = 0").select("file", "offset")
    hop = edges.select("file", "offset", F.col("leaves").alias("to"))
    hop = hop.join(edges.select("file", F.col("offset").alias("to")), ["file", "to"], "left_semi")
    if not hop.isEmpty():
        hop = cut(hop)
        for _ in range(rounds):
            reach = cut(reach.unionByName(reach.join(hop, ["file", "offset"]).select("file", F.col("to").alias("offset"))).distinct())
            longer = hop.join(hop.select("file", F.col("offset").alias("to"), F.col("to").alias("next")), ["file", "to"]).select("file", "offset", F.col("next").alias("to"))
            if longer.isEmpty():
                break
            hop = cut(longer)
    entry = reach.join(edges.select("file", "split", "offset"), ["file", "offset"])
    entry = entry.select(*[F.col(c).alias(c) for c in ("file", "split", "offset")])

    def follow(key, starts, own):
        import numpy as np
        import pandas as pd

        own = own.sort_values("offset")
        offset, succ = own["offset"].to_numpy(), own["successor"].to_numpy()
        on = np.isin(offset, starts["offset"].to_numpy())
        at = np.searchsorted(offset, succ)
        for i in range(len(offset)):
            if on[i] and at[i] < len(offset) and offset[at[i]] == succ[i]:
                on[at[i]] = True
        return pd.DataFrame({"file": own["file"][on], "offset": offset[on], "successor": succ[on]})

    return entry.groupBy("file", "split").cogroup(edges.groupBy("file", "split")).applyInPandas(follow, "file string, offset long, successor long")


def read_archives(spark: SparkSession, path: str) -> DataFrame:
    """The records of all archives below path: file, header, payload (binary).

    Bytes before the first record of a file, and after a broken one, belong to no record.
    """
    segs = segments(fixed_splits(spark, path), path)
    c = cut(candidates(segs))
    kept = cut(reachable(c))
    c = c.select("file", "split", "seq", "offset", "length", "header", "head", "content")
    sound = kept.join(c, ["file", "offset"])
    # a payload is whole in its own segment unless a magic lies inside it; what is not is the exception
    usual = sound.where(F.col("length") >= F.col("head") + F.col("content")).select("file", "split", "seq", "offset")
    others = cut(c.join(usual, ["file", "split", "seq"], "left_anti").select("file", "split", "seq"))
    one = segs.join(_sent(others), ["file", "split", "seq"], "left_anti")
    header = F.substring_index("body", BREAK, 1)
    head = F.octet_length("header") + len(BREAK)
    one = one.withColumn("header", header).withColumn("head", head).withColumn("content", _field(F.col("header"), "Content-Length").cast("int"))
    body = F.col("body").cast("binary")
    one = one.select("file", "header", F.expr("substring(cast(body as binary), cast(head + 1 as int), content)").alias("payload"))
    broken = cut(sound.where(F.col("length") < F.col("head") + F.col("content")).select("file", F.col("offset").alias("start"), "successor", F.col("header").alias("own"), F.col("head").alias("skip"), F.col("content").alias("size")))
    if broken.isEmpty():
        return one
    # ranges of one file do not overlap, so a segment belongs to the last broken record that starts before it, if to any
    begun = c.select("file", "split", "seq", "offset").join(_sent(broken), (c["file"] == broken["file"]) & (c["offset"] == broken["start"]), "left")
    begun = begun.select(c["file"], "split", "seq", "offset", F.when(F.col("start").isNotNull(), F.struct("start", "successor", "own", "skip", "size")).alias("r"))
    last = F.last("r", ignorenulls=True).over(Window.partitionBy("file").orderBy("offset").rowsBetween(Window.unboundedPreceding, Window.currentRow))
    parts = begun.withColumn("r", last).where(F.col("offset") < F.col("r.successor")).select("file", "split", "seq", "offset", "r.start", "r.own", "r.skip", "r.size")
    held = segs.join(parts, ["file", "split", "seq"]).groupBy("file", "start", "own", "skip", "size").agg(F.sort_array(F.collect_list(F.struct("offset", body.alias("b")))).alias("all"))
    joined = F.aggregate(F.slice(F.col("all"), 2, F.greatest(F.size("all") - 1, F.lit(1))), F.element_at("all", 1)["b"], lambda x, y: F.concat(x, F.lit(MAGIC).cast("binary"), y["b"]))
    held = held.withColumn("raw", joined).select("file", F.col("own").alias("header"), F.expr("substring(raw, cast(skip + 1 as int), cast(size as int))").alias("payload"))
    return one.unionByName(held)


def described(found: DataFrame) -> DataFrame:
    """page_id, payload_bytes, payload_digest, record_type, refers_to of records read back.

    A response's bytes and digest are taken from its payload; a revisit's from its header,
    which speaks of the payload it refers to.
    """
    h = F.col("header")
    kind = _field(h, "WARC-Type")
    number = lambda name: F.when(_field(h, name) != "", _field(h, name).cast("long"))
    response = kind == "response"
    return found.select(
        number("X-Page-ID").alias("page_id"),
        F.when(response, F.octet_length("payload").cast("long")).otherwise(number("X-Payload-Bytes")).alias("payload_bytes"),
        F.when(response, F.sha1("payload")).otherwise(F.substring_index(_field(h, "WARC-Payload-Digest"), ":", -1)).alias("payload_digest"),
        kind.alias("record_type"),
        F.when(~response, number("X-Refers-To-Page")).alias("refers_to"),
    )


def round_trip(pages: DataFrame, path: str | None = None) -> DataFrame:
    """Writes archives of pages and describes what is read back.

    pages needs page_id, url, html; other columns are ignored. A null html is an empty
    payload; a null page_id stays null; line breaks in a url are dropped; rows repeated
    whole write a record each. No rows give none.
    """
    spark = pages.sparkSession
    path = path or f"{shared_dir(spark).rstrip('/')}/warc-{uuid.uuid4().hex}"
    write_archives(pages, path)
    return described(read_archives(spark, path))


SQL = """
WITH p AS (
  SELECT page_id, octet_length(encode(coalesce(html, ''))) AS payload_bytes, sha1(coalesce(html, '')) AS payload_digest, coalesce(html, '') AS html FROM pages
), g AS (
  SELECT html, max(page_id) AS top FROM p WHERE payload_bytes >= 1000 GROUP BY html
)
SELECT page_id, payload_bytes, payload_digest, CASE WHEN g.top IS NULL OR page_id = g.top THEN 'response' ELSE 'revisit' END AS record_type,
  CASE WHEN page_id <> g.top THEN g.top END AS refers_to
FROM p LEFT JOIN g ON p.html = g.html
"""
