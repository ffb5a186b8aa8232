"""The corpus pipeline: quality rules, exact dedup, near dedup, mixing, packing.

Each stage takes (spark, docs, sf_dir) and works on all that the stage before kept. All
but the last return the columns of documents. Rows are told apart by doc_id and a hash of
the text, so ids that repeat with other texts are judged apart. Nulls and empty tables are
handled as the operators' docstrings say; a stage joins the columns of docs as one struct,
so extra columns of any name pass through.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from density_peaks.llm import exact_dedup, mixing, near_dedup, packing, quality
from density_peaks.llm.common import finished, lowered, remove, shared_dir, whole
from density_peaks.llm.queries import tokenizer


def _held(docs: DataFrame, mark: Column) -> DataFrame:
    """own (all columns of docs as one), id and mark (a hash of the text)."""
    return docs.select(F.struct(*docs.columns).alias("own"), F.col("doc_id").alias("id"), mark.alias("mark"))


def _only(docs: DataFrame, rows: DataFrame, mark: Column | None = None) -> DataFrame:
    """own, id and mark of the rows of docs whose doc_id and mark (a hash of the text by default) are among rows."""
    held = _held(docs, F.xxhash64(whole(F.col("text"))) if mark is None else mark)
    rows = rows.toDF("kept_id", "kept_mark")
    return held.join(rows, F.col("id").eqNullSafe(F.col("kept_id")) & (F.col("mark") == F.col("kept_mark")), "left_semi")


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules and the line-frequency rule keep, without the boilerplate lines of their source."""
    return quality.clean(docs)


def exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of equal texts: that with the largest doc_id."""
    kept = exact_dedup.dedup(docs).where("kept").select("doc_id", "text_sha256")
    return _only(docs, kept, F.sha2(lowered(F.col("text")), 256)).dropDuplicates(["id", "mark"]).select("own.*")


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate component (five-word shingles, 0.8): the smallest doc_id."""
    found = near_dedup.near_duplicates(docs, size=5)
    return _only(docs, found.where("kept").select("doc_id", "text_hash")).select("own.*")


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them; a document taken twice is two rows."""
    copies = mixing.mix(docs).groupBy(F.col("doc_id").alias("mix_id"), F.col("text_hash").alias("mix_hash"), F.col("source").alias("mix_source")).agg(F.max("copies").alias("copies"))
    own = _held(docs, F.xxhash64(whole(F.col("text")))).withColumn("at", F.col("own.source").cast("string"))
    same = F.col("id").eqNullSafe(F.col("mix_id")) & (F.col("mark") == F.col("mix_hash")) & F.col("at").eqNullSafe(F.col("mix_source"))
    taken = own.join(copies.where("copies > 0"), same)
    return taken.select("own", F.explode(F.sequence(F.lit(1), F.col("copies")))).select("own.*")


def packed_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The pieces of all rows in sequences of at most 2048 tokens."""
    return packing.pack(docs, tokenizer("word_bpe_49k.json"))


STAGES = [
    ("quality_rules", quality_rules),
    ("exact_dedup", exact_copies),
    ("near_dedup", near_copies),
    ("source_mix", source_mix),
    ("packing", packed_sequences),
]

#: The genetic algorithm of the last stage has no SQL; tests/llm/test_pipeline.py follows the stages by other means.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str, folder: str | None = None) -> DataFrame:
    """All stages over documents, each written as Parquet and read again.

    folder: where the stages are written, a new folder of the shared one by default. A run
    that is started again with the same folder goes on after the last stage that ended; a
    stage's files go when the next one is written.
    """
    base = (folder or f"{shared_dir(spark).rstrip('/')}/pipeline-{uuid.uuid4().hex}").rstrip("/")
    paths = [f"{base}/{k}-{name}" for k, (name, _) in enumerate(STAGES[:-1])]
    docs = None
    for k, (path, (_, stage)) in enumerate(zip(paths, STAGES, strict=False)):
        if any(finished(spark, later) for later in paths[k + 1 :]):
            continue
        if not finished(spark, path):
            before = spark.read.parquet(paths[k - 1] if k else f"{sf_dir}/documents.parquet")
            stage(spark, before, sf_dir).write.mode("overwrite").parquet(path)
        if k:
            remove(spark, paths[k - 1])
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)
