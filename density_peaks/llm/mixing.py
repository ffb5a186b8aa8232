"""Mixing sources to target weights by Pareto order sampling, in DataFrame functions only.

A source's target and a document's weight say how many copies of it are expected. The
whole copies are certain; the fractional rest is an inclusion probability p, and documents
are ranked by u / (1 - u) over p / (1 - p), u uniform. The front of that ranking is taken until the
words that the certain copies leave over are filled, so the size is fixed and only which
documents fill it is random.
"""

from __future__ import annotations

from collections.abc import Callable, Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from density_peaks.llm.common import cut, whole, word_count

#: Steps of the ranking whose word sums are added up before the last step is ranked row by row.
STEPS = 4096


def uniform(key: Column, seed: int) -> Column:
    """A reproducible number in (0, 1) for each key: 52 bits of an MD5."""
    text = F.concat_ws(":", F.coalesce(key.cast("string"), F.lit("null")), F.lit(str(seed)))
    bits = F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("double")
    return (bits + F.lit(0.5)) / F.lit(4503599627370496.0)


def by_length(size: Column) -> Column:
    """A document's weight: twice as many copies a word from 1000 words on as for the shortest, in whole thousandths."""
    return F.lit(1000) + F.least(size, F.lit(1000))


def source_targets(sizes: DataFrame, weights: Sequence[float], share: float, most: float) -> DataFrame:
    """source, source_size, target: weighted shares of share * all words, each at most most * its source.

    One row a source meets in the window here, never the rows of documents. The excess of
    capped sources goes to the others by weight; with sources ordered by the words at which
    they cap, the first that stays below its cap fixes the level for all after it.
    """
    by = sizes.groupBy("source").agg(F.sum("size").alias("source_size"))
    turn = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    weight = F.element_at(F.array(*[F.lit(float(w)) for w in weights]), (turn % len(weights) + 1).cast("int"))
    by = by.withColumn("weight", weight).withColumn("most", F.lit(float(most)) * F.col("source_size"))
    order = Window.orderBy(F.col("most") / F.col("weight"), F.col("source").asc_nulls_last())
    before, after = order.rowsBetween(Window.unboundedPreceding, -1), order.rowsBetween(0, Window.unboundedFollowing)
    left = F.lit(float(share)) * F.sum("source_size").over(Window.partitionBy()) - F.coalesce(F.sum("most").over(before), F.lit(0.0))
    by = by.withColumn("level", left / F.sum("weight").over(after)).withColumn("open", F.col("level") * F.col("weight") <= F.col("most"))
    first = F.max(F.when(F.col("open"), F.col("level"))).over(Window.partitionBy())  # levels only fall after the first open one
    target = F.least(F.col("most"), F.coalesce(first * F.col("weight"), F.col("most")))
    return by.select("source", F.col("source_size").cast("long").alias("source_size"), target.alias("target"))


def mix(docs: DataFrame, weights: Sequence[float] = (5, 2, 1), share: float = 1.5, most: float = 2.0, seed: int = 17, weight: Column | Callable[[Column], Column] | None = by_length) -> DataFrame:
    """How many copies of each document a mix takes.

    docs needs doc_id, text, source; other columns are ignored. Sources in code point
    order, null last, weigh weights in turn. weight is a positive column of docs, or a
    function of the column of sizes, by which the expected copies of a document differ
    from its source's rate; with None all documents of a source have the same rate.
    Returns doc_id, text_hash, size, source, source_size, target, copies, taken for each row. A
    document without words is size 0 and takes 0 words; rows repeated whole are drawn as
    separate documents with the same number u; an empty table gives no rows.
    """
    own = F.coalesce(weight.cast("double"), F.lit(1.0)) if isinstance(weight, Column) else F.lit(1.0)
    sizes = docs.select("doc_id", F.col("source").cast("string").alias("source"), F.xxhash64(whole(F.col("text"))).alias("text_hash"), word_count(F.col("text")).alias("size"), own.alias("own"))
    if callable(weight) and not isinstance(weight, Column):
        sizes = sizes.withColumn("own", weight(F.col("size")).cast("double"))
    sizes = cut(sizes)
    targets = source_targets(sizes, weights, share, most)
    mean = sizes.groupBy("source").agg((F.sum(F.col("own") * F.col("size")) / F.greatest(F.sum("size"), F.lit(1))).alias("mean_own"))
    plan = targets.alias("t").join(mean.alias("m"), F.expr("t.source <=> m.source")).select("t.*", "m.mean_own")
    d = sizes.alias("d").join(plan.alias("p"), F.expr("d.source <=> p.source")).select("d.*", "p.source_size", "p.target", "p.mean_own")

    rate = F.when(F.col("source_size") > 0, F.col("target") / F.col("source_size")).otherwise(F.lit(0.0))
    expected = F.least(F.lit(float(most)), F.when(F.col("mean_own") > 0, F.col("rate") * F.col("own") / F.col("mean_own")).otherwise(F.lit(0.0)))
    d = d.withColumn("rate", rate).withColumn("expected", expected).withColumn("whole", F.floor("expected"))
    d = d.withColumn("p", F.col("expected") - F.col("whole")).withColumn("u", uniform(F.col("doc_id"), seed))
    odds = F.col("u") / (1 - F.col("u"))
    d = d.withColumn("rank", F.when(F.col("p") > 0, odds / (F.col("p") / (1 - F.col("p")))))
    # the step is the rank scaled by the source's own odds into (0, 1): u itself where all weigh the same
    base = F.col("rate") - F.floor("rate")
    z = F.when(F.col("rank").isNotNull(), F.col("rank") * F.when(base > 0, base / (1 - base)).otherwise(F.lit(1.0)))
    d = d.withColumn("step", F.floor(F.lit(float(STEPS)) * z / (1 + z)).cast("int"))

    steps = d.groupBy("source", "step").agg(F.sum("size").alias("words"), F.sum(F.col("size") * F.col("whole")).alias("certain"), F.max("target").alias("target"))
    run = Window.partitionBy("source").orderBy("step").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    steps = steps.withColumn("room", F.col("target") - F.sum("certain").over(Window.partitionBy("source")))
    steps = steps.where("step is not null").withColumn("upto", F.sum("words").over(run))
    last = steps.where("upto >= room").groupBy("source").agg(F.min_by(F.struct("step", F.col("upto") - F.col("words"), "room"), "step").alias("c"))
    last = last.select("source", F.col("c.step").alias("cut_step"), F.col("c.col2").alias("before"), F.col("c.room").alias("room"))
    d = d.alias("d").join(last.alias("l"), F.expr("d.source <=> l.source"), "left").select("d.*", "l.cut_step", "l.before", "l.room")

    inner = Window.partitionBy("source").orderBy("rank", "doc_id", "size").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    at_cut = d.where("step = cut_step").withColumn("upto", F.col("before") + F.sum("size").over(inner))
    at_cut = at_cut.withColumn("extra", (F.col("upto") - F.col("size") / F.lit(2.0) <= F.col("room")).cast("int"))
    others = d.where("step is null or cut_step is null or step <> cut_step")
    others = others.withColumn("extra", F.when(F.col("step").isNotNull() & (F.col("cut_step").isNull() | (F.col("step") < F.col("cut_step"))), 1).otherwise(0))
    out = at_cut.drop("upto").unionByName(others)
    copies = (F.col("whole") + F.col("extra")).cast("int")
    return out.select("doc_id", "text_hash", "size", "source", "source_size", "target", copies.alias("copies"), (F.col("size") * copies).cast("long").alias("taken"))


SQL = """
WITH d AS (
  SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+'))::BIGINT AS size FROM documents
), s AS (
  SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source
), w AS (
  SELECT *, [5e0, 2e0, 1e0][((row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3 + 1)::INT] AS weight, 2e0 * source_size AS most FROM s
), l AS (
  SELECT *, (1.5e0 * (SELECT sum(source_size) FROM s)::DOUBLE - coalesce(sum(most) OVER (ORDER BY most / weight, source NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0e0))
    / sum(weight) OVER (ORDER BY most / weight, source NULLS LAST ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level FROM w
), f AS (
  SELECT max(level) AS level FROM l WHERE level * weight <= most
), t AS (
  SELECT l.source, l.source_size, least(l.most, coalesce(f.level * l.weight, l.most)) AS target FROM l, f
), v AS (
  SELECT source, sum((1000 + least(size, 1000)) * size)::DOUBLE / greatest(sum(size), 1)::DOUBLE AS mean FROM d GROUP BY source
), r AS (
  SELECT d.doc_id, d.size, d.source, t.source_size, t.target,
    least(2e0, CASE WHEN v.mean > 0 THEN (CASE WHEN t.source_size > 0 THEN t.target / t.source_size ELSE 0e0 END) * (1000 + least(d.size, 1000))::DOUBLE / v.mean ELSE 0e0 END) AS expected,
    (('0x' || substr(md5(coalesce(d.doc_id::VARCHAR, 'null') || ':17'), 1, 13))::UBIGINT::DOUBLE + 0.5e0) / 4503599627370496e0 AS u
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source JOIN v ON d.source IS NOT DISTINCT FROM v.source
), q AS (
  SELECT *, floor(expected) AS whole, expected - floor(expected) AS p FROM r
), o AS (
  SELECT *, sum(CASE WHEN p > 0 THEN size ELSE 0 END) OVER (PARTITION BY source ORDER BY CASE WHEN p > 0 THEN (u / (1 - u)) / (p / (1 - p)) END NULLS LAST, doc_id, size ROWS UNBOUNDED PRECEDING) AS upto,
    target - (sum(size * whole) OVER (PARTITION BY source)) AS room
  FROM q
)
SELECT doc_id, size, source_size, target, (size * (whole + CASE WHEN p > 0 AND upto - size / 2e0 <= room THEN 1 ELSE 0 END))::BIGINT AS taken FROM o
"""
