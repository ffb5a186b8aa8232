"""The corpus pipeline, stage by stage, against plain loops; and the registered queries."""

import re
from collections import Counter, defaultdict

import corpus_pipeline
import pytest
from pyspark.sql import functions as F

from density_peaks.llm import near_dedup, quality
from density_peaks.llm.queries import ORACLES, QUERIES

from .conftest import HARD
from .test_corpus_operators import plain_components, plain_quality


def documents(spark, sf):
    return spark.read.parquet(f"{sf}/documents.parquet")


def keyed(df):
    return Counter(tuple(r) for r in df.collect())


def test_stages_follow_the_definitions(spark, sf):
    docs = documents(spark, sf)
    columns = docs.columns
    rows = [(r.doc_id, r.text, r.source) for r in docs.collect()]
    kept = {k[0] for k in plain_quality(rows) if k[-1]}
    stages = dict(corpus_pipeline.STAGES)
    one = stages["quality_rules"](spark, docs, sf)
    assert one.columns == columns and keyed(one) == Counter(tuple(r) for r in docs.collect() if r.doc_id in kept)

    top = {}
    lower = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    for r in one.collect():
        t = (r.text or "").translate(lower)
        top[t] = max(top.get(t, r.doc_id), r.doc_id)
    two = stages["exact_dedup"](spark, one, sf)
    assert two.columns == columns and {r.doc_id for r in two.collect()} == set(top.values())

    own = [(r.doc_id, r.text) for r in two.collect()]
    three = stages["near_dedup"](spark, two, sf)
    assert three.columns == columns and {r.doc_id for r in three.collect()} == {k[0] for k in plain_components(own, 5, 80) if k[-1]}

    four = stages["source_mix"](spark, three, sf)
    size = lambda t: len(re.findall(r"[^\x20\x09-\x0D]+", t or ""))
    had, has, largest = defaultdict(int), defaultdict(int), 0
    for r in three.collect():
        had[r.source] += size(r.text)
        largest = max(largest, size(r.text))
    for r in four.collect():
        has[r.source] += size(r.text)
    assert four.columns == columns and max(Counter(r.doc_id for r in four.collect()).values()) <= 2
    assert abs(sum(has.values()) - 1.5 * sum(had.values())) <= len(had) * largest

    five = stages["packing"](spark, four, sf)
    load = Counter()
    for r in five.collect():
        load[r.sequence_id] += r.length
    assert max(load.values()) <= 2048
    assert Counter(r.doc_id for r in five.where("piece = 0").collect()) == Counter(r.doc_id for r in four.collect())


def test_quality_stage_removes_boilerplate_lines(spark, sf):
    words = lambda k: " ".join(f"t{k}x{j}" for j in range(60))
    foot = "All rights  reserved by the site"
    rows = []
    for k in range(40):  # in source a the line is in 12 of 40 texts, in source b in 5 of 40, without a source in 12 of 40
        rows.append((k, f"{words(k)}\n\n {foot.upper()}\r\nlast line {k}" if k < 12 else words(k), "a"))
        rows.append((100 + k, f"{words(k)}\n{foot}" if k < 5 else words(k), "b"))
        rows.append((200 + k, f"{foot}\n{words(k)}\n{foot}" if k < 12 else words(k), None))
    rows += [(0, rows[0][1], "a"), (0, rows[0][1], "b")]  # a row twice, and its id and text under another source
    docs = spark.createDataFrame([(*r, len(r[1])) for r in rows], "doc_id long, text string, source string, n_chars int")
    want = Counter()
    for i, t, s in rows:
        if s == "a" and i < 12:
            t = f"{words(i)}\n\nlast line {i}"
        if s is None and i < 212:
            t = words(i - 200)
        want[i, t, s, len(t)] += 1
    got = dict(corpus_pipeline.STAGES)["quality_rules"](spark, docs.repartition(3), sf)
    assert got.schema == docs.schema and keyed(got) == want


def test_stages_take_hard_rows_and_none(spark, sf, hard, none):
    docs = hard.withColumnRenamed("source_size", "lang")
    for c in ("kept_id", "kept_own", "kept_mark", "kept_host", "mix_own", "mix_copy", "mix_id", "own", "id", "mark", "at", "copies", "without"):
        docs = docs.withColumn(c, F.lit(f"extra {c}"))
    for name, stage in corpus_pipeline.STAGES:
        out = stage(spark, docs, sf)
        assert stage(spark, docs.limit(0), sf).count() == 0, name
        if name != "packing":
            rows = out.collect()
            assert out.columns == docs.columns and len(rows) <= 2 * len(HARD), name
            assert all(r[c] == f"extra {c}" for r in rows for c in ("kept_id", "mix_own", "own", "copies")), name


def test_run_gives_the_last_stage_and_goes_on_where_it_ended(spark, sf, tmp_path, monkeypatch):
    ran, folder = [], str(tmp_path / "run")

    def counted(name, stage):
        def once(*a):
            ran.append(name)
            if name == "source_mix" and ran.count(name) == 1:
                raise RuntimeError("lost")
            return stage(*a)

        return name, once

    monkeypatch.setattr(corpus_pipeline, "STAGES", [counted(*s) for s in corpus_pipeline.STAGES])
    with pytest.raises(RuntimeError):
        corpus_pipeline.run(spark, sf, folder)
    out = corpus_pipeline.run(spark, sf, folder)
    assert ran == ["quality_rules", "exact_dedup", "near_dedup", "source_mix", "source_mix", "packing"]
    assert sorted(p.name for p in (tmp_path / "run").iterdir()) == ["3-source_mix"]
    assert out.columns == ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"] and out.count() > 0


def test_one_query_an_operator():
    assert [q.split("_")[0] for q in QUERIES] == [f"op{i}" for i in range(1, 11)]
    assert set(ORACLES) <= set(QUERIES) and corpus_pipeline.ORACLE_SQL is None
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "exact_dedup", "near_dedup", "source_mix", "packing"]


def test_large_buckets_meet_in_blocks(spark, monkeypatch):
    import random

    monkeypatch.setattr(near_dedup, "SMALL", 1)
    monkeypatch.setattr(near_dedup, "BLOCK", 4)
    rng = random.Random(2)
    words = ["z%d" % i for i in range(3000)]
    base, rows = rng.choices(words, k=150), []
    for i in range(80):
        w = list(base)
        for _ in range(rng.choice([0, 2, 6, 9, 12])):
            w[rng.randrange(len(w))] = rng.choice(words)
        rows.append((i, " ".join(w)))
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = Counter((r.doc_id, r.n_shingles, r.component_id, r.kept) for r in near_dedup.near_duplicates(df).collect())
    assert got == plain_components(rows, 4, 80)


def test_limits_of_lines_are_by_host():
    assert (quality.LINE_DOCS, quality.LINE_SHARE_PERCENT) == (10, 5)
