"""Operators that compare documents with each other, against plain loops over small tables."""

import hashlib
import random
from collections import Counter, defaultdict

import numpy as np
import pytest

from density_peaks.llm import near_dedup, quality, substring_dedup, warc
from density_peaks.llm.common import Words

from .conftest import HARD

WS = b" \t\n\r\x0b\x0c"


def plain_removed(rows, window):
    """rows: (doc_id, text), each once; words and kept words by the definition."""
    seen, out = {}, {}
    for i, t in sorted(rows, key=lambda r: (r[0] is not None, r[0] or 0)):
        w = (t or "").encode().split()
        gone = set()
        for k in range(len(w) - window + 1):
            s = b" ".join(w[k : k + window])
            if s in seen:
                gone.update(range(k, k + window))
            else:
                seen[s] = (i, k)
        out[i] = (len(w), len(gone), b" ".join(x for k, x in enumerate(w) if k not in gone).decode())
    return out


def corpus(seed=3, n=120):
    rng = random.Random(seed)
    words = ["w%d" % i for i in range(40)] + ["…", "ünï", "\x1c", "a,b"]
    passage = " ".join(rng.choices(words, k=60))
    line = " ".join(rng.choices(words, k=12))
    out = []
    for i in range(n):
        body = rng.choices(words, k=rng.choice([0, 5, 19, 20, 21, 60, 400]))
        text = " ".join(body)
        if i % 3 == 0:
            text = passage + rng.choice([" ", "\n\n", "\t"]) + text
        if i % 4 == 0:
            text = text + " \n" + line + "\n " + line
        out.append((i, text))
    return out + [(n, out[0][1]), (n + 1, out[0][1] * 3), (n + 2, None), (n + 3, "same " * 300)]


@pytest.mark.parametrize("parts,hot,portion", [(None, 1.0, 4_000_000), (3, 1.0, 500), (7, 0.0, 2_000)])
def test_substring_dedup(spark, monkeypatch, parts, hot, portion):
    monkeypatch.setattr(substring_dedup, "PORTION", portion)
    if not hot:  # every minimiser is hot: all windows travel alone
        real = substring_dedup.super_kmers
        monkeypatch.setattr(substring_dedup, "super_kmers", lambda d, w, g, p, h: real(d, w, g, p, np.ones_like(h)))
    rows = corpus()
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    got = {r.doc_id: (r.n_words, r.n_removed, r.kept_text) for r in substring_dedup.substring_dedup(df, parts=parts).collect()}
    assert got == plain_removed(rows, 20)


def test_substring_dedup_hard(spark, hard, none):
    got = Counter((r.doc_id, r.n_words) for r in substring_dedup.substring_dedup(hard).collect())
    assert got == Counter((i, len((t or "").encode().split())) for i, t, _ in HARD)
    by = {r.doc_id: r for r in substring_dedup.substring_dedup(hard).collect()}
    assert by[3].n_removed == 120 - 3 and by[8].n_removed == 6000 - 1 and by[2].kept_text == ""
    assert substring_dedup.substring_dedup(none).count() == 0


def test_windows_with_equal_hashes(monkeypatch):
    monkeypatch.setattr(substring_dedup, "window_hashes", lambda codes, window: np.zeros(len(codes) - window + 1, dtype=np.uint64))
    codes = np.array([1, 2, 3, 1, 2, 9, 1, 2, 3])
    later, first = substring_dedup.repeated_windows(codes, np.arange(7), 3)
    assert dict(zip(later.tolist(), first.tolist(), strict=True)) == {6: 0}


def test_words_split_as_bytes_do():
    texts = [t.encode() for t in ("", " a", "b  c\t", "\x0b\x0c", "é\x1cx  y", "w" * 200)]
    w = Words(texts)
    for i, t in enumerate(texts):
        assert [w.data[a:b] for a, b in zip(w.start[w.first[i] : w.first[i + 1]], w.end[w.first[i] : w.first[i + 1]], strict=True)] == t.split()
    assert len(set(Words([b"ab ba a b aa w" + b"w" * 70 + b" " + b"w" * 72]).hash.tolist())) == 7


def plain_quality(rows):
    lines, hosts = defaultdict(set), defaultdict(set)
    norm = lambda x: b" ".join(x.split()).lower()
    for _, t, h in rows:
        t = (t or "").encode()
        hosts[h].add(t)
        for x in t.split(b"\n"):
            if x.split():
                lines[h, norm(x)].add(t)
    out = Counter()
    for i, t, h in rows:
        t = (t or "").encode()
        w = t.split()
        own = [x for x in t.split(b"\n") if x.split()]
        windows = Counter(tuple(w[k : k + 3]) for k in range(len(w) - 2))
        inside = {k + j for k in range(len(w) - 2) if windows[tuple(w[k : k + 3])] > 1 for j in range(3)}
        gone = sum(len(x.split()) for x in own if (n := len(lines[h, norm(x)])) > 10 and 100 * n > 5 * len(hosts[h]))
        failed = len(w) < 50 or 100 * len(inside) > 50 * len(w)
        out[i, len(w), sum(len(x.decode()) for x in w), sum(t.count(c.encode()) for c in "#*$%&|<>"), len(own) - len(set(own)), len(inside), gone, failed, not failed and 2 * gone <= len(w)] += 1
    return out


def test_quality(spark, hard, none):
    rng = random.Random(9)
    words = ["v%d" % i for i in range(300)] + ["#x", "<b>", "é…"]
    shared = " ".join(rng.choices(words, k=40))
    rows = [(i, "\n".join([" ".join(rng.choices(words, k=rng.choice([10, 45, 70])))] + ([shared.upper(), "  " + shared] if i % 5 == 0 else [])), rng.choice(["a", "b", None, "\x00"])) for i in range(200)]
    rows += [(200 + i, rows[1][1], "a") for i in range(40)]  # copies of one text count once
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(4)
    columns = ["doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_removed_words", "base_failed", "kept"]
    got = Counter(tuple(r) for r in quality.judge(df).select(columns).collect())
    assert got == plain_quality(rows)
    assert any(not k[-1] and not k[-2] for k in got)
    assert Counter(tuple(r) for r in quality.judge(hard).select(columns).collect()) == plain_quality(HARD)
    assert quality.judge(none).count() == 0


def plain_components(rows, size, percent):
    sets = []
    for _, t in rows:
        w = (t or "").encode().lower().split()
        sets.append({tuple(w[k : k + size]) for k in range(len(w) - size + 1)} if len(w) >= size else ({tuple(w)} if w else set()))
    up = list(range(len(rows)))

    def root(x):
        while up[x] != x:
            x = up[x]
        return x

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                up[root(a)] = root(b)
    least = {}
    for x, (i, _) in enumerate(rows):
        r = root(x)
        ids = [j for j in (least.get(r), i) if j is not None]
        least[r] = min(ids, default=None)
    return Counter((i, len(sets[x]), least[root(x)], i == least[root(x)]) for x, (i, _) in enumerate(rows))


@pytest.mark.parametrize("size", [4, 5])
def test_near_duplicates(spark, size):
    rng = random.Random(size)
    words = ["u%d" % i for i in range(2000)]
    rows = []
    for _ in range(40):
        base = rng.choices(words, k=rng.choice([3, 30, 120, 400]))
        for _ in range(rng.choice([1, 2, 6])):
            w = list(base)
            for _ in range(rng.choice([0, 1, 2, 5])):
                w[rng.randrange(len(w))] = rng.choice(words)
            rows.append(" ".join(w))
    chain = rng.choices(words, k=100)  # each step is near, the ends are not
    for k in range(30):
        chain = [*chain[4:], *rng.choices(words, k=4)]
        rows.append(" ".join(chain))
    rng.shuffle(rows)
    rows = [(i, t.upper() if i % 7 == 0 else t) for i, t in enumerate(rows)] + [(900, None), (901, " "), (902, "a b"), (903, "A b")]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(3)
    got = Counter((r.doc_id, r.n_shingles, r.component_id, r.kept) for r in near_dedup.near_duplicates(df, size).collect())
    assert got == plain_components(rows, size, 80)


def test_near_duplicates_hard(spark, hard, none):
    got = Counter((r.doc_id, r.n_shingles) for r in near_dedup.near_duplicates(hard).collect())
    assert sum(got.values()) == len(HARD) and got[10, 1] == 2 and got[0, 0] == 1
    by = {(r.doc_id, r.text_hash): r for r in near_dedup.near_duplicates(hard).collect()}
    assert {r.component_id for r in by.values() if r.doc_id in (3, 4, 5)} == {3}
    assert near_dedup.near_duplicates(none).count() == 0


def test_fewest_matches_bound():
    need = near_dedup.fewest_matches()
    assert list(need) == [30, 60, 90, 120, 150]
    assert all(need[n] / n < 0.8 for n in need) and need[150] / 150 > need[30] / 30


def pages(spark, rows):
    return spark.createDataFrame(rows, "page_id long, url string, html string, offset long, body string")


def test_warc_round_trip(spark, tmp_path):
    big = "<p>" + "x" * 2000 + "</p>"
    fake = f"head {warc.MAGIC}WARC-Type: response\r\nContent-Length: 5\r\n\r\nhello\r\n\r\n tail {warc.MAGIC}WARC-Type: response\r\nX-Page-ID: 77\r\nContent-Length: 3\r\n\r\nabc\r\n\r\n" + "y" * 1500
    rows = [(1, "http://a", big), (2, "http://b", big), (5, None, big), (3, "http://c\r\nEvil: 1", "short"), (4, "u", "short"), (6, "u", None), (7, "u", ""), (8, "u", fake), (9, "u", fake), (10, "u", warc.MAGIC * 3), (11, "u", "é漢\r\n\r\n" * 300), (None, "u", "null id"), (12, "u", "z"), (12, "u", "z")]
    rows = [(*r, 1, "x") for r in rows]
    top = {}
    for i, _, h, *_ in rows:
        if h and len(h.encode()) >= 1000:
            top[h] = max(top.get(h, i), i)
    want = Counter()
    for i, _, h, *_ in rows:
        p = (h or "").encode()
        again = h in top and top[h] != i
        want[i, len(p), hashlib.sha1(p).hexdigest(), "revisit" if again else "response", top[h] if again else None] += 1
    got = warc.round_trip(pages(spark, rows).repartition(2), str(tmp_path / "w"))
    assert Counter(tuple(r) for r in got.collect()) == want
    found = warc.read_archives(spark, str(tmp_path / "w"))
    bodies = sorted(bytes(r.payload) for r in found.collect())
    assert bodies == sorted((h or "").encode() if not (h in top and top[h] != i) else b"" for i, _, h, *_ in rows)


def test_warc_over_many_splits(spark, tmp_path, monkeypatch):
    fake = warc.MAGIC + "Content-Length: 9\r\n\r\n"
    rows = [(i, f"http://p/{i}", (fake if i % 3 == 0 else "") + "text %d " % i * (i % 50 + 1) + (fake if i % 5 == 0 else ""), 0, "") for i in range(300)]
    before = spark.conf.get("spark.sql.files.maxPartitionBytes")
    try:
        warc.write_archives(pages(spark, rows).coalesce(1), str(tmp_path / "w"))
        monkeypatch.setattr(warc, "LEAST_SPLIT", 4096)
        monkeypatch.setattr(warc, "MOST_SPLIT", 4096)
        spark.conf.set("spark.sql.files.maxPartitionBytes", "70000")  # the splits are warc's own
        got = warc.described(warc.read_archives(spark, str(tmp_path / "w"))).collect()
    finally:
        spark.conf.set("spark.sql.files.maxPartitionBytes", before)
    assert Counter((r.page_id, r.payload_bytes, r.payload_digest) for r in got) == Counter((i, len(h.encode()), hashlib.sha1(h.encode()).hexdigest()) for i, _, h, *_ in rows)


def test_warc_empty(spark, tmp_path):
    assert warc.round_trip(pages(spark, []), str(tmp_path / "w")).count() == 0
