"""Secret scans: an Aho-Corasick keyword prefilter, anchored expressions near hits, checksums.

One automaton pass over a text finds all keywords. Only where a keyword ends is an
expression tried, anchored at the keyword's start. Tokens that carry their own checksum
(a CRC-32 in six base-62 digits at their end) count only if it agrees. Runs of hex digits
have no keyword; they are found by their character class.
"""

from __future__ import annotations

import hashlib
import re
import zlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from density_peaks.llm.common import encoded

# Kinds, keywords and patterns.
KINDS = ("assign", "access", "hex", "token")
ASSIGN_WORDS = ("password", "passwd", "secret", "token", "apikey", "api_key")
ASSIGN = re.compile(r"""(?:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{32,}")
#: Prefixes of tokens whose last six characters are the base-62 CRC-32 of the thirty before.
TOKEN_WORDS = ("ghp_", "gho_", "ghu_", "ghs_", "ghr_", "npm_")
TOKEN = re.compile(r"(?:gh[pousr]|npm)_([A-Za-z0-9]{30})([A-Za-z0-9]{6})(?![A-Za-z0-9_])")
BASE62 = "0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"

SCHEMA = "doc_id long, n_assign long, n_access long, n_hex long, n_token long, base_sha256 string, spans string"
_HEX_CLASS = bytes(49 if c in b"0123456789abcdef" else 48 for c in range(256))
_RUN = b"1" * 32


def checksum(body: str) -> str:
    """Six base-62 digits of the CRC-32 of a token's body."""
    n, out = zlib.crc32(body.encode()), ""
    for _ in range(6):
        n, r = divmod(n, 62)
        out = BASE62[r] + out
    return out


def automaton():
    import ahocorasick

    a = ahocorasick.Automaton()
    for word in ASSIGN_WORDS:
        a.add_word(word, ("assign", len(word)))
    a.add_word("akia", ("access", 4))
    for word in TOKEN_WORDS:
        a.add_word(word, ("token", len(word)))
    a.make_automaton()
    return a


def find(text: str, keywords) -> list[tuple[int, int, int]]:
    """Spans (start, kind, end) of a text in code points, by start, then kind."""
    raw = text.encode()
    low = raw.lower().decode() if not text.isascii() else text.lower()
    found: list[tuple[int, int, int]] = []
    done = {"assign": 0, "access": 0, "token": 0}
    for last, (kind, size) in keywords.iter(low):
        start = last - size + 1
        if start < done[kind]:
            continue
        if kind == "assign":
            if m := ASSIGN.match(text, start):
                done[kind] = m.end()
                if len(m[1]) >= 8:
                    found.append((start, 0, m.end()))
        elif kind == "access":
            if m := ACCESS.match(text, start):
                done[kind] = m.end()
                if m.end() - start >= 16:
                    found.append((start, 1, m.end()))
        elif m := TOKEN.match(text, start):
            done[kind] = m.end()
            if checksum(m[1]) == m[2]:
                found.append((start, 3, m.end()))
    if _RUN in raw.translate(_HEX_CLASS):
        found += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(found)


def joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


def secret_spans(docs: DataFrame) -> DataFrame:
    """Secrets in each row's whole text.

    docs needs doc_id and text; other columns are ignored. Returns doc_id, the number of
    spans of each kind, base_sha256 over the spans of the first three kinds, and spans,
    all of them. Positions are code points, end exclusive. A null text counts as empty and
    has none; a null doc_id stays null; repeated rows are scanned each; no rows give none.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keywords = automaton()
        for b in batches:
            counts: list[list[int]] = [[], [], [], []]
            shas, spans = [], []
            for t in encoded(b.column("text")):
                found = find(t.decode("utf-8", "replace"), keywords)
                for k, c in enumerate(counts):
                    c.append(sum(x[1] == k for x in found))
                shas.append(hashlib.sha256(joined([x for x in found if x[1] < 3]).encode()).hexdigest())
                spans.append(joined(found))
            columns = [b.column("doc_id").cast(pa.int64()), *(pa.array(c, pa.int64()) for c in counts), pa.array(shas, pa.string()), pa.array(spans, pa.string())]
            yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "n_assign", "n_access", "n_hex", "n_token", "base_sha256", "spans"])

    return docs.select("doc_id", "text").mapInArrow(run, SCHEMA)


def redact(text: str, spans: str, mask: str = "[secret]") -> str:
    """A text with its spans masked; overlapping spans are masked once."""
    out, at = [], 0
    for start, end in sorted((int(x.split(":")[1]), int(x.split(":")[2])) for x in spans.split(",") if x):
        if end <= at:
            continue
        if start >= at:
            out += [text[at:start], mask]
        at = end
    return "".join(out) + text[at:]
