"""Token counts of a byte-level BPE with a whole-token shortcut.

Before the job, every vocabulary string is encoded alone on the driver; those that give
one token are the proved set, which is broadcast: it is no larger than the vocabulary. A
pre-token of that set counts as one token without any merging. Other pre-tokens are merged
by the library, once for each distinct one that a worker meets. The pattern is the
byte-level pre-tokenizer's. A text with characters for which two Unicode tables may differ,
or with a special string, goes to the library whole, and so do all texts where the file has
another normaliser or pre-tokenizer.
"""

from __future__ import annotations

import json
import os
from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from density_peaks.llm.common import encoded

#: Distinct pre-tokens that a worker remembers before it starts anew.
REMEMBERED = 600_000
SCHEMA = "doc_id long, n_bytes long, n_tokens long"

#: Fixed value: the byte-level pre-tokenizer's pattern, with its white space spelled out.
PRE_TOKEN = regex.compile(
    r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\p{White_Space}\p{L}\p{N}]+|\p{White_Space}+(?!\P{White_Space})|\p{White_Space}+"
)
# Fixed value: the pre-tokenizer that splits by that pattern; such a file has no normaliser.
BYTE_LEVEL = {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": True}
#: Latin, Greek, Cyrillic and common punctuation, assigned for many Unicode versions.
SETTLED = regex.compile(r"[\t\n\r\x20-~\xA0-˿Α-ΡΣ-ώЀ-ҁ‐-‧‰-⁞€]*")

_READY: dict[str, TokenCounter] = {}


class TokenCounter:
    """Counts tokens with one vocabulary file; lives as long as its worker."""

    def __init__(self, path: str, single: set[str] | None = None):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_padding()
        self.library.no_truncation()
        spec = json.loads(self.library.to_str())
        self.by_pattern = not spec["normalizer"] and spec["pre_tokenizer"] is not None and spec["pre_tokenizer"] | {"trim_offsets": True} == BYTE_LEVEL
        self.special = [t.content for t in self.library.get_added_tokens_decoder().values()]
        self.single = single if single is not None else self.whole_tokens() if self.by_pattern else set()
        self.known: dict[str, int] = dict.fromkeys(self.single, 1)

    def whole_tokens(self) -> set[str]:
        """Vocabulary strings that, alone, are one pre-token and encode as exactly one token."""
        from tokenizers import decoders

        plain = decoders.ByteLevel()
        words = [plain.decode([t]) for t in self.library.get_vocab(with_added_tokens=False)]
        words = [w for w in words if w and "�" not in w and SETTLED.fullmatch(w) and PRE_TOKEN.fullmatch(w)]
        return {w for w, e in zip(words, self.library.encode_batch_fast(words, add_special_tokens=False), strict=True) if len(e) == 1}

    def count(self, text: str) -> int:
        if not self.by_pattern or not SETTLED.fullmatch(text) or any(s in text for s in self.special):
            return len(self.library.encode(text, add_special_tokens=False))
        parts = PRE_TOKEN.findall(text)
        known = self.known
        try:
            return sum(map(known.__getitem__, parts))
        except KeyError:
            self.learn(set(parts))
            return sum(map(self.known.__getitem__, parts))

    def learn(self, parts: set[str]) -> None:
        """Makes all of parts known; starts anew where too many are remembered."""
        if len(self.known) > REMEMBERED:
            self.known = dict.fromkeys(self.single, 1)
        words = [p for p in parts if p not in self.known]
        for w, e in zip(words, self.library.encode_batch_fast(words, add_special_tokens=False), strict=True):
            self.known[w] = len(e)


def counter(path: str, single: set[str] | None = None) -> TokenCounter:
    if path not in _READY:
        _READY[path] = TokenCounter(path, single)
    return _READY[path]


def token_counts(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_bytes and n_tokens of each row's whole text, without special tokens added.

    docs needs doc_id and text; other columns are ignored. A null text counts as empty, with
    0 tokens; a null doc_id stays null; repeated rows are counted each; no rows give none.
    """
    proved = docs.sparkSession.sparkContext.broadcast(counter(path).single)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = counter(path, proved.value)
        for b in batches:
            texts = encoded(b.column("text"))
            counts = [own.count(t.decode("utf-8", "replace")) for t in texts]
            yield pa.RecordBatch.from_arrays([b.column("doc_id").cast(pa.int64()), pa.array(map(len, texts), pa.int64()), pa.array(counts, pa.int64())], names=["doc_id", "n_bytes", "n_tokens"])

    return docs.select("doc_id", "text").mapInArrow(run, SCHEMA)
