"""Best-fit packing of token sequences by a grouping genetic algorithm on islands.

A document's ids are cut into pieces only where it is longer than a sequence; only the
lengths of pieces are packed. Pieces are dealt into blocks of bounded size by a hash.
Each block is an instance of its own that several islands work on. An island starts from
randomised fits; its generations cross them: whole well-filled bins of one parent go into
the other, the bins that hold the same pieces are removed, and the pieces so displaced are
put back by best fit, the longest first. After each epoch an island's best solution
migrates to its neighbour. A block whose solution meets the bound of its total length is
done. Bins that remain poorly filled are opened again and packed together in a last round,
so that blocks cost no sequences.
"""

from __future__ import annotations

import json
import os
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from density_peaks.llm.common import Words, cut, encoded, portions, released

#: Tokens of a sequence; the id that ends a document; pieces of a block.
SEQUENCE, END, BLOCK = 2048, 0, 4096
#: Islands of a block, epochs between which elites migrate, solutions of an island, those it keeps from epoch to epoch, and generations of an epoch.
ISLANDS, EPOCHS, POPULATION, KEPT, GENERATIONS = 3, 3, 10, 4, 24
#: Words that a worker remembers before it starts anew, and words that the library is given at once.
REMEMBERED, AT_ONCE = 600_000, 4000
#: ASCII punctuation that, after letters, is a pre-token of its own; the apostrophe is not, as it may begin one with letters.
MARKS = "!\"#$%&()*+,-./:;<=>?@[\\]^_`{|}~"
#: Letters whose lower case is one letter in every Unicode version.
LETTERS = re.compile("[A-Za-zÀ-ÖØ-öø-ÿ]+")

# The normaliser and the pre-tokenizer under which words between white space have ids of their own.
BY_WORDS = {
    "normalizer": {"type": "Sequence", "normalizers": [{"type": "NFC"}, {"type": "Replace", "pattern": {"Regex": "\\s+"}, "content": " "}, {"type": "Lowercase"}]},
    "pre_tokenizer": {
        "type": "Sequence",
        "pretokenizers": [
            {"type": "Split", "pattern": {"Regex": "'s|'t|'re|'ve|'m|'ll|'d|[\\p{L}]+|[\\p{N}]|[^\\s\\p{L}\\p{N}]+"}, "behavior": "Removed", "invert": True},
            {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": False},
        ],
    },
}

PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"
STATE = "block long, island int, items array<long>, lengths array<int>, least long, bins long, generations long, migrants long, solutions array<int>"
_READY: dict[str, WordIds] = {}


class WordIds:
    """Ids of texts, word by word with what a worker remembers of words by their hashes.

    The file's own normaliser and pre-tokenizer say whether words between white space have
    the same ids everywhere; where they do not, or the vocabulary does not mark the ends of
    words, the library encodes whole texts. A word is split off at ASCII white space; what
    is not letters and then punctuation is encoded by the library as it stands.
    """

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.library.no_padding()
        self.library.no_truncation()
        spec = json.loads(self.library.to_str())
        suffix = spec["model"].get("end_of_word_suffix")
        self.by_words = bool(suffix) and all(spec[k] == v for k, v in BY_WORDS.items()) and spec["post_processor"] is None
        vocab = self.library.get_vocab(with_added_tokens=True)
        self.ends = np.zeros(max(vocab.values()) + 1, dtype=bool)
        self.ends[[i for t, i in vocab.items() if suffix and t.endswith(suffix)]] = True
        self.forget()

    def forget(self) -> None:
        """Slots are runs of the pool of ids; words (by hash) and their parts (by text) have one each."""
        self.slot: dict[int, int] = {}
        self.part: dict[str, int] = {}
        self.pool = np.empty(0, dtype="<u4")
        self.begin, self.size = np.empty(0, dtype=np.int64), np.empty(0, dtype=np.int64)
        self.check = np.empty(0, dtype=np.uint64)

    def ids(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """The ids of all texts in one array, END after each text, and how many each text has."""
        if not self.by_words:
            return self.joined([self.whole(t) for t in texts])
        if len(self.slot) > REMEMBERED:
            self.forget()
        words = Words(texts, check=True)
        each, at, own = np.unique(words.hash, return_index=True, return_inverse=True)
        slots = np.array([self.slot.get(h, -1) for h in each.tolist()], dtype=np.int64)
        if len(fresh := np.flatnonzero(slots < 0)):
            slots[fresh] = self.learn(words, at[fresh], each[fresh])
        slots = slots[own]
        other = np.flatnonzero(self.check[slots] != words.check)
        if len(other):  # words of equal hash: such texts are encoded whole
            hit = set((np.searchsorted(words.first, other, side="right") - 1).tolist())
            flat, many = self.gathered(slots, words.first)
            rest = np.split(flat, np.cumsum(many)[:-1])
            return self.joined([self.whole(t) if d in hit else r for d, (t, r) in enumerate(zip(texts, rest, strict=True))])
        return self.ended(*self.gathered(slots, words.first))

    def gathered(self, slots: np.ndarray, first: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The ids of words in turn, and how many the words of each text have."""
        size = self.size[slots]
        upto = np.concatenate(([0], np.cumsum(size)))
        return self.pool[np.repeat(self.begin[slots] - upto[:-1], size) + np.arange(upto[-1])], np.diff(upto[first])

    @staticmethod
    def ended(flat: np.ndarray, many: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        out = np.empty(len(flat) + len(many), dtype="<u4")
        inner = np.ones(len(out), dtype=bool)
        inner[np.cumsum(many + 1) - 1] = False
        out[inner], out[~inner] = flat, END
        return out, many + 1

    def joined(self, parts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
        many = np.array([len(p) for p in parts], dtype=np.int64)
        return self.ended(np.concatenate([np.empty(0, dtype="<u4"), *parts]), many)

    def whole(self, text: bytes) -> np.ndarray:
        return np.array(self.library.encode(text.decode("utf-8", "replace"), add_special_tokens=False).ids, dtype="<u4")

    def add(self, ids: np.ndarray, size: np.ndarray) -> np.ndarray:
        """New slots for runs of ids."""
        at = np.arange(len(self.size), len(self.size) + len(size))
        self.begin = np.concatenate((self.begin, len(self.pool) + np.cumsum(size) - size))
        self.size, self.pool = np.concatenate((self.size, size)), np.concatenate((self.pool, ids))
        self.check = np.concatenate((self.check, np.zeros(len(size), dtype=np.uint64)))
        return at

    def learn(self, words: Words, at: np.ndarray, hashes: np.ndarray) -> np.ndarray:
        """Slots of new words, given one place and the hash of each."""
        stems, tails, fresh, odd = [], [], {}, {}
        for a, b in zip(words.start[at].tolist(), words.end[at].tolist(), strict=True):
            w = words.data[a:b].decode("utf-8", "replace")
            stem = w.rstrip(MARKS)
            tail = ""
            if LETTERS.fullmatch(stem):
                tail, stem = w[len(stem) :], stem.lower()
                if stem not in self.part:
                    fresh[stem] = True
            else:
                stem = w
                if w not in self.part:
                    odd[w] = True
            if tail not in self.part:
                odd[tail] = True
            stems.append(stem)
            tails.append(tail)
        todo = list(fresh)
        for lo in range(0, len(todo), AT_ONCE):
            self.several(todo[lo : lo + AT_ONCE])
        self.each(list(odd))
        one, two = (np.array([self.part[x] for x in v], dtype=np.int64) for v in (stems, tails))
        flat, many = self.gathered(np.stack((one, two), axis=1).ravel(), np.arange(0, 2 * len(one) + 1, 2))
        slots = self.add(flat, many)
        self.check[slots] = words.check[at]
        self.slot.update(zip(hashes.tolist(), slots.tolist(), strict=True))
        return slots

    def several(self, parts: list[str]) -> None:
        """Learns words of letters only, each one pre-token, from one text: the last token of each is marked."""
        ids = np.array(self.library.encode_batch_fast([" ".join(parts)], add_special_tokens=False)[0].ids, dtype="<u4")
        last = np.flatnonzero(self.ends[ids]) + 1
        if len(last) != len(parts) or last[-1] != len(ids):
            return self.each(parts)
        self.part.update(zip(parts, self.add(ids, np.diff(last, prepend=0)).tolist(), strict=True))

    def each(self, parts: list[str]) -> None:
        found = [np.array(e.ids, dtype="<u4") for e in self.library.encode_batch_fast(parts, add_special_tokens=False)]
        size = np.array([len(x) for x in found], dtype=np.int64)
        self.part.update(zip(parts, self.add(np.concatenate([np.empty(0, dtype="<u4"), *found]), size).tolist(), strict=True))


def word_ids(path: str) -> WordIds:
    """The worker's own WordIds of a file; it outlives tasks, as this module's table is not sent with them."""
    if path not in _READY:
        _READY[path] = WordIds(path)
    return _READY[path]


def pieces(docs: DataFrame, path: str, most: int = SEQUENCE) -> DataFrame:
    """The pieces of each row's ids with the end id: doc_id, piece, start, length, ids_crc32."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = word_ids(path)
        for b in released(batches):
            docs_, texts = b.column("doc_id").cast(pa.int64()), encoded(b.column("text"))
            for lo, hi in portions(texts, 2_000_000):
                ids, many = own.ids(texts[lo:hi])
                cuts = -(-many // most)
                doc = np.repeat(np.arange(lo, hi), cuts)
                piece = np.arange(len(doc)) - np.repeat(np.cumsum(cuts) - cuts, cuts)
                start = piece * most
                length = np.minimum(np.repeat(many, cuts) - start, most)
                raw, ends = memoryview(ids).cast("B"), 4 * np.cumsum(length)
                crc = [zlib.crc32(raw[e - n : e]) for e, n in zip(ends.tolist(), (4 * length).tolist(), strict=True)]
                columns = [docs_.take(pa.array(doc)), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64())]
                yield pa.RecordBatch.from_arrays(columns, names=["doc_id", "piece", "start", "length", "ids_crc32"])

    return docs.select("doc_id", "text").mapInArrow(run, PIECES)


class Packing:
    """A solution: the bin of each item, and how much each bin holds."""

    def __init__(self, label: np.ndarray, load: np.ndarray):
        self.label, self.load = label, load

    def __len__(self) -> int:
        return len(self.load)

    @classmethod
    def of(cls, label: np.ndarray, length: np.ndarray) -> Packing:
        return cls(label.astype(np.int64), np.bincount(label, weights=length).astype(np.int64))

    def rank(self, most: int) -> tuple[int, float]:
        """Greater is better: fewer bins, then the mean square of how full they are."""
        return -len(self), float(np.mean((self.load / most) ** 2)) if len(self) else 0.0


def best_fit(order: np.ndarray, length: np.ndarray, label: np.ndarray, load: np.ndarray, most: int) -> Packing:
    """Adds items in the given order, each to the fullest bin that has room for it.

    Bins of equal room are stacked; one long integer has a bit for each room that any bin
    has, so the least sufficient room is its lowest bit from the item's size on.
    """
    stacks: list[list[int]] = [[] for _ in range(most + 1)]
    fill = load.tolist()
    for b, x in enumerate(fill):
        stacks[most - x].append(b)
    rooms = sum(1 << r for r, s in enumerate(stacks) if s)
    seats = []
    for size in length[order].tolist():
        fits = rooms >> size
        if fits:
            room = size + (fits & -fits).bit_length() - 1
            stack = stacks[room]
            b = stack.pop()
            if not stack:
                rooms ^= 1 << room
        else:
            room, b = most, len(fill)
            fill.append(0)
        seats.append(b)
        fill[b] += size
        room -= size
        if not stacks[room]:
            rooms |= 1 << room
        stacks[room].append(b)
    label[order] = seats
    return Packing(label, np.array(fill, dtype=np.int64))


def fitted(order: np.ndarray, length: np.ndarray, most: int) -> Packing:
    """Best fit of all items in an order."""
    return best_fit(order, length, np.empty(len(length), dtype=np.int64), np.empty(0, dtype=np.int64), most)


def falling(length: np.ndarray) -> np.ndarray:
    return np.argsort(-length, kind="stable")


def crossover(one: Packing, other: Packing, length: np.ndarray, most: int, rng: np.random.Generator) -> Packing:
    """Whole well-filled bins of other go into one; what they displace is put back by best fit."""
    good = np.flatnonzero(other.load >= np.median(other.load))
    given = np.zeros(len(other), dtype=bool)
    given[rng.choice(good, size=max(1, len(good) // 3), replace=False)] = True
    inside = given[other.label]
    hit = np.zeros(len(one), dtype=bool)
    hit[one.label[inside]] = True
    gone = np.flatnonzero(hit[one.label] & ~inside)
    kept = int((~hit).sum())
    label = np.where(inside, kept + (np.cumsum(given) - 1)[other.label], (np.cumsum(~hit) - 1)[one.label])
    return best_fit(gone[falling(length[gone])], length, label, np.concatenate((one.load[~hit], other.load[given])), most)


def mutate(one: Packing, length: np.ndarray, most: int, rng: np.random.Generator) -> Packing:
    """Opens the emptiest bins and a few others and packs their items again, longest first but for a little noise."""
    n = max(1, len(one) // 20)
    opened = np.zeros(len(one), dtype=bool)
    opened[np.argsort(one.load, kind="stable")[:n]] = True
    opened[rng.integers(0, len(one), n)] = True
    loose = np.flatnonzero(opened[one.label])
    loose = loose[falling(length[loose] * (1 + 0.05 * rng.random(len(loose))))]
    return best_fit(loose, length, (np.cumsum(~opened) - 1)[one.label], one.load[~opened], most)


def bound(length: np.ndarray, most: int) -> int:
    """No packing has fewer bins: total length, or items that pair with none of their kind."""
    return max(-(-int(length.sum()) // most), int((2 * length > most).sum()))


def evolve(length: np.ndarray, most: int, seed: int, people: list[Packing] | None = None, population: int = POPULATION, generations: int = GENERATIONS) -> tuple[list[Packing], int]:
    """An island's solutions, best first, after some generations, and how many these were.

    people: solutions kept from the epoch before and migrants; randomised fits fill up the
    population. Each generation crosses the best with another in both ways, one child is
    mutated too, and the worst give way. Ends early where a solution meets the bound.
    """
    rng, least, people = np.random.default_rng(seed), bound(length, most), list(people or [])
    while len(people) < population:
        # from nearly falling orders to random ones, none of them plain falling best fit
        noise = 0.2 + 2.0 * len(people) / population
        people.append(fitted(falling(length * (1 + noise * rng.random(len(length)))), length, most))
    rank = lambda p: p.rank(most)
    people.sort(key=rank, reverse=True)
    done = 0
    while done < generations and len(people[0]) > least:
        a, b = people[0], people[1 + int(rng.integers(0, max(1, min(len(people) - 1, population // 2))))]
        children = [mutate(crossover(a, b, length, most, rng), length, most, rng), crossover(b, a, length, most, rng)]
        people = sorted([*people[: population - 2], *children], key=rank, reverse=True)
        done += 1
    return people, done


def islands_of(items: DataFrame, islands: int) -> DataFrame:
    """A row an island of each block, its items by number; no solutions yet. items: block, item, length."""
    held = items.groupBy("block").agg(F.array_sort(F.collect_list(F.struct("item", F.col("length").cast("int").alias("length")))).alias("own"))
    island = F.explode(F.sequence(F.lit(0), F.lit(islands - 1))).alias("island")
    none = F.lit(0).cast("long")
    start = held.select("block", island, F.col("own.item").alias("items"), F.col("own.length").alias("lengths"), none.alias("least"), none.alias("bins"), none.alias("generations"), none.alias("migrants"), F.array().cast("array<int>").alias("solutions"))
    return start.repartition("block", "island")


def epoch(state: DataFrame, number: int, most: int) -> DataFrame:
    """All islands of a state after an epoch's generations. Rows are those of STATE, and migrant where one came."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            rows = []
            for r in f.itertuples(index=False):
                length = np.asarray(r.lengths, dtype=np.int64)
                n = len(length)
                people = [Packing.of(s, length) for s in np.asarray(r.solutions, dtype=np.int64).reshape(-1, n)]
                came = getattr(r, "migrant", None)
                if came is not None:
                    people.append(Packing.of(np.asarray(came, dtype=np.int64), length))
                seed = (int(r.block) * 1009 + int(r.island) * 31 + number) & 0x7FFFFFFF
                if number and came is not None:  # a later epoch may do no worse than plain falling best fit
                    people.append(fitted(falling(length), length, most))
                people, done = evolve(length, most, seed, people)
                kept = np.concatenate([p.label for p in people[:KEPT]]).astype(np.int32)
                rows.append((r.block, r.island, r.items, r.lengths, bound(length, most), len(people[0]), r.generations + done, r.migrants + (came is not None), kept))
            yield pd.DataFrame(rows, columns=[c.split()[0] for c in STATE.split(", ")])

    return state.mapInPandas(run, STATE)


def evolved(items: DataFrame, most: int, epochs: int, islands: int) -> DataFrame:
    """The last state of all islands (columns of STATE); the first solution of each is its best."""
    state = cut(epoch(islands_of(items, islands), 0, most))
    for number in range(1, epochs):
        # a block that meets its bound on any island needs no further epoch
        open_ = state.groupBy("block").agg(F.min("bins").alias("best"), F.max("least").alias("bound")).where("best > bound").select("block")
        going = state.join(open_, "block", "left_semi")
        if going.isEmpty():
            break
        onward = ((F.col("island") + 1) % islands).cast("int").alias("island")
        elite = going.select("block", onward, F.slice("solutions", F.lit(1), F.size("items")).alias("migrant"))
        moved = epoch(going.join(elite, ["block", "island"]), number, most)
        state = cut(moved.unionByName(state.join(open_, "block", "left_anti")))
    return state


def solve(items: DataFrame, most: int, epochs: int, islands: int) -> DataFrame:
    """The bin of each item of each block by the best of its islands: block, item, length, bin. items: block, item, length."""
    state = evolved(items, most, epochs, islands)
    best = state.groupBy("block").agg(F.min_by("island", F.struct("bins", "island")).alias("island"))
    chosen = state.join(best, ["block", "island"], "left_semi")
    label = F.slice("solutions", F.lit(1), F.size("items")).alias("bin")
    chosen = chosen.select("block", F.explode(F.arrays_zip("items", "lengths", label)).alias("e"))
    return chosen.select("block", F.col("e.items").alias("item"), F.col("e.lengths").cast("long").alias("length"), F.col("e.bin").cast("long").alias("bin"))


def pack(docs: DataFrame, path: str, most: int = SEQUENCE, islands: int = ISLANDS, epochs: int = EPOCHS) -> DataFrame:
    """Packs all pieces of docs into sequences of at most `most` tokens.

    docs needs doc_id and text; other columns are ignored. path: a tokenizer file. Returns
    per piece doc_id, piece, start, length, ids_crc32, sequence_id, offset. A null or empty
    text is one piece that holds the end id; repeated rows are packed each; a null doc_id
    stays null; no rows give none.
    """
    p = cut(pieces(docs, path, most).withColumn("item", F.monotonically_increasing_id()))
    full, rest = p.where(F.col("length") == most), p.where(F.col("length") < most)
    blocks = max(1, round(rest.count() / BLOCK))
    first = solve(rest.select(F.pmod(F.xxhash64("item"), F.lit(blocks)).alias("block"), "item", "length"), most, epochs, islands)
    first = cut(first.withColumn("sequence_id", F.col("block") * 2 * BLOCK * most + F.col("bin")))
    if blocks > 1:
        # each block leaves about one poor bin: a few thousandths of all pieces, packed once more
        load = first.groupBy("sequence_id").agg(F.sum("length").alias("load"))
        poor = load.where(F.col("load") < most * 0.97).select("sequence_id")
        again = first.join(poor, "sequence_id", "left_semi")
        groups = max(1, round(again.count() / BLOCK))
        second = solve(again.select((-1 - F.pmod(F.xxhash64("item", F.lit(1)), F.lit(groups))).alias("block"), "item", "length"), most, epochs, islands)
        second = second.withColumn("sequence_id", F.col("block") * 2 * BLOCK * most + F.col("bin"))
        first = first.join(poor, "sequence_id", "left_anti").select("item", "length", "sequence_id").unionByName(second.select("item", "length", "sequence_id"))
    seats = first.select("item", "length", "sequence_id")
    # a sequence holds at most `most` pieces, so its window is small
    before = Window.partitionBy("sequence_id").orderBy("item").rowsBetween(Window.unboundedPreceding, -1)
    seats = seats.withColumn("offset", F.coalesce(F.sum("length").over(before), F.lit(0))).select("item", "sequence_id", "offset")
    packed = rest.join(seats, "item")
    alone = full.withColumn("sequence_id", F.lit(1 << 61) + F.col("item")).withColumn("offset", F.lit(0).cast("long"))
    columns = ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]
    return packed.select(columns).unionByName(alone.select(columns))
