"""Minimum-cost-flow resharding: the block transfers that move the fewest bytes.

Documents fall into blocks by a hash of their text within their old shard, so equal texts
share a block. A block that outgrows its limit is split by a second hash of the text; only
a single text that outgrows the limit alone is split by a hash of the id. The driver sees
block sums only, whose number is bounded by parameters. A flow from old shard sizes to new
capacities, free within a shard and costing a byte for each byte moved, says how much goes
where; whole blocks then fill these flows. A row's new shard follows from its own columns
and these small tables, so its text is shuffled once, when affected shards are rewritten.
"""

from __future__ import annotations

import heapq
import math
from collections import defaultdict
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, LongType, StructField, StructType

from density_peaks.llm.common import cut, whole

#: Blocks of each old shard, and how many blocks an even new shard is made of at least.
BLOCKS, GRAIN = 512, 64
#: Most bytes of a part of a block, whatever the shards hold; files of a new shard at least, and most bytes of each.
PART_BYTES, FILES, FILE_BYTES = 4 << 30, 4, 256 << 20


def min_cost_flow(supply: list[int], capacity: list[int], cost) -> dict[tuple[int, int], int]:
    """The cheapest shipment of all supplies into capacities by successive shortest paths.

    cost(i, j) is the price of a unit from i to j. Raises where capacities do not suffice.
    """
    n, m = len(supply), len(capacity)
    if sum(supply) > sum(capacity):
        raise ValueError("the new capacities hold less than the old shards")
    left, room, flow = list(supply), list(capacity), defaultdict(int)
    price = [0.0] * (n + m)
    while any(left):
        dist, back = [math.inf] * (n + m), [-1] * (n + m)
        heap = []
        for i in range(n):
            if left[i]:
                dist[i] = 0.0
                heapq.heappush(heap, (0.0, i))
        while heap:
            d, v = heapq.heappop(heap)
            if d > dist[v]:
                continue
            if v < n:
                edges = [(n + j, cost(v, j)) for j in range(m)]
            else:
                edges = [(i, -cost(i, v - n)) for i in range(n) if flow[i, v - n]]
            for u, c in edges:
                step = d + c + price[v] - price[u]
                if step < dist[u] - 1e-9:
                    dist[u], back[u] = step, v
                    heapq.heappush(heap, (step, u))
        end = min((n + j for j in range(m) if room[j]), key=lambda v: dist[v] + price[v])
        price = [p + min(d, dist[end]) for p, d in zip(price, dist, strict=True)]
        path = [end]
        while back[path[-1]] >= 0:
            path.append(back[path[-1]])
        path.reverse()
        amount = min(left[path[0]], room[end - n])
        for a, b in zip(path, path[1:], strict=False):
            if a >= n:
                amount = min(amount, flow[b, a - n])
        for a, b in zip(path, path[1:], strict=False):
            if a < n:
                flow[a, b - n] += amount
            else:
                flow[b, a - n] -= amount
        left[path[0]] -= amount
        room[end - n] -= amount
    return {k: v for k, v in flow.items() if v}


def place_blocks(blocks: list[tuple], capacity: list[int]) -> dict:
    """Which new shard each block goes to.

    blocks: (key, old shard, bytes). Quotas come from the flow; from the largest block down,
    each goes where its old shard's quota has most left. At last small blocks move from the
    fullest to the emptiest shard while that narrows the spread.
    """
    old = sorted({b[1] for b in blocks})
    at = {s: i for i, s in enumerate(old)}
    supply = [0] * len(old)
    for _, s, size in blocks:
        supply[at[s]] += size
    flow = min_cost_flow(supply, capacity, lambda i, j: 0 if old[i] == j else 1)
    quota = defaultdict(dict)
    for (i, j), v in flow.items():
        quota[i][j] = v
    where, load, members = {}, [0] * len(capacity), defaultdict(list)
    for key, s, size in sorted(blocks, key=lambda b: (-b[2], b[1], b[0])):
        q = quota[at[s]] or {j: 0 for j in range(len(capacity))}
        to = max(q, key=lambda j: (q[j], j == s, -j))
        q[to] = q.get(to, 0) - size
        where[key] = to
        load[to] += size
        members[to].append((size, key))
    over = [a - b for a, b in zip(load, capacity, strict=True)]
    for m in members.values():
        m.sort()
    for _ in range(64 * len(capacity)):
        hi, lo = max(range(len(over)), key=over.__getitem__), min(range(len(over)), key=over.__getitem__)
        gap = over[hi] - over[lo]
        best = max((b for b in members[hi] if 2 * b[0] <= gap), default=None) if gap > 1 else None
        if best is None or best[0] == 0:
            break
        members[hi].remove(best)
        members[lo].append(best)
        where[best[1]] = lo
        over[hi] -= best[0]
        over[lo] += best[0]
    return where


@dataclass
class Layout:
    """Where each part of a block goes, as tables of a row a block or part at most.

    hot: old_shard, block, parts (of blocks that are split); alone: old_shard, block,
    text_hash, begin, pieces (of texts split by id); placed: old_shard, block, part, shard,
    base (its first slot there), file. moved: bytes that change shards; affected: shards
    that lose or gain rows; emptied: those of them that end without rows.
    """

    hot: DataFrame
    alone: DataFrame
    placed: DataFrame
    moved: int
    affected: set[int]
    emptied: set[int]


def _keyed(docs: DataFrame, old_shard: Column) -> dict[str, Column]:
    """What decides a row's block and part, and what a plan says of it."""
    text = whole(F.col("text"))
    return {
        "size": (F.octet_length(text) + 1).cast("long"),
        "text_crc32": F.crc32(text.cast("binary")),
        "old_shard": F.coalesce(old_shard.cast("int"), F.lit(0)),
        "block": F.pmod(F.xxhash64(text, F.lit("block")), F.lit(BLOCKS)).cast("int"),
        "text_hash": F.xxhash64(text, F.lit("text")),
        "part_hash": F.xxhash64(F.coalesce("doc_id", F.lit(-1)), F.lit("part")),
    }


def _parted(d: DataFrame, hot: DataFrame, alone: DataFrame) -> DataFrame:
    """d with the part of its block that each row is in."""
    d = d.join(F.broadcast(hot), ["old_shard", "block"], "left").join(F.broadcast(alone), ["old_shard", "block", "text_hash"], "left")
    by_text = F.pmod("text_hash", F.coalesce("parts", F.lit(1)))
    part = F.coalesce(F.col("begin") + F.pmod("part_hash", F.col("pieces")), by_text).cast("int")
    return d.withColumn("part", part).drop("parts", "begin", "pieces", "part_hash", "text_hash")


def _layout(d: DataFrame, shards: int, capacities: list[int] | None) -> Layout:
    """d: doc_id and the columns of _keyed(), cut."""
    spark = d.sparkSession
    sums = d.groupBy("old_shard", "block").agg(F.sum("size").alias("size")).collect()
    total = sum(r.size for r in sums)
    capacity = capacities or [total // shards + (i < total % shards) for i in range(shards)]
    limit = max(1, min(total // (shards * GRAIN), PART_BYTES))
    rest = {(r.old_shard, r.block): r.size for r in sums if r.size > limit}
    outgrown = spark.createDataFrame(list(rest), "old_shard int, block int")
    # texts that outgrow the limit alone: at most total / limit of them
    texts = d.join(F.broadcast(outgrown), ["old_shard", "block"], "left_semi").groupBy("old_shard", "block", "text_hash").agg(F.sum("size").alias("size")).where(F.col("size") > limit).collect()
    for r in texts:
        rest[r.old_shard, r.block] -= r.size
    parts = {k: max(1, math.ceil(size / limit)) for k, size in rest.items()}
    begin, large = dict(parts), []
    for r in sorted(texts, key=lambda r: (r.old_shard, r.block, r.text_hash)):
        n = math.ceil(r.size / limit)
        large.append((r.old_shard, r.block, r.text_hash, begin[r.old_shard, r.block], n))
        begin[r.old_shard, r.block] += n
    # these tables hold a row a block at most: BLOCKS an old shard, and total / limit parts or texts of large ones
    hot = spark.createDataFrame([(*k, n) for k, n in parts.items()], "old_shard int, block int, parts int")
    alone = spark.createDataFrame(large, "old_shard int, block int, text_hash long, begin int, pieces int")
    found = _parted(d.drop("text_crc32"), hot, alone).groupBy("old_shard", "block", "part").agg(F.sum("size").alias("size"), F.count(F.lit(1)).alias("n")).collect()
    where = place_blocks([((r.old_shard, r.block, r.part), r.old_shard, r.size) for r in found], list(capacity))
    file_bytes = max(1, min(FILE_BYTES, total // (shards * FILES)))
    filled, held, rows, moved, affected = defaultdict(int), defaultdict(int), [], 0, set()
    for r in sorted(found, key=lambda r: (r.old_shard, r.block, r.part)):
        to = where[r.old_shard, r.block, r.part]
        rows.append((r.old_shard, r.block, r.part, to, filled[to], held[to] // file_bytes))
        filled[to] += r.n
        held[to] += r.size
        if to != r.old_shard:
            moved += r.size
            affected |= {to, r.old_shard}
    placed = spark.createDataFrame(rows, "old_shard int, block int, part int, shard int, base long, file long")
    return Layout(hot, alone, placed, moved, affected, affected - set(filled))


def _narrow(docs: DataFrame, old_shard: Column) -> DataFrame:
    return cut(docs.select("doc_id", *[c.alias(n) for n, c in _keyed(docs, old_shard).items()]))


def layout(docs: DataFrame, old_shard: Column, shards: int = 16, capacities: list[int] | None = None) -> Layout:
    """The layout that moves as few bytes as the new capacities allow.

    docs needs doc_id and text; old_shard is an integer Column of docs (null: shard 0).
    capacities: bytes for each new shard, equal shares of all by default. Size is UTF-8
    bytes plus 1, so a null or empty text has size 1.
    """
    return _layout(_narrow(docs, old_shard), shards, capacities)


def _own(*first: str):
    """A part's rows in order: its slots follow one another in the new shard."""
    return Window.partitionBy(*first, "old_shard", "block", "part").orderBy("doc_id", "text_crc32", "size")


def _seats(d: DataFrame, own: Layout, placed: DataFrame) -> DataFrame:
    d = _parted(d, own.hot, own.alone).withColumn("row", F.row_number().over(_own()))
    d = d.join(F.broadcast(placed), ["old_shard", "block", "part"])
    return d.select("doc_id", "size", "text_crc32", "old_shard", "shard", (F.col("base") + F.col("row") - 1).alias("slot"))


def reshard(docs: DataFrame, old_shard: Column, shards: int = 16, capacities: list[int] | None = None) -> DataFrame:
    """A new shard and slot for each document by layout(), without moving texts.

    Returns doc_id, size, text_crc32, old_shard, shard, slot for each row; slots of a shard
    run from 0 without gaps. Rows repeated whole get slots of their own. No rows give no
    rows; other columns are ignored.
    """
    d = _narrow(docs, old_shard)
    own = _layout(d, shards, capacities)
    return _seats(d, own, own.placed)


def reshard_files(docs: DataFrame, old_shard: Column, path: str, shards: int = 16, capacities: list[int] | None = None) -> DataFrame:
    """What reshard() returns, after the affected shards were rewritten below path: their rows are read back from there."""
    d = _narrow(docs, old_shard)
    own = _layout(d, shards, capacities)
    if not own.affected:
        return _seats(d, own, own.placed)
    rewrite(docs, own, path, old_shard)
    back = read_shards(docs, path)
    k = _keyed(back, old_shard)
    back = back.select("doc_id", k["size"].alias("size"), k["text_crc32"].alias("text_crc32"), k["old_shard"].alias("old_shard"), "shard", "slot")
    touched = F.col("shard").isin(sorted(own.affected))
    return back.where(touched).unionByName(_seats(d, own, own.placed.where(~touched)))


def rewrite(docs: DataFrame, own: Layout, path: str, old_shard: Column) -> None:
    """Writes the new content of affected shards below path, a folder shard=N each; others stay as they are.

    own: the layout() of docs. Rows get the slots that reshard() gives them; rows that
    agree in doc_id, text and old shard may change places. Columns shard and slot of docs
    are replaced. An affected shard that ends empty loses its folder. path may be the
    folder that docs was read from.
    """
    keep = [c for c in docs.columns if c not in ("shard", "slot")]
    rows = docs.select(F.struct(*keep).alias("own"), "doc_id", *[c.alias(n) for n, c in _keyed(docs, old_shard).items()])
    rows = _parted(rows, own.hot, own.alone).join(F.broadcast(own.placed.where(F.col("shard").isin(sorted(own.affected)))), ["old_shard", "block", "part"])
    # one shuffle, which the window keeps: a file's parts meet in one task
    files = max(1, own.placed.select("shard", "file").distinct().count())
    rows = rows.repartition(files, "shard", "file").withColumn("row", F.row_number().over(_own("shard", "file")))
    rows = rows.select("own.*", "shard", (F.col("base") + F.col("row") - 1).alias("slot"))
    rows.sortWithinPartitions("shard", "slot").write.partitionBy("shard").mode("overwrite").option("partitionOverwriteMode", "dynamic").parquet(path)
    spark = docs.sparkSession
    for n in own.emptied:
        folder = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/shard={n}")
        folder.getFileSystem(spark._jsc.hadoopConfiguration()).delete(folder, True)


def read_shards(docs: DataFrame, path: str) -> DataFrame:
    """The rows of rewritten shards: the columns of docs, shard and slot. docs tells the schema."""
    keep = [f for f in docs.schema.fields if f.name not in ("shard", "slot")]
    schema = StructType([*keep, StructField("slot", LongType()), StructField("shard", IntegerType())])
    return docs.sparkSession.read.schema(schema).parquet(path)
