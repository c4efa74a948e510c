"""Byte-balanced shards of indivisible groups by Karmarkar-Karp differencing.

Documents with equal texts form a group that stays together.  A partial partition is a list of shard sums; the two
with the largest spread are added in opposite order until one is left.  Each task does this for the groups that
hash to it, and the partial partitions of all tasks, one row each, are combined the same way, in as many levels as
their number asks for.  Groups are summed before anything is moved, so a hot text is one row.

A null text counts no bytes, is a group of its own and has the checksum of an empty text.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import stored

#: Items that one task combines.
FAN_IN = 100_000
#: Rows of a shard that are numbered together.
CELL_ROWS = 50_000
OVERHEAD = 8


def difference(items: list[list[int]], shards: int) -> tuple[list[list[int]], list[int]]:
    """items: each a list of at most ``shards`` sums.  Returns for each item the shard of each of its sums, and the sums by shard.

    Sums of a tree node are kept in descending order; ``turn[j]`` is the place in the larger part of its j-th sum.
    """
    nodes: list[tuple] = []
    heap: list[tuple] = []
    for k, sums in enumerate(items):
        order = sorted(range(len(sums)), key=lambda i: -sums[i])
        s = [sums[i] for i in order] + [0] * (shards - len(sums))
        nodes.append((order,))
        heap.append((s[-1] - s[0], k, s, s[-1] * 0))
    low = [0] * len(items)  # what was taken off every sum of a node
    heapq.heapify(heap)
    while len(heap) > 1:
        _, a, x, _ = heapq.heappop(heap)
        _, b, y, _ = heapq.heappop(heap)
        raw = [p + q for p, q in zip(x, reversed(y))]
        turn = sorted(range(shards), key=raw.__getitem__, reverse=True)
        base = raw[turn[-1]]
        nodes.append((a, b, turn))
        low.append(low[a] + low[b] + base)
        s = [raw[i] - base for i in turn]
        heapq.heappush(heap, (-s[0], len(nodes) - 1, s, 0))
    if not heap:
        return [], [0] * shards
    top = heap[0][1]
    total = [v + low[top] for v in heap[0][2]]
    places: dict[int, list[int]] = {top: list(range(shards))}
    out: list[list[int]] = [[]] * len(items)
    for k in range(len(nodes) - 1, -1, -1):
        place, node = places.pop(k), nodes[k]
        if len(node) == 1:
            out[k] = [0] * len(node[0])
            for at, i in enumerate(node[0]):
                out[k][i] = place[at]
        else:
            a, b, turn = node
            mine, other = [0] * shards, [0] * shards
            for j, i in enumerate(turn):
                mine[i] = place[j]
                other[shards - 1 - i] = place[j]
            places[a], places[b] = mine, other
    return out, total


def _level(items: DataFrame, shards: int, count: int) -> DataFrame:
    """(id, sums) -> (id, up, places, sums): ``sums`` is given once for each ``up``, with a null id."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, sums = [], []
        for b in batches:
            ids += b.column(0).to_pylist()
            sums += b.column(1).to_pylist()
        if not ids:
            return
        order = sorted(range(len(ids)), key=ids.__getitem__)
        places, total = difference([sums[i] for i in order], shards)
        up = f"{TaskContext.get().partitionId()}"
        for at in range(0, len(ids), 10_000):
            part = order[at : at + 10_000]
            yield pa.RecordBatch.from_pydict({"id": pa.array([ids[i] for i in part]), "up": pa.array([up] * len(part)), "places": pa.array(places[at : at + 10_000], pa.list_(pa.int32())), "sums": pa.array([None] * len(part), pa.list_(pa.int64()))})
        yield pa.RecordBatch.from_pydict({"id": pa.array([None], pa.string()), "up": pa.array([up]), "places": pa.array([None], pa.list_(pa.int32())), "sums": pa.array([total], pa.list_(pa.int64()))})

    parts = max(1, -(-count // FAN_IN))
    dealt = items.select("id", "sums").repartition(parts, "id") if parts > 1 else items.select("id", "sums").repartition(1)
    return stored(dealt.mapInArrow(run, "id string, up string, places array<int>, sums array<bigint>"), "shard-level")


def assign(groups: DataFrame, shards: int) -> DataFrame:
    """groups (id string, bytes long) -> (id, shard)."""
    count = groups.count()
    level = _level(groups.select("id", F.array("bytes").alias("sums")), shards, count)
    out = level.where("id is not null").select("id", "up", F.get("places", 0).alias("place"))
    while True:
        partial = level.where("id is null").select(F.col("up").alias("id"), "sums")
        count = partial.count()
        if count <= 1:
            return out.select("id", F.col("place").alias("shard"))
        level = _level(partial, shards, count)
        step = level.where("id is not null").select(F.col("id").alias("up"), F.col("up").alias("next"), F.col("places").alias("turn"))
        out = out.join(step, "up").select("id", F.col("next").alias("up"), F.get("turn", F.col("place")).alias("place"))


def numbered(rows: DataFrame, count: int) -> DataFrame:
    """Adds ``slot``, gapless from 0 in each shard: rows are numbered in cells of a shard, cells by their counts."""
    cells = max(64, -(-count // CELL_ROWS))
    rows = rows.withColumn("cell", F.pmod(F.xxhash64("doc_id"), F.lit(cells)).cast("int"))
    sizes = rows.groupBy("shard", "cell").agg(F.count("*").alias("n"))
    before = sizes.select("shard", "cell", (F.sum("n").over(Window.partitionBy("shard").orderBy("cell")) - F.col("n")).alias("before"))
    rank = F.row_number().over(Window.partitionBy("shard", "cell").orderBy("doc_id", "text_crc32", "size")) - 1
    return rows.withColumn("rank", rank).join(before, ["shard", "cell"]).withColumn("slot", F.col("before") + F.col("rank"))


def shard(docs: DataFrame, shards: int = 24) -> DataFrame:
    """One row per document: doc_id, size, text_crc32, law 'bytes', shard, slot, grown_shard (null)."""
    text = F.col("text").cast("string")
    base = docs.select("doc_id", (F.coalesce(F.octet_length(text), F.lit(0)) + OVERHEAD).cast("long").alias("size"), F.crc32(F.coalesce(text, F.lit("")).cast("binary")).alias("text_crc32"), F.coalesce(F.sha2(text.cast("binary"), 256), F.lit("null")).alias("id"))
    base = stored(base, "shard-rows")
    placed = assign(base.groupBy("id").agg(F.sum("size").alias("bytes")), shards)
    rows = stored(base.join(placed, "id").drop("id"), "shard-placed")
    return numbered(rows, base.count()).select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), F.col("shard").cast("int").alias("shard"), F.col("slot").cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
