"""Sharding by best-fit-decreasing bin packing of indivisible groups.

Groups enter bins by falling size; each goes where the least room is left that still holds it. A
balanced tree over (room, bin) finds that bin in logarithmic time. For a set number of bins of nearly
equal size, the smallest capacity with which best fit needs no more bins is searched for.

Groups of more than a small part of a shard are few, whatever the corpus, and enter the shards as they
are. All smaller ones are dealt to packs of some 100,000 and packed there, each pack by one task, into
bins of one part; the bins then enter the shards like groups. No two bins of a pack fit into one, so the
bins are at most twice as many as such parts and one more for each pack.
"""

from __future__ import annotations

import random
from collections.abc import Iterable

import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from contrast.llm.common import materialise

#: Parts of a shard: groups of more than one part enter shards alone, others in bins of one part.
PARTS = 256
#: Groups of a pack, about.
PACK = 100_000
#: Buckets of a shard's rows within which slots are counted.
BUCKETS = 64


class _Node:
    __slots__ = ("key", "rank", "left", "right")

    def __init__(self, key, rank):
        self.key, self.rank, self.left, self.right = key, rank, None, None


class RoomTree:
    """A treap of distinct (room, bin) keys: balanced by random ranks, from a fixed seed."""

    def __init__(self):
        self.root, self.random = None, random.Random(0)

    def _split(self, node, key):
        """Nodes below key, and from key on."""
        if node is None:
            return None, None
        if node.key < key:
            node.right, rest = self._split(node.right, key)
            return node, rest
        rest, node.left = self._split(node.left, key)
        return rest, node

    def _join(self, a, b):
        if a is None or b is None:
            return a or b
        if a.rank < b.rank:
            a.right = self._join(a.right, b)
            return a
        b.left = self._join(a, b.left)
        return b

    def add(self, room: int, bin_: int) -> None:
        a, b = self._split(self.root, (room, bin_))
        self.root = self._join(self._join(a, _Node((room, bin_), self.random.random())), b)

    def take_tightest(self, need: int) -> tuple[int, int] | None:
        """Removes and returns the least key whose room holds need."""
        a, b = self._split(self.root, (need, -1))
        if b is None:
            self.root = a
            return None
        parent, node = None, b
        while node.left:
            parent, node = node, node.left
        if parent is None:
            b = node.right
        else:
            parent.left = node.right
        self.root = self._join(a, b)
        return node.key


def best_fit_decreasing(sizes: Iterable[int], capacity: int, limit: int | None = None) -> list[int] | None:
    """The bin of each item, as few bins as best fit finds; an item above the capacity has a bin alone.

    Equal sizes enter in their order. With a limit, None as soon as more bins are needed.
    """
    sizes = list(sizes)
    tree, out, bins = RoomTree(), [0] * len(sizes), 0
    for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
        if (got := tree.take_tightest(sizes[i])) is None:
            room, bin_ = capacity, bins
            bins += 1
            if limit is not None and bins > limit:
                return None
        else:
            room, bin_ = got
        out[i] = bin_
        if room > sizes[i]:
            tree.add(room - sizes[i], bin_)
    return out


def equal_bins(sizes: list[int], bins: int, rounds: int = 14) -> list[int]:
    """A bin below `bins` for each item, with nearly equal sums.

    Items of a fair share or more have bins alone; the rest are packed by best fit with the least
    capacity found by halving. With fewer items than bins some bins stay empty.
    """
    order, out, first, rest = sorted(range(len(sizes)), key=lambda i: -sizes[i]), [0] * len(sizes), 0, sum(sizes)
    while first < len(order) and bins - first > 1 and sizes[order[first]] * (bins - first) >= rest:
        out[order[first]] = first
        rest -= sizes[order[first]]
        first += 1
    left, small = order[first:], [sizes[i] for i in order[first:]]
    if not small:
        return out
    free = bins - first
    low = max(small[0], -(-rest // free))
    high = low + small[0]
    while (got := best_fit_decreasing(small, high, free)) is None:
        low, high = high, high + high - low + small[0]
    for _ in range(rounds):
        middle = (low + high) // 2
        if middle >= high:
            break
        if (better := best_fit_decreasing(small, middle, free)) is None:
            low = middle + 1
        else:
            got, high = better, middle
    for i, b in zip(left, got):
        out[i] = first + b
    return out


def assign(rows: DataFrame, shards: int, parts: int = PARTS, pack_groups: int = PACK) -> DataFrame:
    """rows (group, size, ...) with `shard` from 0 to shards - 1: sums nearly equal, groups whole.

    What reaches the driver and is broadcast are 2 * shards * parts bins and groups, and one more for each pack_groups
    groups, at most. A group above a fair share makes its shard larger than the others. Null is a group.
    """
    spark = rows.sparkSession
    groups = materialise(rows.groupBy("group").agg(F.sum("size").alias("bytes")), "groups")
    total, number = groups.agg(F.coalesce(F.sum("bytes"), F.lit(0)), F.count(F.lit(1))).first()
    part = max(1, total // (shards * parts))
    small = materialise(pack(groups.where(F.col("bytes") <= part), part, max(1, -(-number // pack_groups))), "packed")
    alone = [(r["group"], r["bytes"]) for r in groups.where(F.col("bytes") > part).orderBy(F.col("bytes").desc(), "group").toLocalIterator()]
    binned = [tuple(r) for r in small.groupBy("pack", "bin").agg(F.sum("bytes")).orderBy("pack", "bin").toLocalIterator()]
    homes = equal_bins([b for _, b in alone] + [b for _, _, b in binned], shards)
    of_group = spark.createDataFrame([(g, s) for (g, _), s in zip(alone, homes)], f"large {rows.schema['group'].dataType.simpleString()}, alone int")
    of_bin = spark.createDataFrame([(p, b, s) for (p, b, _), s in zip(binned, homes[len(alone) :])], "pack int, bin int, together int")
    # a large group's rows are placed by broadcast; a small group's are a part's bytes at most, so they meet by shuffle
    placed = rows.join(F.broadcast(of_group), F.col("group").eqNullSafe(F.col("large")), "left").drop("large")
    to_bin = small.join(F.broadcast(of_bin), ["pack", "bin"]).select(F.col("group").alias("packed"), "together")
    left = placed.where("alone is null").drop("alone").join(to_bin, F.col("group").eqNullSafe(F.col("packed"))).drop("packed").withColumnRenamed("together", "shard")
    return placed.where("alone is not null").withColumnRenamed("alone", "shard").unionByName(left)


def with_slots(rows: DataFrame, order: list[str], buckets: int = BUCKETS) -> DataFrame:
    """rows (shard, ...) with `slot`: places from 0 without gaps in each shard, by bucket and then `order`.

    A shard's rows are counted in hash buckets, so no task numbers a whole shard.
    """
    placed = rows.withColumn("bucket", F.pmod(F.xxhash64(*order), F.lit(buckets)).cast("int"))
    before = F.sum("n").over(Window.partitionBy("shard").orderBy("bucket").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n")
    begins = placed.groupBy("shard", "bucket").agg(F.count(F.lit(1)).alias("n")).select("shard", "bucket", before.alias("before"))
    within = F.row_number().over(Window.partitionBy("shard", "bucket").orderBy(*order)) - 1
    return placed.withColumn("within", within).join(begins, ["shard", "bucket"]).withColumn("slot", (F.col("before") + F.col("within")).cast("long")).drop("bucket", "before", "within")


def sized(docs: DataFrame, id_column: str = "doc_id", text: str = "text", overhead: int = 16) -> DataFrame:
    """doc_id, size, text_crc32 and group (digest of the text) of each row; a null text is empty."""
    value = F.coalesce(F.col(text), F.lit(""))
    return docs.select(F.col(id_column).alias("doc_id"), (F.octet_length(value) + overhead).cast("long").alias("size"), F.crc32(value.cast("binary")).alias("text_crc32"), F.unhex(F.sha2(value.cast("binary"), 256)).alias("group"))


def shard_documents(docs: DataFrame, shards: int, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, group, shard, slot: equal texts together, bytes nearly equal.

    Repeated rows each have a slot. An empty table gives no rows. Null ids come first within a bucket.
    """
    rows = materialise(sized(docs, id_column, text), "sized")
    return with_slots(materialise(assign(rows, shards), "assigned"), ["doc_id", "group"])


def pack(groups: DataFrame, capacity: int, packs: int = 1) -> DataFrame:
    """groups (group, bytes) with `pack` and `bin`: as few bins of a capacity as best fit finds in each pack.

    Groups are dealt to packs by hash and each is packed by one task, so choose packs for some 100,000
    groups each; every pack can end with one bin that isn't full. A group above the capacity has a bin alone.
    """

    def one(frame: pd.DataFrame) -> pd.DataFrame:
        frame = frame.sort_values(["bytes", "group"], ascending=[False, True], kind="stable")
        return frame.assign(bin=best_fit_decreasing(frame["bytes"].tolist(), capacity)).astype({"bin": "int32"})

    dealt = groups.select("group", "bytes", F.pmod(F.xxhash64("group"), F.lit(packs)).cast("int").alias("pack"))
    return dealt.groupBy("pack").applyInPandas(one, dealt.schema.simpleString()[7:-1].replace(":", " ") + ", bin int")
