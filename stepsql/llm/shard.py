"""Sharding by best-fit-decreasing bin packing.

Rows of equal texts form a group that no shard boundary cuts. Groups with a large share of all bytes
are packed one by one; the many small ones first join parcels by hash, so what reaches the driver is
bounded by the two parameters and not by the data. With a fixed capacity, large groups and parcels are measured by
it as well: a parcel beyond it is cut by order of hash, so units stay in proportion to the shards that come out. Parcels and large groups enter, from the largest down, the bin with
the tightest remaining capacity that holds them, found in a balanced tree. With a fixed number of
shards, the smallest capacity that needs no more bins is found by bisection, which makes sizes near
equal; with a fixed capacity, the number of shards is what the packing needs.
"""

from __future__ import annotations

import random
from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import pick, written


@dataclass(frozen=True)
class Config:
    shards: int = 8
    parcels: int = 4096  # parcels of small groups
    large: int = 4096  # a group is large from 1 / large of all bytes on, so there are at most so many
    fine: int = 64  # with a capacity, a group is large from 1 / fine of it on, and parcels hold less than twice that
    unit: int = 512  # rows that a numbered part has at least, in expectation, before a unit is split
    parts: int = 65_536  # parts that all units together are split into at most, beside one each


class Tree:
    """A treap of (remaining capacity, bin) with deterministic priorities: expected logarithmic height."""

    def __init__(self) -> None:
        self.root, self.random = None, random.Random(5)

    def _split(self, node, key):
        if node is None:
            return None, None
        if node[0] < key:
            node[3], right = self._split(node[3], key)
            return node, right
        left, node[2] = self._split(node[2], key)
        return left, node

    def _join(self, a, b):
        if a is None or b is None:
            return a or b
        if a[1] > b[1]:
            a[3] = self._join(a[3], b)
            return a
        b[2] = self._join(a, b[2])
        return b

    def add(self, key: tuple[int, int]) -> None:
        left, right = self._split(self.root, key)
        self.root = self._join(self._join(left, [key, self.random.random(), None, None]), right)

    def take(self, least: int) -> tuple[int, int] | None:
        """Remove and return the smallest key with a capacity of `least` or more."""
        left, right = self._split(self.root, (least, -1))
        if right is None:
            self.root = left
            return None
        node = right
        while node[2] is not None:
            node = node[2]
        key = node[0]
        _, right = self._split(right, (key[0], key[1] + 1))
        self.root = self._join(left, right)
        return key


def best_fit_decreasing(sizes: list[int], capacity: int) -> list[int]:
    """Bin of every item; items over the capacity get a bin of their own. Equal sizes: in the order given."""
    tree, bins, out = Tree(), 0, [0] * len(sizes)
    for i in sorted(range(len(sizes)), key=lambda i: -sizes[i]):
        found = tree.take(sizes[i]) if sizes[i] <= capacity else None
        left, out[i] = found if found else (max(capacity, sizes[i]), bins)
        bins += found is None
        tree.add((left - sizes[i], out[i]))
    return out


def into_bins(sizes: list[int], bins: int) -> list[int]:
    """Bin of every item for at most `bins` bins of the smallest capacity that best-fit-decreasing can do with."""
    if not sizes:
        return []
    low, high = max(max(sizes), -(-sum(sizes) // bins)), sum(sizes)
    best = [0] * len(sizes)
    while low <= high:
        middle = (low + high) // 2
        got = best_fit_decreasing(sizes, middle)
        if max(got) < bins:
            best, high = got, middle - 1
        else:
            low = middle + 1
    return best


def shard(docs: DataFrame, config: Config = Config(), capacity: int | None = None) -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot, grown_shard for every row of docs.

    Size is the text's UTF-8 bytes plus 1; a null text counts as empty. Rows of equal texts share a shard;
    shards have near equal bytes, as far as the largest group allows. With a capacity, shards hold at most that many bytes
    (a group beyond it stands alone) and are as many as the packing needs. slot numbers a shard's rows from 0
    without gaps, by doc_id within a unit of rows; ties are in any order. Repeated rows
    get a slot each; an empty table gives no rows. Other columns are ignored.
    """
    spark = docs.sparkSession
    text = F.coalesce("text", F.lit(""))
    rows = written(
        pick(docs, "doc_id", "text").select(
            F.col("doc_id").cast("bigint").alias("doc_id"),
            (F.octet_length(text) + 1).cast("bigint").alias("size"),
            F.crc32(text.cast("binary")).alias("text_crc32"),
            F.xxhash64(text).alias("group"),
            # its place in this table deals a row out, as ids may repeat or lack
            F.monotonically_increasing_id().alias("row"),
        )
    )
    groups = written(rows.groupBy("group").agg(F.sum("size").alias("bytes"), F.count("*").alias("rows")))
    total = groups.agg(F.coalesce(F.sum("bytes"), F.lit(0)).alias("b")).first().b
    least = max(1, -(-total // config.large))
    parcels = config.parcels
    if capacity:
        least = max(1, min(least, capacity // config.fine))
        parcels = max(parcels, -(-total // least))
    # at most total / least groups, and as many parcels, beside those of the parameter
    units = [(r.group, True, r.bytes, r.rows) for r in groups.where(F.col("bytes") >= least).collect()] if total else []
    parcel = F.pmod("group", F.lit(parcels))
    small = groups.where(F.col("bytes") < least).withColumn("parcel", parcel)
    if capacity:
        # groups that begin in the same stretch of `least` bytes: less than two stretches together
        so_far = Window.partitionBy("parcel").orderBy("group").rowsBetween(Window.unboundedPreceding, -1)
        small = small.withColumn("stretch", F.floor(F.coalesce(F.sum("bytes").over(so_far), F.lit(0)) / least))
    else:
        small = small.withColumn("stretch", F.lit(0))
    # a parcel is named by its first group
    cut = small.groupBy("parcel", "stretch").agg(F.min("group").alias("first"), F.sum("bytes").alias("bytes"), F.sum("rows").alias("rows")).collect()
    units += [(r["first"], False, r.bytes, r.rows) for r in cut]
    firsts: dict[int, list[int]] = {}
    for r in cut:
        firsts.setdefault(r.parcel, []).append(r["first"])
    units.sort()
    sizes = [u[2] for u in units]
    bins = best_fit_decreasing(sizes, capacity) if capacity else into_bins(sizes, config.shards)
    # a unit with many rows is numbered in as many salted parts as it needs; parts are bounded by rows / unit + units
    unit = max(config.unit, sum(u[3] for u in units) // config.parts)
    placed = [(key, large, b, max(1, -(-n // unit))) for (key, large, _, n), b in zip(units, bins)]
    fields = "key bigint, large boolean, shard int, parts bigint"
    places = F.broadcast(spark.createDataFrame(placed, fields))
    big = F.broadcast(spark.createDataFrame([(u[0],) for u in units if u[1]], "big bigint"))
    names = F.broadcast(spark.createDataFrame(list(firsts.items()), "parcel bigint, firsts array<bigint>"))
    dealt = (
        rows.join(big, rows["group"] == big["big"], "left")
        .withColumn("parcel", parcel)
        .join(names, "parcel", "left")
        .withColumn("large", F.col("big").isNotNull())
        .withColumn("key", F.when(F.col("large"), F.col("group")).otherwise(F.array_max(F.filter("firsts", lambda first: first <= F.col("group")))))
        .join(places, ["key", "large"])
        .withColumn("part", F.pmod(F.xxhash64("row"), F.col("parts")))
        .select("doc_id", "size", "text_crc32", "shard", "key", "large", "part")
    )
    counts = dealt.groupBy("shard", "key", "large", "part").count()
    before = Window.partitionBy("shard").orderBy("key", "large", "part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.withColumn("offset", F.coalesce(F.sum("count").over(before), F.lit(0))).drop("count")
    own = Window.partitionBy("shard", "key", "large", "part").orderBy("doc_id", "size")
    return (
        dealt.withColumn("at", F.row_number().over(own) - 1)
        .join(offsets, ["shard", "key", "large", "part"])
        .select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", (F.col("offset") + F.col("at")).cast("bigint").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
    )
