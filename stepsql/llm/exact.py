"""Exact deduplication with counting quotient filters.

Each text, with A-Z lower-cased, gives a 64-bit fingerprint. Every task builds counting quotient filters over its own
fingerprints: the high bits are the quotient, which names a home slot, the rest is the remainder that is stored. Remainders of one
quotient form a sorted run, shifted to the right where slots are taken; a bitmap marks quotients that occur and
another one the last slot of each run, so the k-th mark of one belongs to the k-th of the other; a count above one takes the next slot, which
a third bitmap marks. Filters of a range of quotients (a block) travel as one packed row, and those of all tasks merge without
loss, by merging sorted remainders and adding counts. The number of blocks grows with the rows, so that a merged
block stays as large at any size. A fingerprint with a merged count of one is
proof that its text is alone. The others go to byte verification: their texts are grouped by their
bytes, after a partial grouping in each task, so a group of any size costs one row a task.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, pick, ship, written

BLOCK_ROWS = 1 << 19  # fingerprints of a merged block, about
FEWEST_BITS = 8  # quotient bits that name a block, at least
FILTER_ROWS = 1 << 21  # fingerprints that a task holds before it packs filters
LOAD = 0.75  # share of a filter's home slots that its fingerprints would take


def fold(text: str | None) -> bytes:
    """UTF-8 with A-Z, and nothing else, in lower case."""
    return (text or "").encode("utf-8", "surrogatepass").lower()


def fingerprint(digest: bytes) -> int:
    return int.from_bytes(digest[:8], "little", signed=True)


@dataclass
class Filter:
    """A counting quotient filter over some of the values of 64 - shift bits and more: first is its first quotient."""

    shift: int  # bits of a remainder
    first: int
    occupied: np.ndarray  # bool by quotient
    last: np.ndarray  # bool by slot: the end of a run
    counter: np.ndarray  # bool by slot: the count less one of the remainder before it
    slots: np.ndarray  # uint64


def build(values: np.ndarray, counts: np.ndarray, shift: int, first: int, quotients: int) -> Filter:
    """The filter of sorted, distinct fingerprints whose quotients are first to first + quotients - 1."""
    q = (values >> np.uint64(shift)).astype(np.int64) - first
    many = counts > 1
    before = np.cumsum(1 + many) - (1 + many)  # slots taken so far, were they all side by side
    start = before + np.maximum.accumulate(q - before) if len(q) else before
    ends = start + many
    size = max(quotients, int(ends[-1]) + 1 if len(q) else 0)
    occupied, last, counter, slots = np.zeros(quotients, bool), np.zeros(size, bool), np.zeros(size, bool), np.zeros(size, np.uint64)
    occupied[q] = True
    last[ends[np.append(np.flatnonzero(np.diff(q)), len(q) - 1)] if len(q) else []] = True
    slots[start] = values & np.uint64((1 << shift) - 1)
    slots[ends[many]] = (counts[many] - 1).astype(np.uint64)
    counter[ends[many]] = True
    return Filter(shift, first, occupied, last, counter, slots)


def entries(f: Filter) -> tuple[np.ndarray, np.ndarray]:
    """Sorted fingerprints and counts that a filter holds."""
    homes, ends = np.flatnonzero(f.occupied), np.flatnonzero(f.last)
    if not len(homes):
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    # a run begins at its home or right behind the run before
    starts = np.maximum(homes, np.concatenate([[0], ends[:-1] + 1]))
    length = ends - starts + 1
    slot = np.repeat(starts - np.concatenate([[0], np.cumsum(length)[:-1]]), length) + np.arange(length.sum())
    quotient = np.repeat(homes + f.first, length)
    plain = ~f.counter[slot]
    at = slot[plain]
    value = quotient[plain].astype(np.uint64) << np.uint64(f.shift) | f.slots[at]
    behind = np.minimum(at + 1, len(f.slots) - 1)
    return value, 1 + np.where(f.counter[behind] & (behind > at), f.slots[behind], np.uint64(0)).astype(np.int64)


def filters_of(prints: np.ndarray, block_bits: int) -> dict[int, Filter]:
    """Counting quotient filters of unsigned 64-bit fingerprints by block, the first block_bits of the quotient."""
    value, count = np.unique(prints.astype(np.uint64), return_counts=True)
    bits = min(60, max(block_bits, math.ceil(math.log2(max(len(value), 1) / LOAD))))
    block = (value >> np.uint64(64 - block_bits)).astype(np.int64)
    cut = np.flatnonzero(np.diff(block)) + 1
    own = 1 << (bits - block_bits)  # quotients of a block
    return {int(b[0]): build(v, c, 64 - bits, int(b[0]) * own, own) for b, v, c in zip(np.split(block, cut), np.split(value, cut), np.split(count, cut)) if len(b)}


def merge(filters: list[Filter]) -> tuple[np.ndarray, np.ndarray]:
    """Sorted fingerprints and added counts of filters of one block."""
    held = [entries(f) for f in filters]
    value, count = np.concatenate([v for v, _ in held]), np.concatenate([c for _, c in held])
    order = np.argsort(value, kind="stable")
    value, count = value[order], count[order]
    first = np.flatnonzero(np.concatenate([[True], value[1:] != value[:-1]])) if len(value) else np.zeros(0, np.int64)
    return value[first], np.add.reduceat(count, first) if len(first) else count


_PACKED = "block int, shift int, first bigint, quotients int, occupied binary, last binary, counter binary, slots binary"


def to_row(block: int, f: Filter) -> tuple:
    bits = lambda x: np.packbits(x, bitorder="little").tobytes()
    return block, f.shift, f.first, len(f.occupied), bits(f.occupied), bits(f.last), bits(f.counter), f.slots.tobytes()


def from_row(shift: int, first: int, quotients: int, occupied: bytes, last: bytes, counter: bytes, slots: bytes) -> Filter:
    slots_ = np.frombuffer(slots, np.uint64)
    bits = lambda x, n: np.unpackbits(np.frombuffer(x, np.uint8), count=n, bitorder="little").astype(bool)
    return Filter(shift, first, bits(occupied, quotients), bits(last, len(slots_)), bits(counter, len(slots_)), slots_)


def _pack(block_bits: int):
    def out(held: list[np.ndarray]) -> pa.RecordBatch:
        rows = [to_row(b, f) for b, f in filters_of(np.concatenate(held), block_bits).items()]
        kinds = (pa.int32(), pa.int32(), pa.int64(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.binary())
        return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows), kinds)], names=[f.split()[0] for f in _PACKED.split(", ")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0
        for b in batches:
            held.append(b.column(0).to_numpy(zero_copy_only=False).view(np.uint64))
            n += b.num_rows
            if n >= FILTER_ROWS:
                yield out(held)
                held, n = [], 0
        if n:
            yield out(held)

    return run


def _repeats(table: pa.Table) -> pa.Table:
    columns = (table[n].to_pylist() for n in ("shift", "first", "quotients", "occupied", "last", "counter", "slots"))
    value, count = merge([from_row(*row) for row in zip(*columns)])
    keep = count > 1
    return pa.table({"print": pa.array(value[keep].view(np.int64), pa.int64()), "n": pa.array(count[keep], pa.int64())})


def repeated_prints(prints: DataFrame) -> DataFrame:
    """print, n of the fingerprints (column print) that the merged filters count more than once."""
    ship(prints.sparkSession)
    block_bits = max(FEWEST_BITS, math.ceil(math.log2(max(prints.count(), 1) / BLOCK_ROWS)))
    packed = pick(prints, "print").mapInArrow(_pack(block_bits), _PACKED)
    return packed.groupBy("block").applyInArrow(_repeats, "print bigint, n bigint")


def fingerprints(docs: DataFrame, with_text: bool = False) -> DataFrame:
    """doc_id, print, text_sha256 (and folded, the normalised bytes) for every row."""

    def run(b: pa.RecordBatch) -> dict:
        texts = [fold(t) for t in b.column(1).to_pylist()]
        digests = [hashlib.sha256(t).digest() for t in texts]
        out = {"doc_id": b.column(0), "print": [fingerprint(d) for d in digests], "text_sha256": [d.hex() for d in digests]}
        return out | {"folded": texts} if with_text else out

    rows = pick(docs, "doc_id", "text").selectExpr("cast(doc_id as bigint) doc_id", "text")
    return map_batches(rows, run, "doc_id bigint, print bigint, text_sha256 string" + ", folded binary" * with_text)


def keep(docs: DataFrame) -> DataFrame:
    """One row of each class of equal texts, all columns: the one with the largest doc_id (nulls last; of
    repeated rows one), as dedup says."""
    ship(docs.sparkSession)
    at = docs.columns.index("text")

    def mark(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(0, b.num_rows, 512):
                part = b.slice(k, 512)
                own = [fingerprint(hashlib.sha256(fold(t)).digest()) for t in part.column(at).to_pylist()]
                yield pa.RecordBatch.from_arrays([pa.array(own, pa.int64()), *part.columns], names=["print", *part.schema.names])

    repeated = written(repeated_prints(written(fingerprints(docs).select("print"))))
    marked = docs.mapInArrow(mark, "print bigint, " + ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema))
    alone = marked.join(repeated.select("print"), "print", "left_anti").select(*docs.columns)
    row = F.struct(F.col("doc_id").alias("first"), F.struct(*docs.columns).alias("row"))
    folded = F.translate(F.coalesce("text", F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    groups = marked.join(repeated.select("print"), "print", "left_semi").groupBy("print", folded.alias("folded")).agg(F.max(row).alias("best"))
    return alone.unionByName(groups.select("best.row.*"))


def dedup(docs: DataFrame) -> DataFrame:
    """doc_id, keep_id, group_size, kept, text_sha256 for every row of docs, dropped ones too.

    Texts are equal when identical after lower-casing A-Z; null counts as empty. Of equal texts one row stays: that with
    the largest doc_id, nulls last; of rows that share it as well one, so every group keeps exactly one row (keep_id is null
    where all doc_ids are). Whole texts count, however long. Other columns are ignored.
    """
    prints = written(fingerprints(docs).withColumn("row", F.monotonically_increasing_id()))
    repeated = written(repeated_prints(prints))
    routed = fingerprints(docs, with_text=True).join(repeated.select("print"), "print", "left_semi")
    # verified by bytes: texts that share a fingerprint only are groups of their own
    groups = routed.groupBy("print", "folded").agg(F.count("*").alias("size"), F.max("text_sha256").alias("text_sha256"))
    best = F.max(F.struct("doc_id", (-F.col("row")).alias("less")))
    stays = prints.join(repeated.select("print"), "print", "left_semi").groupBy("text_sha256").agg(best.alias("best"))
    # a table of its own, so that the join below can split a group of any size
    verified = written(groups.select("text_sha256", "size").join(stays, "text_sha256"))
    out = prints.join(verified, "text_sha256", "left")
    return out.select(
        "doc_id",
        F.when(F.col("size").isNull(), F.col("doc_id")).otherwise(F.col("best.doc_id")).alias("keep_id"),
        F.coalesce("size", F.lit(1)).cast("bigint").alias("group_size"),
        F.when(F.col("size").isNull(), F.lit(True)).otherwise(F.col("row") == -F.col("best.less")).alias("kept"),
        "text_sha256",
    )
