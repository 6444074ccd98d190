"""SimHash near-duplicate classes by the generalised pigeonhole principle.

Fingerprints link at `radius` or fewer differing bits. The 64 bits are grouped into partitions, correlated bits
together. If two fingerprints link, then for any thresholds t_i >= -1 with sum(t_i + 1) = radius + 1
some partition of theirs differs in at most t_i bits. So each fingerprint gets thresholds of its own, by
dynamic programming over candidate counts estimated on a bounded sample, and probes, in each partition, the values within
t_i bits of its own. Hits are verified on all bits.

A partition value that more than `bucket` fingerprints have is not paired up. Its members and those that
probe it take an exact way whose cost is linear: each emits the 65 fingerprints within one bit; two fingerprints within two
bits of each other share at least one of these, and all that share one are within two bits, so linking
each to the least of those sharing it keeps every link's component. (For this the radius is 2.)

Components come from alternating star operations on distinct fingerprints, tables all the way.
"""

from __future__ import annotations

from dataclasses import dataclass
from itertools import combinations, repeat

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import map_batches, pick, written
from .exact import fold

SEED, SHINGLE, RADIUS = 42, 3, 2


@dataclass(frozen=True)
class Config:
    partitions: int = 3
    sample: int = 2048  # fingerprints that grouping and estimates read at most (in expectation)
    bucket: int = 64  # members of a partition value that are paired up; beyond, the linear way
    probe_cost: float = 0.5  # of one probe, in candidates


def simhash(text: str | None) -> int:
    """Unsigned 64-bit fingerprint of one whole text."""
    words = fold(text).split()
    if not words:
        return 0
    ones, n = np.zeros(64, np.int64), 0
    for at in range(0, max(1, len(words) - SHINGLE + 1), 65_536):
        part = words[at : at + 65_536 + SHINGLE - 1]
        joined = map(b" ".join, zip(*[part[k:] for k in range(SHINGLE)])) if len(words) >= SHINGLE else [b" ".join(words)]
        h = np.array(list(map(xxhash.xxh64_intdigest, joined, repeat(SEED))), "<u8")
        ones += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
        n += len(h)
    return int(np.packbits(2 * ones > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame) -> DataFrame:
    """doc_id, print (the fingerprint as a signed 64-bit integer) for every row of docs."""

    def run(b: pa.RecordBatch) -> dict:
        return {"doc_id": b.column(0), "print": np.array([simhash(t) for t in b.column(1).to_pylist()], np.uint64).view(np.int64)}

    return map_batches(pick(docs, "doc_id", "text").selectExpr("cast(doc_id as bigint) doc_id", "text"), run, "doc_id bigint, print bigint")


def bit_order(sample: np.ndarray, parts: int) -> tuple[np.ndarray, list[int]]:
    """Order of the 64 bits that puts correlated ones side by side, and the partitions' widths."""
    widths = [64 // parts + (k < 64 % parts) for k in range(parts)]
    bits = np.unpackbits(sample.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").astype(float)
    if len(bits) < 2:
        return np.arange(64), widths
    centred = bits - bits.mean(0)
    spread = np.sqrt((centred**2).mean(0)) + 1e-9
    tie = np.abs(centred.T @ centred / len(bits) / np.outer(spread, spread))
    np.fill_diagonal(tie, 0)
    free, order = set(range(64)), []
    for width in widths:
        left = sorted(free)
        first = left[int(tie[np.ix_(left, left)].max(1).argmax())]
        group = [first]
        free.remove(first)
        while len(group) < width:
            left = sorted(free)
            best = left[int(tie[np.ix_(left, group)].mean(1).argmax())]
            group.append(best)
            free.remove(best)
        order += group
    return np.array(order), widths


def reorder(prints: np.ndarray, order: np.ndarray) -> np.ndarray:
    bits = np.unpackbits(prints.astype("<u8").view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    return np.ascontiguousarray(np.packbits(bits[:, order], axis=1, bitorder="little")).view("<u8").ravel()


def thresholds(parts: np.ndarray, known: np.ndarray, widths: list[int], rows: float, config: Config) -> np.ndarray:
    """t_i for every row: the allocation of least estimated cost. parts, known: partition values, (rows, partitions)."""
    n, m, budget = len(parts), len(widths), RADIUS + 1
    cost = np.zeros((m, budget + 1, n))  # by t + 1
    for i, w in enumerate(widths):
        apart = np.bitwise_count(parts[:, i, None] ^ known[None, :, i])
        ball = 0.0
        for t in range(RADIUS + 1):
            ball += {0: 1, 1: w, 2: w * (w - 1) // 2}[t]
            seen = (apart <= t).sum(1) / max(1, len(known))
            cost[i, t + 1] = rows * np.maximum(seen, ball / 2.0**w) + config.probe_cost * ball
    best = np.full((budget + 1, n), np.inf)
    best[0] = 0
    chosen = np.zeros((m, budget + 1, n), np.int64)
    for i in range(m):
        new = np.full_like(best, np.inf)
        for spent in range(budget + 1):
            for give in range(spent + 1):
                total = best[spent - give] + cost[i, give]
                better = total < new[spent]
                new[spent] = np.where(better, total, new[spent])
                chosen[i, spent] = np.where(better, give, chosen[i, spent])
        best = new
    out, spent = np.zeros((n, m), np.int64), np.full(n, budget)
    for i in reversed(range(m)):
        out[:, i] = chosen[i, spent, np.arange(n)] - 1
        spent = spent - out[:, i] - 1
    return out


def _partition_values(prints: np.ndarray, widths: list[int]) -> np.ndarray:
    starts = np.concatenate([[0], np.cumsum(widths)[:-1]]).astype(np.uint64)
    masks = np.array([(1 << w) - 1 for w in widths], np.uint64)
    return prints[:, None] >> starts[None, :] & masks[None, :]


def entries(prints: DataFrame, known: np.ndarray, rows: int, config: Config) -> DataFrame:
    """key, print, member, probe: every fingerprint's own partition values (member) and the values it probes."""
    order, widths = bit_order(known, config.partitions)
    known_parts = _partition_values(reorder(known, order), widths)

    def run(b: pa.RecordBatch) -> dict:
        own = b.column(0).to_numpy(zero_copy_only=False)
        parts = _partition_values(reorder(own.view(np.uint64), order), widths)
        t = thresholds(parts, known_parts, widths, rows, config)
        keys, who, member, probe = [], [], [], []

        def add(i: int, chosen: np.ndarray, flip: int, first: bool) -> None:
            keys.append((np.uint64(i << 40) | (parts[chosen, i] ^ np.uint64(flip))).astype(np.int64))
            who.append(own[chosen])
            member.append(np.full(len(chosen), first))
            probe.append(t[chosen, i] >= 0)

        for i, w in enumerate(widths):
            add(i, np.arange(len(own)), 0, True)
            for reach in (1, 2):
                near = np.flatnonzero(t[:, i] >= reach)
                if len(near):
                    for flips in combinations(range(w), reach):
                        add(i, near, sum(1 << f for f in flips), False)
        return {"key": np.concatenate(keys), "print": np.concatenate(who), "member": np.concatenate(member), "probe": np.concatenate(probe)}

    return map_batches(prints, run, "key bigint, print bigint, member boolean, probe boolean", rows=1024)


def _balls(prints: DataFrame) -> DataFrame:
    """near, print: the 65 fingerprints within one bit of each."""
    flips = np.array([0] + [1 << k for k in range(64)], np.uint64)

    def run(b: pa.RecordBatch) -> dict:
        own = b.column(0).to_numpy(zero_copy_only=False)
        return {"near": (own.view(np.uint64)[:, None] ^ flips[None, :]).ravel().view(np.int64), "print": np.repeat(own, len(flips))}

    return map_batches(prints, run, "near bigint, print bigint", rows=4096)


def links(prints: DataFrame, config: Config = Config()) -> DataFrame:
    """a, b: edges between distinct fingerprints (column print) whose components are those of all links."""
    rows = prints.count()
    space = 1 << 30
    near = F.pmod(F.xxhash64(F.lit(3), "print"), F.lit(space)) < int(space * min(1.0, config.sample / max(rows, 1)))
    known = np.array(sorted(r.print for r in prints.where(near).collect()), np.int64).view(np.uint64)
    if rows < 2:
        return prints.select(F.col("print").alias("a"), F.col("print").alias("b")).where(F.lit(False))
    e = written(entries(prints, known, rows, config))
    big = written(e.where("member").groupBy("key").count().where(F.col("count") > config.bucket).select("key"))
    few = e.join(big, "key", "left_anti")
    p, x = few.where("probe").select("key", F.col("print").alias("a")), few.where("member").select("key", F.col("print").alias("b"))
    pairs = p.join(x, "key").where("a <> b and bit_count(a ^ b) <= 2").select("a", "b")
    dense = e.join(big, "key", "left_semi").where("member or probe").select("print").distinct()
    sharing = Window.partitionBy("near")  # at most 65 rows each: so many distinct fingerprints are within one bit
    stars = _balls(dense).select(F.col("print").alias("a"), F.min("print").over(sharing).alias("b")).where("a <> b")
    return written(pairs.union(stars).select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())


def connect(edges: DataFrame) -> DataFrame:
    """a, b with a > b: each node of the edges that is not the least of its component, and that least node.

    Alternating large-star and small-star rounds. A round's least neighbours come from a combined
    aggregation, so a hub of any size is one row a task, and the joins that hand them on may split."""
    edges = edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct()
    before = None
    while True:
        both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.where("b > a").join(low, "a").where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a")
        edges = written(
            small.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b")).union(low.select("a", F.col("m").alias("b"))).distinct()
        )
        now = edges.agg(F.count("*").alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("h")).first()
        if before == (now.n, now.h):
            return edges
        before = (now.n, now.h)


def components(docs: DataFrame, config: Config = Config()) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id for every row of docs.

    component_id is the smallest doc_id that links lead to, its own included. Null and empty texts have
    fingerprint zero, which links like any other. Repeated rows give repeated results; a row without a
    doc_id belongs to its component but cannot name it (component_id is null if no row of the
    component has one). Whole texts count, however long. Other columns are ignored.
    """
    own = written(fingerprints(docs))
    prints = written(own.groupBy("print").agg(F.min("doc_id").alias("first")))
    star = connect(links(prints.select("print"), config))
    member = prints.join(star.select(F.col("a").alias("print"), "b"), "print", "left").select("print", "first", F.coalesce("b", "print").alias("root"))
    member = written(member)
    named = member.groupBy("root").agg(F.min("first").alias("component_id"))
    final = member.join(named, "root").select("print", "component_id")
    return own.join(final, "print").select("doc_id", F.lower(F.lpad(F.hex("print"), 16, "0")).alias("fingerprint"), "component_id")
