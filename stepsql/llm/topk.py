"""Exact top-k by inner product over a bit-sliced index.

Components become integers, floor(scale * x). A block of up to 65,536 vectors stores, for each component, the bits of
`value - least value` as bitmaps (slices), one bit a row. For a query, the slices of a component enter a sum
once for every set bit of the query's component, complemented where that is negative, so that all
addends are non-negative; the sum is done on bitmaps by carry-save adders. The lowest slices are left
out at first, which bounds the error from one side. The k-th largest truncated sum is found from the most
significant slice downward, and the rows whose bound reaches it are read back from all slices, scored exactly and
ranked.

The index is written once. Its blocks and the queries are dealt out to cells of a grid, each lane of blocks
meeting each lane of queries in one, so all queries are answered by one job whose tasks hold a bounded share of both. Vectors
whose integers are too large for 64-bit sums are kept beside the slices and scored with unbounded integers.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import pick, ship, written

#: Vectors of up to 512 components below this have scores that fit 64 bits; others go the way of wide vectors.
LIMIT = 1 << 27
WORD = 1 << 63


@dataclass(frozen=True)
class Config:
    k: int = 5
    scale: float = 256.0
    rows: int = 65_536  # rows of an index block at most
    queries: int = 65_536  # queries of a grid cell at most, in expectation
    blocks: int = 32  # index blocks of a grid cell at most, in expectation
    wide: int = 1024  # wide vectors of an index block at most
    dropped: int = 2  # lowest slices left out of the first sum


@dataclass
class Block:
    ids: np.ndarray  # int64
    low: np.ndarray  # int64, by component
    slices: np.ndarray  # uint64 (component, bit, word)


def integers(vector: list[float], scale: float) -> list[int]:
    """floor(scale * x) of finite components, without a limit."""
    return [math.floor(scale * x) if abs(x) < 1e15 else int(x) * int(scale) if scale.is_integer() else math.floor(scale * x) for x in vector]


def quantised(column: pa.Array, scale: float) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row numbers that take part in 64 bits, their integers, as wide as the longest (missing components are zero), and the row numbers of
    wide vectors. Null vectors and those with null or non-finite components are in neither."""
    vectors = column.cast(pa.list_(pa.float64()))
    starts, flat = vectors.offsets.to_numpy(), vectors.values
    x = flat.fill_null(np.nan).to_numpy(zero_copy_only=False)
    ok = np.isfinite(x)
    with np.errstate(invalid="ignore", over="ignore"):
        value = np.floor(x * scale)
    count = lambda bad: np.concatenate([[0], np.cumsum(bad)])[starts[1:]] - np.concatenate([[0], np.cumsum(bad)])[starts[:-1]]
    valid = vectors.is_valid().to_numpy(zero_copy_only=False) & (count(~ok) == 0)
    lengths = starts[1:] - starts[:-1]
    limit = np.where(lengths <= 512, LIMIT, np.floor(np.sqrt(WORD / np.maximum(lengths, 1)))).astype(np.float64)
    wide = valid & (count(np.where(ok, np.abs(value) >= np.repeat(limit, lengths), False)) > 0)
    take = np.flatnonzero(valid & ~wide)
    lengths = lengths[take]
    out = np.zeros((len(take), int(lengths.max(initial=0))), np.int64)
    at = np.repeat(starts[:-1][take] - np.concatenate([[0], np.cumsum(lengths)[:-1]]), lengths) + np.arange(lengths.sum())
    out[np.arange(out.shape[1]) < lengths[:, None]] = value[at].astype(np.int64)
    return take, out, np.flatnonzero(wide)


def build(ids: np.ndarray, values: np.ndarray) -> Block:
    n, d = values.shape
    low = values.min(0) if n else np.zeros(d, np.int64)
    rest = (values - low).astype(np.uint64)
    bits = max(1, int(rest.max(initial=0)).bit_length())
    words = -(-n // 64)
    slices = np.zeros((d, bits, words), np.uint64)
    for b in range(bits):
        packed = np.packbits((rest >> np.uint64(b) & np.uint64(1)).astype(np.uint8).T, axis=1, bitorder="little")
        padded = np.zeros((d, words * 8), np.uint8)
        padded[:, : packed.shape[1]] = packed
        slices[:, b] = padded.view("<u8")
    return Block(ids, low, slices)


def _count(x: np.ndarray) -> int:
    return int(np.bitwise_count(x).sum())


def _sum(addends: list[list[np.ndarray]], words: int) -> list[np.ndarray]:
    """Slices of the sum of bitmaps, given by weight (a power of two each)."""
    out, weight = [], 0
    while weight < len(addends):
        held = addends[weight]
        while len(held) > 1:
            a, b = held.pop(), held.pop()
            half = a ^ b
            if held:
                c = held.pop()
                held.append(half ^ c)
                carry = (a & b) | (half & c)
            else:
                held.append(half)
                carry = a & b
            if weight + 1 == len(addends):
                addends.append([])
            addends[weight + 1].append(carry)
        out.append(held[0] if held else np.zeros(words, np.uint64))
        weight += 1
    return out


def search(block: Block, query: np.ndarray, own: int, k: int, dropped: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and exact scores of the k best rows of a block, ties to the smaller id; rows with id `own` are out."""
    n, (d, bits, words) = len(block.ids), block.slices.shape
    valid = np.full(words, ~np.uint64(0))
    if n % 64:
        valid[-1] = np.uint64((1 << (n % 64)) - 1)
    for i in np.flatnonzero(block.ids == own).tolist():
        valid[i // 64] &= ~np.uint64(1 << (i % 64))
    live = _count(valid)
    q = np.zeros(d, np.int64)
    m = min(d, len(query))
    q[:m] = query[:m]
    cut = min(dropped, bits - 1)
    if live > 4 * k:
        addends: list[list[np.ndarray]] = []
        for c in np.flatnonzero(q).tolist():
            factor, negative = abs(int(q[c])), q[c] < 0
            planes = ~block.slices[c, cut:] if negative else block.slices[c, cut:]
            for f in range(factor.bit_length()):
                if factor >> f & 1:
                    while len(addends) < f + bits - cut:
                        addends.append([])
                    for b in range(bits - cut):
                        addends[f + b].append(planes[b])
        total = _sum(addends, words)
        sure, tied, kth = np.zeros(words, np.uint64), valid.copy(), 0
        for w in range(len(total) - 1, -1, -1):
            up = tied & total[w]
            if _count(sure) + _count(up) >= k:
                tied, kth = up, kth | 1 << w
            else:
                sure, tied = sure | up, tied & ~total[w]
        # a dropped slice adds at most (2 ** cut - 1) * |q| to a sum that was divided by 2 ** cut
        floor = kth - -(-((1 << cut) - 1) * int(np.abs(q).sum()) // (1 << cut))
        if floor > 0:
            above, tied = np.zeros(words, np.uint64), valid.copy()
            for w in range(max(len(total), floor.bit_length()) - 1, -1, -1):
                plane = total[w] if w < len(total) else np.zeros(words, np.uint64)
                if floor >> w & 1:
                    tied = tied & plane
                else:
                    above, tied = above | (tied & plane), tied & ~plane
            valid = above | tied
    rows = np.flatnonzero(np.unpackbits(valid.view(np.uint8), bitorder="little"))
    score, ids = q @ _values(block, rows), block.ids[rows]
    best = np.lexsort((ids, -score))[:k]
    return ids[best], score[best]


def _values(block: Block, rows: np.ndarray) -> np.ndarray:
    """The integers of some rows of a block, (component, row)."""
    bit = block.slices[:, :, rows // 64] >> (rows % 64).astype(np.uint64) & np.uint64(1)
    return (bit.astype(np.int64) << np.arange(block.slices.shape[1])[None, :, None]).sum(1) + block.low[:, None]


def search_wide(ids: list[int], rows: list[list[int]], query: list[int], own: int, k: int) -> list[tuple[int, int]]:
    """(id, score) of the k best rows with unbounded integers; a score beyond 64 bits is no score."""
    scored = [(sum(a * b for a, b in zip(row, query)), i) for i, row in zip(ids, rows) if i != own]
    return [(i, x) for x, i in sorted((x for x in scored if -WORD <= x[0] < WORD), key=lambda x: (-x[0], x[1]))[:k]]


_FIELDS = "ids binary, low binary, slices binary, bits int"


def index(vectors: DataFrame, config: Config = Config()) -> DataFrame:
    """The bit-sliced index of columns vec_id, embedding: a row for each block. A block of wide vectors has no bits; low holds their
    components."""
    ship(vectors.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def out(held: list) -> pa.RecordBatch:
            wide = max(v.shape[1] for _, v in held)
            block = build(np.concatenate([i for i, _ in held]), np.concatenate([np.pad(v, ((0, 0), (0, wide - v.shape[1]))) for _, v in held]))
            return pa.RecordBatch.from_pydict(
                {"ids": [block.ids.tobytes()], "low": [block.low.tobytes()], "slices": [block.slices.tobytes()], "bits": pa.array([block.slices.shape[1]], pa.int32())}
            )

        held, n = [], 0
        for b in batches:
            take, value, beyond = quantised(b.column(1), config.scale)
            every = b.column(0).to_numpy(zero_copy_only=False)
            ids = every[take]
            for at in range(0, len(ids), config.rows):
                part = slice(at, at + config.rows)
                if n + len(ids[part]) > config.rows and held:
                    yield out(held)
                    held, n = [], 0
                held.append((ids[part], value[part]))
                n += len(ids[part])
            for at in range(0, len(beyond), config.wide):
                some = beyond[at : at + config.wide]
                vectors_ = b.column(1).take(pa.array(some)).to_pylist()
                d = max(map(len, vectors_))
                raw = np.array([v + [0.0] * (d - len(v)) for v in vectors_], np.float64)
                yield pa.RecordBatch.from_pydict({"ids": [every[some].astype(np.int64).tobytes()], "low": [raw.tobytes()], "slices": [b""], "bits": pa.array([0], pa.int32())})
        if n:
            yield out(held)

    rows = pick(vectors, "vec_id", "embedding").where("vec_id is not null").select(F.col("vec_id").cast("bigint").alias("vec_id"), F.col("embedding").cast("array<double>"))
    return rows.mapInArrow(run, _FIELDS)


def _lanes(blocks: int, queries: int, vectors: int, cores: int, config: Config) -> tuple[int, int]:
    """Lanes of index blocks and of queries: cells within the bounds, four for each core if there is that much to deal out, and copies
    of the larger side few."""
    cells = 4 * cores
    by_query = max(-(-queries // config.queries), min(-(-queries // 64), max(round(math.sqrt(cells * queries / max(vectors, 1))), -(-cells // max(blocks, 1))), cells), 1)
    return max(-(-blocks // config.blocks), min(blocks, -(-cells // by_query)), 1), by_query


def top_k(vectors: DataFrame, queries: DataFrame, config: Config = Config()) -> DataFrame:
    """query_id, rank, vec_id, score: the k best rows of vectors for each row of queries (columns vec_id, embedding).

    Score is the inner product of floor(scale * x); ties go to the smaller vec_id; rows with the query's own vec_id
    are no candidates. Vectors that are null or hold null or non-finite components, rows without a vec_id, and pairs whose score does not fit
    64 bits take no part; missing components of shorter vectors count as zero. Candidate rows that
    repeat a vec_id each count; of valid queries that share a vec_id the one with the least vector counts.
    An empty table gives no rows. Other columns are ignored.
    """
    spark = vectors.sparkSession
    blocks = written(index(vectors, config))
    finite = F.forall("q", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    asked = pick(queries, "vec_id", "embedding").select(F.col("vec_id").cast("bigint").alias("query_id"), F.col("embedding").cast("array<double>").alias("q")).where(F.col("query_id").isNotNull() & F.col("q").isNotNull() & finite)
    asked = written(asked.groupBy("query_id").agg(F.min("q").alias("q")))
    size = blocks.agg(F.count("*").alias("n"), F.coalesce(F.sum(F.length("ids") / 8), F.lit(0)).cast("bigint").alias("v")).first()
    by_block, by_query = _lanes(size.n, asked.count(), size.v, spark.sparkContext.defaultParallelism, config)
    lane = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    left = blocks.withColumn("r", F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(by_block)).cast("int")).withColumn("c", lane(by_query))
    right = asked.withColumn("c", F.pmod(F.xxhash64("query_id"), F.lit(by_query)).cast("int")).withColumn("r", lane(by_block))
    met = left.groupBy("r", "c").cogroup(right.groupBy("r", "c")).applyInArrow(_cell(config), "query_id bigint, vec_id bigint, score bigint")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return met.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= config.k).select("query_id", "rank", "vec_id", "score")


def _cell(config: Config):
    """The k best rows of some index blocks for some queries."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        best: dict[int, list[tuple[int, int]]] = {}
        if left.num_rows and right.num_rows:
            column = right["q"].combine_chunks()
            take, value, beyond = quantised(column, config.scale)
            every = right["query_id"].to_numpy()
            plain = list(zip(every[take].tolist(), value))
            wide = [(int(every[i]), integers(column[int(i)].as_py(), config.scale)) for i in beyond]
            for row in left.select(["ids", "low", "slices", "bits"]).to_pylist():
                ids = np.frombuffer(row["ids"], np.int64)
                if row["bits"]:
                    low = np.frombuffer(row["low"], np.int64)
                    block = Block(ids, low, np.frombuffer(row["slices"], np.uint64).reshape(len(low), row["bits"], -(-len(ids) // 64)))
                    for i, v in plain:
                        found, score = search(block, v, i, config.k, config.dropped)
                        best.setdefault(i, []).extend(zip(found.tolist(), score.tolist()))
                    exact = _values(block, np.arange(len(ids))).T.tolist() if wide else []
                    slow = wide
                else:
                    exact = [integers(v, config.scale) for v in np.frombuffer(row["low"], np.float64).reshape(len(ids), -1).tolist()]
                    slow = wide + [(i, v.tolist()) for i, v in plain]
                for i, v in slow:
                    best.setdefault(i, []).extend(search_wide(ids.tolist(), exact, v, i, config.k))
        rows = [(q, i, x) for q, found in best.items() for i, x in sorted(found, key=lambda f: (-f[1], f[0]))[: config.k]]
        return pa.table({name: pa.array([r[n] for r in rows], pa.int64()) for n, name in enumerate(("query_id", "vec_id", "score"))})

    return run
