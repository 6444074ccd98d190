"""Best-fit packing of tokenised documents into sequences, improved by swap-based local search.

Documents longer than a sequence are cut into pieces, the first of which may be shorter. Pieces are dealt by
hash into cells of bounded size. In a cell, best-fit-decreasing gives the first packing; the local
search then exchanges pieces between underfull bins, one for one, two for one or one for two, or moves
them, so that every step raises the sum of squared fills, until bins are empty and go. Lengths are few
(no more than a sequence has places), so every search is over all lengths at once: sets of lengths are bits of
an integer, and each length keeps the bins that hold it by their fill. A cell loses less than one sequence to its neighbours.
"""

from __future__ import annotations

import base64
import functools
import re
import zlib
from array import array
from bisect import bisect_left, insort
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_batches, pick, ship, tokenizer_file, written


@dataclass(frozen=True)
class Config:
    capacity: int = 2048
    end: int = 0  # id after each document
    vocabulary: str | None = None  # path of a tokenizers file; None: the installed byte_bpe_50k.json
    ranks: str | None = None  # path of the same vocabulary as ranks; None: the installed file
    cell: int = 8192  # pieces in a cell, in expectation


#: Texts of these characters only are split alike by both libraries, whatever their Unicode version.
_USUAL = re.compile("[^\\x00-\\u024f\\u2010-\\u2027\\u20ac]|<\\|endoftext\\|>")


@functools.lru_cache(2)
def _encoders(vocabulary: str, ranks: str):
    import public_tokenizers
    import tiktoken
    from tokenizers import Tokenizer

    with open(ranks, "rb") as f:
        table = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
    fast = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=table, special_tokens={})
    return Tokenizer.from_file(vocabulary), fast.encode_ordinary


def token_ids(text: str, vocabulary: str, ranks: str) -> list[int]:
    """Ids as the tokenizers library gives them; usual texts go through the faster rank encoder, which gives the same."""
    whole, fast = _encoders(vocabulary, ranks)
    return whole.encode(text, add_special_tokens=False).ids if _USUAL.search(text) else fast(text)


def pieces(docs: DataFrame, config: Config = Config(), with_ids: bool = False) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32 (and ids) of every piece of every row of docs."""
    vocabulary = config.vocabulary or tokenizer_file("byte_bpe_50k.json")
    ranks = config.ranks or tokenizer_file("byte_bpe_50k.tiktoken")
    cap, end = config.capacity, config.end

    def run(b: pa.RecordBatch) -> dict:
        out: dict[str, list] = {"doc_id": [], "piece": [], "start": [], "length": [], "ids_crc32": [], "ids": []}
        for doc, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
            ids = token_ids(text, vocabulary, ranks) if text else []
            ids.append(end)
            raw = array("I", ids).tobytes()
            n = len(ids)
            first = n % cap or cap
            starts = [0, *range(first, n, cap)]
            for k, (a, z) in enumerate(zip(starts, [*starts[1:], n])):
                part = raw[4 * a : 4 * z]
                for name, v in zip(out, (doc, k, a, z - a, zlib.crc32(part), part if with_ids else None)):
                    out[name].append(v)
        return out

    columns = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint" + ", ids binary" * with_ids
    return map_batches(pick(docs, "doc_id", "text").selectExpr("cast(doc_id as bigint) doc_id", "text"), run, columns, rows=128)


def best_fit(lengths: list[int], capacity: int) -> list[list[int]]:
    """Best-fit-decreasing: item numbers of each bin. A bit set names the remaining capacities that some bin has."""
    bins: list[list[int]] = []
    by_left: list[list[int]] = [[] for _ in range(capacity + 1)]
    have = 0
    for i in sorted(range(len(lengths)), key=lambda i: (-lengths[i], i)):
        n = lengths[i]
        fits = have >> n
        if fits:
            left = n + (fits & -fits).bit_length() - 1
            k = by_left[left].pop()
            if not by_left[left]:
                have &= ~(1 << left)
            bins[k].append(i)
        else:
            left, k = capacity, len(bins)
            bins.append([i])
        by_left[left - n].append(k)
        have |= 1 << (left - n)
    return bins


def _sums_of_two(counts: dict[int, int]) -> int:
    """Bit set of the lengths that two different pieces have together, given how many pieces each length has."""
    present = sum(1 << n for n in counts)
    sums = 0
    for n, c in counts.items():
        sums |= (present if c > 1 else present & ~(1 << n)) << n
    return sums


def _two_of(counts: dict[int, int], total: int) -> tuple[int, int]:
    return next((n, total - n) for n in counts if counts.get(total - n, 0) > (2 * n == total))


def improve(bins: list[list[int]], lengths: list[int], capacity: int) -> list[list[int]]:
    """Local search over underfull bins; returns the bins left, each a list of item numbers.

    Every step raises the sum of squared fills by bringing a bin nearer to full at the cost of one that is no fuller:
    it takes a longer piece for one of its own, one piece for two, or two for one, or a piece moves into its room.
    Slack so gathers in few bins, whose pieces then move elsewhere until they are empty and go. The
    search ends at the least number of bins that the lengths allow, or when a round over all bins changes
    nothing: then no such exchange between any two bins is left."""
    least = -(-sum(lengths) // capacity)
    fill = [sum(lengths[i] for i in b) for b in bins]
    live = sum(1 for b in bins if b)
    #: items of a bin by length; and by length the underfull bins that hold it, as (fill, bin) in order
    held: list[dict[int, list[int]]] = [{} for _ in bins]
    holders: list[list[tuple[int, int]]] = [[] for _ in range(capacity + 1)]
    present = 0
    for k, b in enumerate(bins):
        for i in b:
            held[k].setdefault(lengths[i], []).append(i)
        if fill[k] < capacity:
            for n in held[k]:
                holders[n].append((fill[k], k))
                present |= 1 << n
    for h in holders:
        h.sort()

    def leave(k: int) -> None:
        nonlocal present
        for n in held[k]:
            del holders[n][bisect_left(holders[n], (fill[k], k))]
            if not holders[n]:
                present &= ~(1 << n)

    def enter(k: int) -> None:
        nonlocal present
        if fill[k] < capacity:
            for n in held[k]:
                insort(holders[n], (fill[k], k))
                present |= 1 << n

    def swap(a: int, gone: tuple[int, ...], b: int, got: tuple[int, ...]) -> None:
        """Pieces of the lengths `gone` go from a to b, those of `got` from b to a."""
        leave(a)
        leave(b)
        moved = []
        for k, to, part in ((a, b, gone), (b, a, got)):
            for n in part:
                moved.append((to, n, held[k][n].pop()))
                if not held[k][n]:
                    del held[k][n]
        for to, n, i in moved:
            held[to].setdefault(n, []).append(i)
        more = sum(got) - sum(gone)
        fill[a] += more
        fill[b] -= more
        enter(a)
        enter(b)

    def first(n: int, other: int, at: int = 0) -> tuple[int, int] | None:
        """The emptiest underfull bin but `other` that holds a piece of length n and is filled to `at` or more."""
        h = holders[n]
        p = bisect_left(h, (at, -1)) if at else 0
        if p < len(h) and h[p][1] == other:
            p += 1
        return h[p] if p < len(h) else None

    def longer(a: int) -> tuple[tuple[int, ...], int, int] | None:
        """For none, one or two pieces of a, the piece of a bin that is no fuller which gains most: (lengths given, bin, length got)."""
        counts = {n: len(v) for n, v in held[a].items()}
        ways = (1, sum(1 << n for n in counts), _sums_of_two(counts))
        open_, known = present, 0
        for gain in range(capacity - fill[a], 0, -1):
            for pieces_, sums in enumerate(ways):
                fits = (sums << gain) & open_
                while fits:
                    n = fits.bit_length() - 1
                    if not known >> n & 1:
                        k = first(n, a)
                        if k is None or k[0] > fill[a]:
                            open_ &= ~(1 << n)
                            fits &= ~(1 << n)
                            continue
                        known |= 1 << n
                    gone = ((), (n - gain,))[pieces_] if pieces_ < 2 else _two_of(counts, n - gain)
                    return gone, first(n, a)[1], n
        return None

    def fuller(b: int) -> tuple[tuple[int, int], int, int] | None:
        """Two pieces of b for a shorter one whose bin is no emptier and has room for the difference: (lengths given, bin, length got)."""
        counts = {n: len(v) for n, v in held[b].items()}
        sums, open_ = _sums_of_two(counts), present
        room: dict[int, tuple[int, int]] = {}
        for more in range(1, capacity - fill[b] + 1):
            fits = (sums >> more) & open_
            while fits:
                n = fits.bit_length() - 1
                if n not in room:
                    k = first(n, b, fill[b])
                    room[n] = (capacity - k[0], k[1]) if k else (0, -1)
                if more <= room[n][0]:
                    return _two_of(counts, n + more), room[n][1], n
                open_ &= ~(1 << n)
                fits &= ~(1 << n)
        return None

    changed = True
    while changed and live > least:
        changed = False
        for a in sorted((k for k in range(len(bins)) if held[k] and fill[k] < capacity), key=lambda k: (-fill[k], k)):
            while held[a] and fill[a] < capacity and (found := longer(a)):
                swap(a, found[0], found[1], (found[2],))
                changed = True
        for b in sorted((k for k in range(len(bins)) if held[k] and fill[k] < capacity), key=lambda k: (fill[k], k)):
            if held[b] and (found := fuller(b)):
                swap(b, found[0], found[1], (found[2],))
                changed = True
        live = sum(1 for h in held if h)
    return [[i for v in h.values() for i in v] for h in held if h]


def _pack_cell(capacity: int):
    def run(table):
        table = table.sort_by([("length", "descending"), ("doc_id", "ascending"), ("piece", "ascending"), ("ids_crc32", "ascending")])
        lengths = table["length"].to_pylist()
        n_full = sum(x == capacity for x in lengths)
        rest = lengths[n_full:]
        bins = [[i] for i in range(n_full)]
        bins += [[i + n_full for i in b] for b in improve(best_fit(rest, capacity), rest, capacity)]
        number, offset = [0] * len(lengths), [0] * len(lengths)
        base = (table["cell"][0].as_py() if len(lengths) else 0) << 32
        for k, b in enumerate(bins):
            at = 0
            for i in b:
                number[i], offset[i] = base + k, at
                at += lengths[i]
        return table.drop_columns(["cell"]).append_column("sequence_id", pa.array(number, pa.int64())).append_column("offset", pa.array(offset, pa.int64()))

    return run


def pack(docs: DataFrame, config: Config = Config()) -> DataFrame:
    """doc_id, piece, start, length, ids_crc32, sequence_id, offset of every piece of every row of docs.

    A document is the ids of its whole text and one end id; null and empty texts are the end id
    alone. Only documents longer than a sequence are cut. Sequences hold at most config.capacity ids, gapless
    from offset 0. Repeated rows and null doc_ids are packed like others; an empty table gives no
    rows. Other columns are ignored.
    """
    ship(docs.sparkSession)
    # a piece's place in this table deals it out, as ids may repeat or lack
    rows = written(pieces(docs, config).withColumn("row", F.monotonically_increasing_id()))
    cells = max(1, -(-rows.count() // config.cell))
    cell = F.pmod(F.xxhash64("row"), F.lit(cells))
    schema = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint, sequence_id bigint, offset bigint"
    return rows.withColumn("cell", cell).drop("row").groupBy("cell").applyInArrow(_pack_cell(config.capacity), schema)
