"""Byte-level BPE encoding and decoding with segment trees.

A piece (one match of the split pattern) is a row of byte positions. A segment tree over the
positions keeps, in every node, the smallest key `rank of the pair that starts here << 40 | position`
below it, so the root names the leftmost pair of the lowest rank. A merge gives the left position
the merged token, unlinks the right one and updates three leaves (left, right, previous live
neighbour), each along one path to the root.

Pieces of up to 64 bytes run together, a row of numpy trees each; longer ones run alone. Pieces
that were met before come from a bounded table in each worker.
"""

from __future__ import annotations

import base64
import functools
import hashlib
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .common import map_batches, pick, tokenizer_file

NONE = np.iinfo(np.int64).max
SHIFT, LOW = 40, (1 << 40) - 1
LONGEST_ROW, ROWS, KEPT = 64, 16_384, 250_000


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}


class SegmentBpe:
    """Encoder and decoder for one rank file. Ids equal ranks."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.split = regex.compile(pattern).findall
        self.words = [b""] * (max(ranks.values()) + 1)
        for word, rank in ranks.items():
            self.words[rank] = word
        self.byte_ids = np.array([ranks[bytes([b])] for b in range(256)], np.int64)
        pairs = {}
        for word, rank in ranks.items():
            for cut in range(1, len(word)):
                a, b = ranks.get(word[:cut]), ranks.get(word[cut:])
                if a is not None and b is not None:
                    pairs[a << 20 | b] = rank
        self.pairs = pairs
        self.pair_keys = np.array(sorted(pairs), np.int64)
        self.pair_ranks = np.array([pairs[k] for k in self.pair_keys.tolist()], np.int64)
        self.table: dict[str, bytes] = {}

    def _leaf(self, left: np.ndarray, right: np.ndarray, at: np.ndarray, live: np.ndarray) -> np.ndarray:
        want = left << 20 | right
        i = np.minimum(np.searchsorted(self.pair_keys, want), len(self.pair_keys) - 1)
        return np.where(live & (self.pair_keys[i] == want), self.pair_ranks[i] << SHIFT | at, NONE)

    def _encode_rows(self, pieces: list[bytes]) -> list[bytes]:
        """All pieces at once; all have at most LONGEST_ROW bytes."""
        lengths = np.array([len(p) for p in pieces])
        width = max(2, 1 << (int(lengths.max()) - 1).bit_length())
        n = len(pieces)
        ids = np.zeros((n, width + 1), np.int64)
        filled = np.arange(width) < lengths[:, None]
        ids[:, :width][filled] = self.byte_ids[np.frombuffer(b"".join(pieces), np.uint8)]
        after = np.minimum(np.arange(1, width + 2), lengths[:, None])
        before = np.tile(np.arange(-1, width), (n, 1))
        places = np.arange(width)
        tree = [self._leaf(ids[:, :-1], ids[:, 1:], places, places + 1 < lengths[:, None])]
        while tree[-1].shape[1] > 1:
            tree.append(np.minimum(tree[-1][:, 0::2], tree[-1][:, 1::2]))
        alive = np.arange(n)
        dead = np.zeros((n, width), bool)
        while True:
            root = tree[-1][alive, 0]
            alive, root = alive[root != NONE], root[root != NONE]
            if not len(alive):
                break
            i, token = root & LOW, root >> SHIFT
            j = after[alive, i]
            k, p, end = after[alive, j], before[alive, i], lengths[alive]
            ids[alive, i], after[alive, i], dead[alive, j] = token, k, True
            before[alive, np.minimum(k, width)] = i
            tree[0][alive, i] = self._leaf(token, ids[alive, k], i, k < end)
            tree[0][alive, j] = NONE
            has = p >= 0
            q = np.maximum(p, 0)
            tree[0][alive, q] = np.where(has, self._leaf(ids[alive, q], token, q, has), tree[0][alive, q])
            for level in range(1, len(tree)):
                for at in (i, j, q):
                    up = at >> level
                    tree[level][alive, up] = np.minimum(tree[level - 1][alive, 2 * up], tree[level - 1][alive, 2 * up + 1])
        live = filled & ~dead
        flat, ends = ids[:, :width][live].astype("<u4").tobytes(), np.cumsum(live.sum(1)) * 4
        return [flat[a:b] for a, b in zip([0, *ends[:-1].tolist()], ends.tolist())]

    def _encode_long(self, piece: bytes) -> bytes:
        """One piece of any length."""
        n = len(piece)
        width = 1 << (n - 1).bit_length()
        ids = self.byte_ids[np.frombuffer(piece, np.uint8)].tolist()
        pairs, none = self.pairs, int(NONE)
        tree = [none] * (2 * width)

        def leaf(a: int, b: int) -> int:
            rank = pairs.get(ids[a] << 20 | ids[b])
            return none if rank is None else rank << SHIFT | a

        for a in range(n - 1):
            tree[width + a] = leaf(a, a + 1)
        for a in range(width - 1, 0, -1):
            tree[a] = min(tree[2 * a], tree[2 * a + 1])
        after, before, dead = list(range(1, n + 1)), list(range(-1, n)), bytearray(n)
        while tree[1] != none:
            i, token = tree[1] & LOW, tree[1] >> SHIFT
            j = after[i]
            k, p = after[j], before[i]
            ids[i], after[i], dead[j] = token, k, 1
            before[k] = i
            changed = [(j, none), (i, leaf(i, k) if k < n else none)]
            if p >= 0:
                changed.append((p, leaf(p, i)))
            for at, key in changed:
                at += width
                tree[at] = key
                while at > 1:
                    at >>= 1
                    low = min(tree[2 * at], tree[2 * at + 1])
                    if tree[at] == low:
                        break
                    tree[at] = low
        return np.array([ids[a] for a in range(n) if not dead[a]], "<u4").tobytes()

    def learn(self, pieces: Iterable[str]) -> None:
        """Put the ids of these pieces into the table."""
        if len(self.table) > KEPT:
            self.table.clear()
        new = [(p, p.encode()) for p in set(pieces) if p not in self.table]
        new.sort(key=lambda x: len(x[1]))
        short = [x for x in new if len(x[1]) <= LONGEST_ROW]
        at = 0
        while at < len(short):
            width = 1 << max(1, (len(short[at][1]) - 1).bit_length())
            end = at
            while end < len(short) and end - at < ROWS and len(short[end][1]) <= width:
                end += 1
            self.table.update(zip((p for p, _ in short[at:end]), self._encode_rows([b for _, b in short[at:end]])))
            at = end
        self.table.update((p, self._encode_long(b)) for p, b in new[len(short) :])

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        return self.encode_all([text])[0]

    def encode_all(self, texts: list[str]) -> list[bytes]:
        split = [self.split(t) for t in texts]
        self.learn(p for s in split for p in s)
        get = self.table.__getitem__
        return [b"".join(map(get, s)) for s in split]

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.words.__getitem__, np.frombuffer(ids, "<u4").tolist()))


@functools.lru_cache(4)
def encoder(path: str, pattern: str) -> SegmentBpe:
    return SegmentBpe(read_ranks(path), pattern)


def encode_documents(docs: DataFrame, vocabulary: str | None = None, pattern: str | None = None, keep_ids: bool = True) -> DataFrame:
    """doc_id, n_tokens, ids (little-endian unsigned 32-bit), ids_sha256, decoded_sha256 for every row of docs.

    vocabulary: path of a rank file (the same on every executor); pattern: what splits a text.
    Null and empty texts have no ids and decode to no bytes; repeated rows give repeated results;
    a null doc_id stays null; other columns are ignored.
    """
    import public_tokenizers

    path = vocabulary or tokenizer_file("byte_bpe_multi_50k.tiktoken")
    pattern = pattern or public_tokenizers.PATTERN

    def run(b: pa.RecordBatch) -> dict:
        own = encoder(path, pattern)
        ids = own.encode_all([t or "" for t in b.column(1).to_pylist()])
        out = {
            "doc_id": b.column(0),
            "n_tokens": [len(x) // 4 for x in ids],
            "ids_sha256": [hashlib.sha256(x).hexdigest() for x in ids],
            "decoded_sha256": [hashlib.sha256(own.decode(x)).hexdigest() for x in ids],
        }
        return out | {"ids": ids} if keep_ids else out

    columns = "doc_id bigint, n_tokens bigint, ids_sha256 string, decoded_sha256 string" + ", ids binary" * keep_ids
    return map_batches(pick(docs, "doc_id", "text").selectExpr("cast(doc_id as bigint) doc_id", "text"), run, columns)


def decode_ids(rows: DataFrame, vocabulary: str | None = None, pattern: str | None = None) -> DataFrame:
    """doc_id, text of rows with doc_id and ids (as encode_documents returns them). Null ids give an empty text."""
    import public_tokenizers

    path = vocabulary or tokenizer_file("byte_bpe_multi_50k.tiktoken")
    pattern = pattern or public_tokenizers.PATTERN

    def run(b: pa.RecordBatch) -> dict:
        own = encoder(path, pattern)
        return {"doc_id": b.column(0), "text": [own.decode(x or b"").decode("utf-8", "replace") for x in b.column(1).to_pylist()]}

    return map_batches(pick(rows, "doc_id", "ids"), run, "doc_id bigint, text string")
