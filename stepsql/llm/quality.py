"""Quality classifier: a generalised additive model with pairwise interactions.

Each text gives a few bounded statistics. Their values are cut into at most 48 bins by quantiles of the
training sample. Boosting goes round the features; each visit fits a shallow tree (up to four
leaves over the ordered bins) to the Newton step of the logistic loss and adds it to that feature's
lookup table. Then the pairs whose best 2 x 2 split still lowers the loss most are boosted the same
way into two-way tables. A score is the sum of table entries, one addition per bin.
"""

from __future__ import annotations

from collections import Counter
from dataclasses import dataclass, field
from functools import lru_cache
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_mod, filter_batches, map_batches, pick

FEATURES = (
    "log_chars", "letters", "upper", "digits", "spaces", "marks", "odd_marks", "bars", "wide",
    "word_length", "word_spread", "distinct_words", "top_word", "same_as_before", "line_repeats",
    "line_words", "shouting_words", "marked_words", "distinct_chars",
)


@dataclass(frozen=True)
class Config:
    sample: int = 12_000  # labelled rows that training reads at most (in expectation)
    bins: int = 48
    rounds: int = 60
    pair_rounds: int = 25
    pairs: int = 8
    rate: float = 0.2
    least: float = 8.0  # Hessian weight that a leaf needs, in rows / 4
    seed: int = 11
    reject_below: float = 0.5  # the pipeline rejects under this score


@dataclass
class Model:
    cuts: list[np.ndarray]
    base: float
    single: list[np.ndarray]
    double: dict[tuple[int, int], np.ndarray] = field(default_factory=dict)


@lru_cache(1)
def _kinds() -> np.ndarray:
    """Kind of a code point: 0 other mark, 1 lower or uncased letter, 2 upper, 3 digit, 4 space, 5 usual mark, 6 bar."""
    out = np.zeros(0x110000, np.uint8)
    for c in range(0x33000):
        s = chr(c)
        out[c] = 2 if s.isupper() else 1 if s.isalpha() else 3 if s.isdigit() else 4 if s.isspace() else 5 if s in ".,;:?'\"-()" else 6 if s == "|" else 0
    return out


def measure(text: str) -> list[float]:
    """FEATURES of one whole text; zeros for an empty one."""
    if not text:
        return [0.0] * len(FEATURES)
    codes = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
    n = len(codes)
    kind = np.bincount(_kinds()[codes], minlength=7) / n
    words, lines = text.split(), text.split("\n")
    m = max(1, len(words))
    count = Counter(words)
    length = np.fromiter(map(len, words), np.int64, len(words)) if words else np.zeros(1)
    low = np.minimum(codes, 255)
    return [
        float(np.log1p(n)), kind[1] + kind[2], kind[2], kind[3], kind[4], kind[0] + kind[5], kind[0], kind[6], float((codes > 127).mean()),
        float(length.mean()), float(length.std()), len(count) / m, max(count.values(), default=0) / m,
        sum(map(str.__eq__, words, words[1:])) / m, 1 - len(set(lines)) / len(lines),
        m / len(lines), sum(k for w, k in count.items() if len(w) > 1 and w.isupper()) / m,
        sum(k for w, k in count.items() if not w.isalpha() and not w[:-1].isalpha()) / m,
        len(np.unique(low)) / 256,
    ]


def _tree(g: np.ndarray, h: np.ndarray, least: float, depth: int = 2) -> np.ndarray:
    """Leaf value for every ordered bin: recursive best cuts of gradient sums g under Hessian sums h."""
    whole = g.sum() / (h.sum() + 1.0)
    if depth == 0 or len(g) < 2:
        return np.full(len(g), whole)
    gl, hl = np.cumsum(g)[:-1], np.cumsum(h)[:-1]
    gr, hr = g.sum() - gl, h.sum() - hl
    gain = np.where((hl >= least / 4) & (hr >= least / 4), gl**2 / (hl + 1) + gr**2 / (hr + 1), -np.inf)
    at = int(gain.argmax())
    if gain[at] <= g.sum() ** 2 / (h.sum() + 1) + 1e-9:
        return np.full(len(g), whole)
    return np.concatenate([_tree(g[: at + 1], h[: at + 1], least, depth - 1), _tree(g[at + 1 :], h[at + 1 :], least, depth - 1)])


def _pair_tree(g: np.ndarray, h: np.ndarray, least: float) -> tuple[np.ndarray, float]:
    """Values for a grid of bins from one cut of each axis, and what the best such cut gains."""
    def corner(x: np.ndarray) -> np.ndarray:
        c = x.cumsum(0).cumsum(1)
        a, b, whole = c[:-1, -1:], c[-1:, :-1], c[-1, -1]
        q = c[:-1, :-1]
        return np.stack([q, a - q, b - q, whole - a - b + q])

    if min(g.shape) < 2:
        return np.zeros_like(g), 0.0
    cg, ch = corner(g), corner(h)
    score = np.where((ch >= least / 4).all(0), (cg**2 / (ch + 1)).sum(0), -np.inf)
    i, j = np.unravel_index(int(score.argmax()), score.shape)
    if not np.isfinite(score[i, j]):
        return np.zeros_like(g), 0.0
    v = cg[:, i, j] / (ch[:, i, j] + 1)
    out = np.empty_like(g)
    out[: i + 1, : j + 1], out[: i + 1, j + 1 :], out[i + 1 :, : j + 1], out[i + 1 :, j + 1 :] = v
    return out, float(score[i, j] - g.sum() ** 2 / (h.sum() + 1))


def bins_of(x: np.ndarray, cuts: list[np.ndarray]) -> np.ndarray:
    return np.stack([np.searchsorted(c, x[:, j], side="right") for j, c in enumerate(cuts)], 1)


def train(x: np.ndarray, y: np.ndarray, config: Config = Config()) -> Model:
    cuts = [np.unique(np.quantile(x[:, j], np.linspace(0, 1, config.bins + 1)[1:-1])) for j in range(x.shape[1])]
    b = bins_of(x, cuts)
    sizes = [len(c) + 1 for c in cuts]
    rate = (y.sum() + 1) / (len(y) + 2)
    model = Model(cuts, float(np.log(rate / (1 - rate))), [np.zeros(s) for s in sizes])
    z = np.full(len(y), model.base)

    def step() -> tuple[np.ndarray, np.ndarray]:
        p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        return y - p, p * (1 - p)

    for _ in range(config.rounds):
        for j, size in enumerate(sizes):
            g, h = step()
            add = config.rate * _tree(np.bincount(b[:, j], g, size), np.bincount(b[:, j], h, size), config.least)
            model.single[j] += add
            z += add[b[:, j]]

    def grid(i: int, j: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        cell, shape = b[:, i] * sizes[j] + b[:, j], (sizes[i], sizes[j])
        g, h = step()
        return cell, np.bincount(cell, g, shape[0] * shape[1]).reshape(shape), np.bincount(cell, h, shape[0] * shape[1]).reshape(shape)

    gains = {(i, j): _pair_tree(*grid(i, j)[1:], config.least)[1] for i, j in combinations(range(len(sizes)), 2)}
    best = sorted((k for k in gains if gains[k] > 0), key=lambda k: (-gains[k], k))[: config.pairs]
    model.double = {k: np.zeros((sizes[k[0]], sizes[k[1]])) for k in best}
    for _ in range(config.pair_rounds):
        for i, j in best:
            cell, g, h = grid(i, j)
            add = config.rate * _pair_tree(g, h, config.least)[0]
            model.double[i, j] += add
            z += add.ravel()[cell]
    return model


def score_features(x: np.ndarray, model: Model) -> np.ndarray:
    b = bins_of(x, model.cuts)
    z = np.full(len(x), model.base)
    for j, table in enumerate(model.single):
        z += table[b[:, j]]
    for (i, j), table in model.double.items():
        z += table[b[:, i], b[:, j]]
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def fit(docs: DataFrame, labels: DataFrame, config: Config = Config()) -> Model | None:
    """A model from labelled rows outside fold 1 of 3; None if there are none of either class."""
    wide = F.col("doc_id").cast("bigint").alias("doc_id")  # hashes depend on the type
    marked = pick(labels, "doc_id", "quality").select(wide, "quality").where("quality is not null and doc_id is not null").where(crc_mod("doc_id", 3) != 1)
    n, space = marked.count(), 1 << 30
    near = marked.where(F.pmod(F.xxhash64(F.lit(config.seed), "doc_id"), F.lit(space)) < int(space * min(1.0, config.sample / max(n, 1))))
    near = near.groupBy("doc_id").agg(F.max("quality").alias("quality"))
    # the same hash bound on both sides of the join keeps the texts of other rows out of the shuffle
    texts = pick(docs, "doc_id", "text").select(wide, "text").where(F.pmod(F.xxhash64(F.lit(config.seed), "doc_id"), F.lit(space)) < int(space * min(1.0, config.sample / max(n, 1))))

    def run(b: pa.RecordBatch) -> dict:
        return {"doc_id": b.column(0), "x": [measure(t or "") for t in b.column(1).to_pylist()], "place": b.column(2)}

    # rows that share a doc_id teach once, so there are no more rows than labels drawn
    once = map_batches(texts.withColumn("place", F.xxhash64("text")), run, "doc_id bigint, x array<double>, place bigint").groupBy("doc_id").agg(F.min(F.struct("place", "x")).alias("own"))
    rows = once.join(near, "doc_id").select("doc_id", F.col("own.x").alias("x"), "quality").collect()
    rows.sort(key=lambda r: (r.doc_id, r.x))
    y = np.array([float(r.quality > 0) for r in rows])
    if len(y) == 0 or y.min() == y.max():
        return None
    return train(np.array([r.x for r in rows]), y, config)


def predict(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id, held_out, score, predicted for every row of docs.

    Null texts count as empty ones, which are scored like any other; without a model every score is 0.5.
    Repeated rows give repeated results; held_out is false where doc_id is null. Whole texts count,
    however long. Other columns are ignored."""

    def run(b: pa.RecordBatch) -> dict:
        x = np.array([measure(t or "") for t in b.column(1).to_pylist()]).reshape(-1, len(FEATURES))
        s = score_features(x, model) if model else np.full(len(x), 0.5)
        return {"doc_id": b.column(0), "held_out": b.column(2), "score": s, "predicted": (s >= 0.5).astype(np.int32)}

    rows = pick(docs, "doc_id", "text").select("doc_id", "text", F.coalesce(crc_mod("doc_id", 3) == 1, F.lit(False)).alias("held_out"))
    return map_batches(rows, run, "doc_id bigint, held_out boolean, score double, predicted int")


def keep(docs: DataFrame, model: Model | None, config: Config = Config()) -> DataFrame:
    """The rows of docs that score config.reject_below or more, all columns; all rows without a model."""
    at = docs.columns.index("text")

    def accepted(b: pa.RecordBatch) -> list:
        x = np.array([measure(t or "") for t in b.column(at).to_pylist()]).reshape(-1, len(FEATURES))
        return list(score_features(x, model) >= config.reject_below)

    return filter_batches(docs, accepted) if model else docs
