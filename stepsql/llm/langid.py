"""Language identification: averaged hashed subword embeddings under a linear softmax.

A text is lower-cased, everything but letters counts as a gap, and its character 1- to 4-grams are
hashed to rows of an embedding table; the mean of those rows goes through a linear softmax. The model
is trained by stochastic gradient descent in numpy on a bounded sample of labelled rows, a temperature
is then fitted on the part of the sample that the descent did not see, and the lowest calibrated
score that rows of that part deserve becomes the floor under which a prediction is rejected.
As the mean and the softmax input are both linear, scoring needs only the product of the two tables.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_mod, filter_batches, map_batches, pick

BITS = 13
UNKNOWN = "und"


@dataclass(frozen=True)
class Config:
    sample: int = 4000  # labelled rows that training reads at most (in expectation)
    dim: int = 16
    epochs: int = 14
    rate: float = 40.0
    batch: int = 64
    seed: int = 7
    reject_share: float = 0.001  # of held-back rows that may fall under the floor
    reject_cap: float = 0.5  # the floor is never above this


@dataclass
class Model:
    languages: list[str]
    table: np.ndarray  # hashed subword x language: contribution to the softmax input
    bias: np.ndarray
    temperature: float
    floor: float


@lru_cache(1)
def _fold() -> np.ndarray:
    """Code point to lower-case letter, or a space."""
    out = np.full(0x110000, 32, np.uint32)
    for c in range(0x33000):  # no letters are assigned beyond
        if chr(c).isalpha():
            low = chr(c).lower()
            out[c] = ord(low) if len(low) == 1 else c
    return out


def subwords(text: str) -> np.ndarray | None:
    """Counts by hash, or None for a text without a letter."""
    a = _fold()[np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)]
    if not (a != 32).any():
        return None
    a = np.concatenate([[np.uint32(32)], a, [np.uint32(32)]]).astype(np.uint32)
    total, h = np.zeros(1 << BITS, np.int64), np.zeros(len(a), np.uint32)
    for n in range(1, 5):
        if len(a) < n:
            break
        h = h[: len(a) - n + 1] * np.uint32(0x01000193) ^ (a[n - 1 :] + np.uint32(n))
        key = (h * np.uint32(0x9E3779B1)) >> np.uint32(32 - BITS)
        use = a[: len(h)] != 32 if n == 1 else slice(None)
        total += np.bincount(key[use], minlength=1 << BITS)
    return total


def _softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(1, keepdims=True))
    return e / e.sum(1, keepdims=True)


def train(rows: list[tuple[np.ndarray, np.ndarray, str]], config: Config = Config()) -> Model:
    """rows: (hashes, counts, language). Order of rows does not matter if they are sorted before."""
    languages = sorted({r[2] for r in rows})
    y = np.array([languages.index(r[2]) for r in rows])
    rng = np.random.default_rng(config.seed)
    held = rng.random(len(rows)) < 0.2
    if held.all() or not held.any() or len(rows) < 50:
        held[:] = False
    embedding = rng.normal(0, 0.1, (1 << BITS, config.dim)).astype(np.float32)
    weight = rng.normal(0, 0.1, (config.dim, len(languages))).astype(np.float32)
    bias = np.zeros(len(languages), np.float32)
    share = [(h, (c / c.sum()).astype(np.float32)[:, None]) for h, c, _ in rows]
    own = np.flatnonzero(~held)
    for epoch in range(config.epochs):
        rate = config.rate * (1 - epoch / config.epochs)
        for part in np.array_split(rng.permutation(own), max(1, len(own) // config.batch)):
            mean = np.stack([(embedding[share[i][0]] * share[i][1]).sum(0) for i in part])
            p = _softmax(mean @ weight + bias)
            p[np.arange(len(part)), y[part]] -= 1
            p /= len(part)
            back = p @ weight.T
            weight -= rate * 0.1 * (mean.T @ p)
            bias -= rate * 0.01 * p.sum(0)
            for row, i in enumerate(part):
                embedding[share[i][0]] -= rate * share[i][1] * back[row]
    table = (embedding @ weight).astype(np.float64)
    check = np.flatnonzero(held) if held.any() else own
    z = np.stack([(table[share[i][0]] * share[i][1]).sum(0) for i in check]) + bias if len(check) else np.zeros((0, len(languages)))
    best, temperature = np.inf, 1.0
    for t in np.geomspace(0.05, 20, 60):
        loss = -np.log(np.maximum(_softmax(z / t)[np.arange(len(check)), y[check]], 1e-12)).mean() if len(check) else 0
        if loss < best:
            best, temperature = loss, float(t)
    top = _softmax(z / temperature).max(1) if len(check) else np.ones(1)
    return Model(languages, table, bias.astype(np.float64), temperature, float(min(config.reject_cap, np.quantile(top, config.reject_share))))


def sample(docs: DataFrame, config: Config) -> list[tuple[np.ndarray, np.ndarray, str]]:
    """Hashed counts of about config.sample labelled rows, drawn by a hash of doc_id and text; rows that are alike count once."""
    labelled = pick(docs, "doc_id", "text", "lang").where("lang is not null and text is not null")
    labelled = labelled.where(crc_mod("doc_id", 4) != 2)
    n = labelled.select("doc_id").count()
    space = 1 << 30
    near = labelled.where(F.pmod(F.xxhash64(F.lit(config.seed), "doc_id", "text"), F.lit(space)) < int(space * min(1.0, config.sample / max(n, 1))))

    def run(b: pa.RecordBatch) -> dict:
        found = [subwords(t) for t in b.column(1).to_pylist()]
        at = [np.flatnonzero(f) if f is not None else np.zeros(0, int) for f in found]
        return {
            "doc_id": b.column(0),
            "lang": b.column(2),
            "hashes": [a.astype("<u2").tobytes() for a in at],
            "counts": [f[a].astype("<u4").tobytes() if f is not None else b"" for f, a in zip(found, at)],
        }

    rows = map_batches(near, run, "doc_id bigint, lang string, hashes binary, counts binary").where("length(hashes) > 0").distinct().collect()
    rows.sort(key=lambda r: (r.doc_id is None, r.doc_id, r.lang, r.hashes))
    return [(np.frombuffer(r.hashes, "<u2"), np.frombuffer(r.counts, "<u4").astype(np.float64), r.lang) for r in rows]


def fit(docs: DataFrame, config: Config = Config()) -> Model | None:
    """A model from labelled rows outside fold 2 of 4; None if there are none."""
    rows = sample(docs, config)
    return train(rows, config) if rows else None


def tell(text: str | None, model: Model | None) -> tuple[str, float, bool]:
    """Language, calibrated score, and whether the prediction is rejected."""
    counts = subwords(text) if text and model else None
    if counts is None:
        return UNKNOWN, 0.0, True
    p = _softmax(((counts @ model.table) / counts.sum() + model.bias)[None] / model.temperature)[0]
    best = int(p.argmax())
    return model.languages[best], float(p[best]), bool(p[best] < model.floor)


def keep(docs: DataFrame, model: Model | None) -> DataFrame:
    """The rows of docs that are not rejected, all columns. Without a model: those with a letter in their text."""
    at = docs.columns.index("text")

    def accepted(b: pa.RecordBatch) -> list:
        texts = b.column(at).to_pylist()
        return [not tell(t, model)[2] for t in texts] if model else [bool(t) and subwords(t) is not None for t in texts]

    return filter_batches(docs, accepted)


def predict(docs: DataFrame, model: Model | None) -> DataFrame:
    """doc_id, held_out, lang_pred, score, rejected for every row of docs.

    Null texts, texts without a letter (empty ones too), and every text where there is no model, get
    `und`, score 0 and are rejected; other rows are rejected if their calibrated score is under the
    model's floor. Repeated rows give repeated results; held_out is false where doc_id is null; ties go
    to the first language by name. Whole texts count, however long. Other columns are ignored."""

    def run(b: pa.RecordBatch) -> dict:
        found = [tell(text, model) for text in b.column(1).to_pylist()]
        names, scores, out = zip(*found) if found else ((), (), ())
        return {"doc_id": b.column(0), "held_out": b.column(2), "lang_pred": names, "score": scores, "rejected": out}

    rows = pick(docs, "doc_id", "text").select("doc_id", "text", F.coalesce(crc_mod("doc_id", 4) == 2, F.lit(False)).alias("held_out"))
    return map_batches(rows, run, "doc_id bigint, held_out boolean, lang_pred string, score double, rejected boolean")
