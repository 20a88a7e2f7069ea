"""Quality by attention over passages (gated multiple-instance learning).

A document is a bag of passages of ``PASSAGE`` bytes, all of them. A passage
is encoded by the shares of its character classes and pairs of classes and by
how often it repeats its words; a small layer embeds it, a gated attention
weighs it against the document's others, and a logistic unit scores the
weighted sum. Only documents carry labels; the weights are learned from these.

The fit reads a bounded, documented sample of labelled documents (``fit_rows``,
by the hash of the id), all passages of each; scores cover whole texts of all
rows. Null texts count as
empty and are scored like a bag of one empty passage. Without labels of both
classes the score is the share of label 1 (0.5 if there are none).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import BASE, SPACE, U, mix, slices, span_hash

PASSAGE = 400
PAIRS = 64
#: Class of each byte: lower, upper, digit, space, line end, high byte, other
#: control; then one class for each ASCII sign.
CLASS = np.full(256, 6, np.int64)
CLASS[97:123], CLASS[65:91], CLASS[48:58], CLASS[32], CLASS[10], CLASS[128:] = 0, 1, 2, 3, 4, 5
SIGNS = [b for b in range(33, 127) if not chr(b).isalnum()]
CLASS[SIGNS] = 7 + np.arange(len(SIGNS))
CLASSES = 7 + len(SIGNS)
WIDTH = CLASSES + PAIRS + 4


def encode(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Features of all passages, and the number of passages of each row."""
    lengths = np.diff(offsets)
    count = np.maximum(1, -(-lengths // PASSAGE))
    first = np.cumsum(count) - count
    row = np.repeat(np.arange(len(lengths)), lengths)
    passage = first[row] + (np.arange(len(data)) - offsets[row]) // PASSAGE
    total, kind = int(count.sum()), CLASS[data]
    size = np.bincount(passage, minlength=total).astype(np.float32)
    per = 1 / np.maximum(size, 1)
    single = np.bincount(passage * CLASSES + kind, minlength=total * CLASSES).reshape(total, CLASSES) * per[:, None]
    code = (kind[:-1] * 31 + kind[1:] * 7) % PAIRS
    same = passage[1:] == passage[:-1]
    pair = np.bincount((passage[:-1] * PAIRS + code)[same], minlength=total * PAIRS).reshape(total, PAIRS) * per[:, None]
    letter = ~SPACE[data]
    begin, end = letter.copy(), letter.copy()
    begin[1:] &= ~letter[:-1] | ~same
    end[:-1] &= ~letter[1:] | ~same
    start, stop = np.flatnonzero(begin), np.flatnonzero(end) + 1
    home = passage[start]
    words = np.bincount(home, minlength=total).astype(np.float32)
    # a distinct (passage, word) counts for its passage
    value = mix(span_hash(data, start, stop) + home.astype(U) * U(BASE))
    order = np.argsort(value, kind="stable")
    new = np.ones(len(order), bool)
    new[1:] = value[order][1:] != value[order][:-1]
    distinct = np.bincount(home[order][new], minlength=total).astype(np.float32)
    rest = np.stack([distinct / np.maximum(words, 1), np.log1p(size), np.log1p(size / np.maximum(words, 1)), (size == 0)], 1)
    return np.concatenate([np.sqrt(single), np.sqrt(pair), rest], 1).astype(np.float32), count


class GatedAttention:
    """Passage layer, gated attention, logistic unit; trained with Adam."""

    def __init__(self, hidden: int = 24, gate: int = 12, seed: int = 7):
        rng = np.random.default_rng(seed)
        draw = lambda *shape: (rng.normal(size=shape) / np.sqrt(shape[0])).astype(np.float32)
        self.w = {"W": draw(WIDTH, hidden), "V": draw(hidden, gate), "G": draw(hidden, gate), "a": draw(gate), "u": draw(hidden), "c": np.zeros(1, np.float32)}
        self.center, self.scale, self.constant = np.zeros(WIDTH, np.float32), np.ones(WIDTH, np.float32), 0.5

    def forward(self, x: np.ndarray, count: np.ndarray) -> dict[str, np.ndarray]:
        w, start = self.w, np.cumsum(count) - count
        x = np.clip((x - self.center) / self.scale, -8, 8)
        h = np.tanh(x @ w["W"])
        t, g = np.tanh(h @ w["V"]), 1 / (1 + np.exp(-(h @ w["G"])))
        s = (t * g) @ w["a"]
        s = np.exp(s - np.repeat(np.maximum.reduceat(s, start), count))
        alpha = s / np.repeat(np.add.reduceat(s, start), count)
        z = np.add.reduceat(alpha[:, None] * h, start)
        p = 1 / (1 + np.exp(-np.clip(z @ w["u"] + w["c"], -30, 30)))
        return {"x": x, "h": h, "t": t, "g": g, "alpha": alpha, "z": z, "p": p, "start": start}

    def gradient(self, f: dict[str, np.ndarray], count: np.ndarray, error: np.ndarray) -> dict[str, np.ndarray]:
        w, each = self.w, lambda v: np.repeat(v, count, 0)
        dz = error[:, None] * w["u"]
        dalpha = (each(dz) * f["h"]).sum(1)
        ds = f["alpha"] * (dalpha - each(np.add.reduceat(f["alpha"] * dalpha, f["start"])))
        dt, dg = ds[:, None] * w["a"] * f["g"] * (1 - f["t"] ** 2), ds[:, None] * w["a"] * f["t"] * f["g"] * (1 - f["g"])
        dh = (f["alpha"][:, None] * each(dz) + dt @ w["V"].T + dg @ w["G"].T) * (1 - f["h"] ** 2)
        return {"W": f["x"].T @ dh, "V": f["h"].T @ dt, "G": f["h"].T @ dg, "a": (ds[:, None] * f["t"] * f["g"]).sum(0), "u": f["z"].T @ error, "c": error.sum(keepdims=True)}

    def fit(self, bags: list[np.ndarray], labels: np.ndarray, epochs: int = 30, rate: float = 0.01, seed: int = 7) -> GatedAttention:
        if len(set(labels.tolist())) < 2:
            self.constant = float(labels.mean()) if len(labels) else 0.5
            return self
        self.constant = None
        every = np.concatenate(bags)
        self.center, self.scale = every.mean(0), every.std(0) + 1e-3
        share, rng = labels.mean(), np.random.default_rng(seed)
        weight = np.where(labels == 1, 0.5 / share, 0.5 / (1 - share))
        m, v, step = {k: 0 for k in self.w}, {k: 0 for k in self.w}, 0
        for epoch in range(epochs):
            order = rng.permutation(len(bags))
            for at in range(0, len(order), 128):
                pick = order[at : at + 128]
                count = np.array([len(bags[i]) for i in pick])
                f = self.forward(np.concatenate([bags[i] for i in pick]), count)
                error = ((f["p"] - labels[pick]) * weight[pick] / len(pick)).astype(np.float32)
                step += 1
                for k, g in self.gradient(f, count, error).items():
                    g = g + 1e-4 * self.w[k]
                    m[k], v[k] = 0.9 * m[k] + 0.1 * g, 0.999 * v[k] + 0.001 * g * g
                    self.w[k] = (self.w[k] - rate * 0.93**epoch * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)).astype(np.float32)
        return self

    def score(self, x: np.ndarray, count: np.ndarray) -> np.ndarray:
        return np.full(len(count), self.constant) if self.constant is not None else self.forward(x, count)["p"].astype(np.float64)


def fit_quality(docs: DataFrame, labels: DataFrame, fit_rows: int = 3000) -> GatedAttention:
    """Fit on at most ``fit_rows`` labelled ids whose crc32 leaves no 1 when
    divided by 3. Of an id with several texts one is read (least hash), of one
    with several labels the greatest counts, so that repeats add no rows."""
    train = labels.where("quality is not null and doc_id is not null").select("doc_id", F.col("quality").cast("int").alias("y"))
    train = train.where(F.crc32(F.col("doc_id").cast("string")) % 3 != 1).groupBy("doc_id").agg(F.max("y").alias("y"))
    train = train.orderBy(F.xxhash64("doc_id", F.lit(11)), "doc_id").limit(fit_rows)

    def bag(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, data, offsets in slices(batches, "text"):
            x, count = encode(data, offsets)
            ends = np.cumsum(count)
            out = [x[a:b].astype(np.float16).tobytes() for a, b in zip(ends - count, ends, strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], ["y", "bag"])

    rows = docs.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(train), "doc_id")
    rows = rows.groupBy("doc_id", "y").agg(F.min_by("text", F.xxhash64("text")).alias("text")).select("y", "text")
    got = rows.mapInArrow(bag, "y int, bag binary").toArrow()
    order = sorted(zip(got["bag"].to_pylist(), got["y"].to_pylist(), strict=True))
    bags = [np.frombuffer(b, np.float16).reshape(-1, WIDTH).astype(np.float32) for b, _ in order]
    return GatedAttention().fit(bags, np.array([y for _, y in order], np.float32))


def score_quality(docs: DataFrame, model: GatedAttention, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, score) of every row, from its whole text."""
    kind = docs.schema[key].dataType.simpleString()

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, data, offsets in slices(batches, "text"):
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(model.score(*encode(data, offsets)))], ["key", "score"])

    return docs.select(F.col(key).alias("key"), F.coalesce(F.col(text), F.lit("")).alias("text")).mapInArrow(judge, f"key {kind}, score double").withColumnRenamed("key", key)


def keep_good(docs: DataFrame, model: GatedAttention, floor: float = 0.5, text: str = "text") -> DataFrame:
    """The rows of ``docs``, all columns, that score ``floor`` or more; a narrow
    pass without a join."""
    at = docs.columns.index(text)

    def keep(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, data, offsets in slices(batches, text):
            yield batch.filter(pa.array(model.score(*encode(data, offsets)) >= floor))

    return docs.mapInArrow(keep, docs.schema) if at >= 0 else docs


def quality_query(docs: DataFrame, labels: DataFrame) -> DataFrame:
    scored = score_quality(docs, fit_quality(docs, labels))
    held = F.crc32(F.col("doc_id").cast("string")) % 3 == 1
    return scored.select("doc_id", F.coalesce(held, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
