"""Language by two levels: the family first, then pairs within the family.

Linear support vector machines over hashed byte trigrams of the whole text
(letters in lower case): one against the rest for the family, one against one
for each pair of languages of a family. The fit reads a bounded, documented
sample (``fit_rows`` ids by their hash); every row is predicted.
A null text, or one without a letter, is ``und`` with score 0. With one
learned language, that one is predicted; with none, ``und``.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LOWER, slices

DIMS = 2048
#: Most rows that are encoded at a time: 512 rows of DIMS numbers are 8 MB.
ROWS = 512
#: Families of common languages; another language is a family of its own.
FAMILIES = {
    "germanic": ["en", "de", "nl", "sv", "da", "no", "is"],
    "romance": ["fr", "es", "it", "pt", "ro", "ca"],
    "slavic": ["ru", "uk", "pl", "cs", "sk", "bg", "sr", "hr"],
}
FAMILY = {lang: family for family, langs in FAMILIES.items() for lang in langs}


def encode(data: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """Unit vectors of the square roots of trigram counts, by row."""
    rows = len(offsets) - 1
    low = LOWER[data].astype(np.int64)
    if len(low) > 1:
        low[1:] += 32 * ((data[:-1] == 0xC3) & (data[1:] >= 0x80) & (data[1:] <= 0x9E))
    row = np.repeat(np.arange(rows), np.diff(offsets))
    if len(low) < 3:
        return np.zeros((rows, DIMS), np.float32)
    code = (low[:-2] * 40503 + low[1:-1] * 2654435 + low[2:] * 97) >> 3
    code = (code ^ (code >> 11)) % DIMS
    inside = row[2:] == row[:-2]
    x = np.bincount((row[:-2] * DIMS + code)[inside], minlength=rows * DIMS).reshape(rows, DIMS)
    x = np.sqrt(x).astype(np.float32)
    return x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)


def fit_svm(x: np.ndarray, y: np.ndarray, epochs: int = 60, penalty: float = 1e-4) -> np.ndarray:
    """Weights and bias of a linear machine with squared hinge loss; y is 1 or
    -1, and both classes weigh the same. Nesterov steps over the whole sample."""
    x = np.concatenate([x, np.ones((len(x), 1), np.float32)], 1)
    weight = np.where(y > 0, 0.5 / max((y > 0).sum(), 1), 0.5 / max((y < 0).sum(), 1)).astype(np.float32)
    w = ahead = np.zeros(x.shape[1], np.float32)
    rate = 0.2
    for step in range(epochs * 5):
        slack = np.maximum(0, 1 - y * (x @ ahead))
        new = ahead - rate * (penalty * ahead - 2 * x.T @ (weight * slack * y))
        ahead, w = new + step / (step + 3) * (new - w), new
    return w


class LanguageTree:
    def __init__(self, x: np.ndarray, langs: list[str]):
        self.langs = sorted(set(langs))
        own, names = np.array([FAMILY.get(lang, lang) for lang in langs]), np.array(langs)
        self.families = sorted(set(own.tolist()))
        self.members = {f: [v for v in self.langs if FAMILY.get(v, v) == f] for f in self.families}
        self.roots = [fit_svm(x, np.where(own == f, 1, -1).astype(np.float32)) for f in self.families] if len(self.families) > 1 else []
        self.pairs = {}
        for f in self.families:
            for a, b in combinations(self.members[f], 2):
                pick = (names == a) | (names == b)
                self.pairs[a, b] = fit_svm(x[pick], np.where(names[pick] == a, 1, -1).astype(np.float32))

    def predict(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Index into ``langs`` (-1 if there is none) and a score from 0 to 1."""
        n = len(x)
        if not self.langs:
            return np.full(n, -1), np.zeros(n)
        margin = lambda w: x @ w[:-1] + w[-1]
        sure = lambda m: 1 / (1 + np.exp(-4 * np.clip(m, -8, 8)))
        root = np.stack([margin(w) for w in self.roots], 1) if self.roots else np.full((n, 1), 2.0)
        family, score, out = root.argmax(1), sure(root.max(1)), np.zeros(n, int)
        for k, f in enumerate(self.families):
            members = self.members[f]
            votes, least = np.zeros((n, len(members))), np.full((n, len(members)), 2.0)
            for i, j in combinations(range(len(members)), 2):
                m = margin(self.pairs[members[i], members[j]])
                votes[:, i] += (m >= 0) + sure(m) * 1e-3
                votes[:, j] += (m < 0) + sure(-m) * 1e-3
                least[:, i], least[:, j] = np.minimum(least[:, i], m), np.minimum(least[:, j], -m)
            best, mine = votes.argmax(1), family == k
            out[mine] = np.array([self.langs.index(v) for v in members])[best[mine]]
            score[mine] *= sure(least[np.arange(n), best][mine])
        return out, score


def fit_languages(docs: DataFrame, fit_rows: int = 3000) -> LanguageTree:
    """Fit on at most ``fit_rows`` ids with text and language whose crc32 is no
    multiple of 5, least hash of the id first. Of an id with several rows one is
    read (least hash of its text and language)."""
    train = docs.where("text is not null and lang is not null and doc_id is not null").where(F.crc32(F.col("doc_id").cast("string")) % 5 != 0)
    ids = F.broadcast(train.select("doc_id").distinct().orderBy(F.xxhash64("doc_id", F.lit(5)), "doc_id").limit(fit_rows))

    def bag(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, data, offsets in slices(batches, "text", rows=ROWS):
            x = encode(data, offsets).astype(np.float16)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([r.tobytes() for r in x], pa.binary())], ["lang", "x"])

    rows = train.select("doc_id", "lang", "text").join(ids, "doc_id", "left_semi")
    rows = rows.groupBy("doc_id").agg(F.min_by(F.struct("lang", "text"), F.xxhash64("text", "lang")).alias("r")).select("r.lang", "r.text")
    got = rows.mapInArrow(bag, "lang string, x binary").toArrow()
    order = sorted(zip(got["x"].to_pylist(), got["lang"].to_pylist(), strict=True))
    x = np.frombuffer(b"".join(b for b, _ in order), np.float16).reshape(-1, DIMS).astype(np.float32)
    return LanguageTree(x, [lang for _, lang in order])


def predict_languages(docs: DataFrame, model: LanguageTree, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, lang_pred, score) of every row, from its whole text."""
    names = pa.array([*model.langs, "und"], pa.string())
    kind = docs.schema[key].dataType.simpleString()

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, data, offsets in slices(batches, "text", rows=ROWS):
            best, score = model.predict(encode(data, offsets))
            bad = ~batch.column(1).to_numpy(zero_copy_only=False).astype(bool) | (best < 0)
            yield pa.RecordBatch.from_arrays([batch.column(0), names.take(pa.array(np.where(bad, len(names) - 1, best))), pa.array(np.where(bad, 0.0, score).astype(np.float64))], ["key", "lang_pred", "score"])

    letter = F.coalesce(F.col(text).rlike(r"\p{L}"), F.lit(False))
    rows = docs.select(F.col(key).alias("key"), letter.alias("letter"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    return rows.mapInArrow(judge, f"key {kind}, lang_pred string, score double").withColumnRenamed("key", key)


def language_query(docs: DataFrame) -> DataFrame:
    held = F.crc32(F.col("doc_id").cast("string")) % 5 == 0
    return predict_languages(docs, fit_languages(docs)).select("doc_id", F.coalesce(held, F.lit(False)).alias("held_out"), "lang_pred", "score")
