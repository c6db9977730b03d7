"""Quality classification by nearest-neighbour voting in a latent semantic space.

A bounded, seeded sample of labelled documents (`MAX_LABELLED`) is turned into weighted counts of hashed byte
trigrams, shapes of characters and repetition measures; a truncated singular value decomposition gives the
latent space. The labelled vectors (a few MB at most, whatever the corpus) go to every worker. Every document
is projected and compared with all labelled vectors by exact cosine products, a block of documents at a time;
the `NEIGHBOURS` nearest vote with weights that grow with similarity.

The pass over documents is narrow. Labels, language, source and ids are no inputs of a score.

Defined cases: null or empty texts, and texts without a similar neighbour, get the share of label 1 in the
sample; without any labels every score is 0.5. Ties between neighbours go to the smaller row of the sample.
Label rows that repeat count once; rows with a null label or id are ignored; conflicting labels: the larger; of
several texts of one labelled id the least is learned from.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_mod4

MAX_LABELLED = 3000
DIMENSIONS = 48
NEIGHBOURS = 15
THRESHOLD = 0.7
GRAM_BITS, SHAPE_BITS, MEASURES = 12, 12, 40
WIDTH = (1 << GRAM_BITS) + (1 << SHAPE_BITS) + MEASURES
BLOCK = 256

_SHAPE = np.arange(256, dtype=np.uint32)
_SHAPE[ord("a") : ord("z") + 1] = ord("a")
_SHAPE[128:] = ord("a")
_SHAPE[ord("A") : ord("Z") + 1] = ord("A")
_SHAPE[ord("0") : ord("9") + 1] = ord("0")
_SHAPE[9:14] = ord(" ")


def counts_of(text: str | None) -> np.ndarray:
    """Hashed counts of one text; all zero without text."""
    out = np.zeros(WIDTH, np.float32)
    if not text or not text.strip():
        return out
    b = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    x, s = b.astype(np.uint32), _SHAPE[b]
    if len(b) >= 3:
        grams = ((x[:-2] * 0x9E3779B1) ^ (x[1:-1] * 0x85EBCA6B) ^ (x[2:] * 0xC2B2AE35)) * np.uint32(0x27D4EB2F)
        out[: 1 << GRAM_BITS] = np.bincount(grams >> (32 - GRAM_BITS), minlength=1 << GRAM_BITS)
        shapes = ((s[:-2] * 0x9E3779B1) ^ (s[1:-1] * 0x7FEB352D) ^ (s[2:] * 0x846CA68B)) * np.uint32(0x27D4EB2F)
        out[1 << GRAM_BITS : -MEASURES] = np.bincount(shapes >> (32 - SHAPE_BITS), minlength=1 << SHAPE_BITS)
        out[:-MEASURES] = np.log1p(out[:-MEASURES] * (1000 / len(b)))
    words = text.split()
    n = len(words)
    seen = Counter(words)
    lines = [y for y in text.split("\n") if y.strip()]
    letters = max(1, int(np.isin(s, (ord("a"), ord("A"))).sum()))
    measures = (
        sum(map(str.__eq__, words, words[1:])) / n,
        seen.most_common(1)[0][1] / n,
        (1 - len(seen) / n) * min(1.0, n / 50),
        1 - len(set(lines)) / max(1, len(lines)),
        (s == ord("A")).sum() / letters,
        (s == ord("0")).sum() / len(b),
        ((s != ord("a")) & (s != ord("A")) & (s != ord("0")) & (s != ord(" "))).sum() / len(b),
        min(1.0, np.log1p(n) / 10),
    )
    for i, value in enumerate(measures):  # two neighbouring steps of five share a value
        at = min(max(float(value), 0.0), 1.0) ** 0.5 * 4
        low = min(3, int(at))
        out[WIDTH - MEASURES + i * 5 + low] = 1 - (at - low)
        out[WIDTH - MEASURES + i * 5 + low + 1] = at - low
    return out


def nearest(sims: np.ndarray, k: int) -> np.ndarray:
    """Whether each column is among its row's k largest; of equal ones the first are."""
    least = np.partition(sims, sims.shape[1] - k, axis=1)[:, sims.shape[1] - k, None]
    above, equal = sims > least, sims == least
    return above | (equal & (np.cumsum(equal, axis=1) <= k - above.sum(axis=1, keepdims=True)))


@dataclass
class LatentModel:
    weights: np.ndarray  # of every feature
    basis: np.ndarray  # features x dimensions
    vectors: np.ndarray  # labelled rows x dimensions, of length one
    labels: np.ndarray
    prior: float

    def project(self, counts: np.ndarray) -> np.ndarray:
        v = (counts * self.weights) @ self.basis
        return v / np.maximum(np.linalg.norm(v, axis=1, keepdims=True), 1e-9)

    def score(self, counts: np.ndarray) -> np.ndarray:
        empty = ~counts.any(axis=1)
        if not len(self.labels):
            return np.full(len(counts), self.prior)
        sims = self.project(counts) @ self.vectors.T
        k = min(NEIGHBOURS, sims.shape[1])
        w = np.where(nearest(sims, k), np.maximum(sims, 0) ** 4, 0)
        total = w.sum(axis=1)
        out = np.where(total > 1e-9, (w @ self.labels) / np.maximum(total, 1e-9), self.prior)
        out[empty] = self.prior
        return np.clip(out, 0, 1)


def fit(counts: np.ndarray, labels: np.ndarray, dimensions: int = DIMENSIONS, seed: int = 11) -> LatentModel:
    """Latent space by randomised subspace iteration over the weighted counts."""
    if not len(labels):
        return LatentModel(np.ones(WIDTH, np.float32), np.zeros((WIDTH, 1), np.float32), np.zeros((0, 1), np.float32), labels, 0.5)
    df = (counts > 0).sum(axis=0)
    weights = (np.log((1 + len(labels)) / (1 + df)) + 0.3).astype(np.float32)
    weights[1 << GRAM_BITS : -MEASURES] *= 2
    weights[-MEASURES:] = 8 * np.sqrt(np.maximum(1e-6, (counts[:, : 1 << GRAM_BITS] ** 2).sum(axis=1).mean())) / np.sqrt(1 << 9)
    x = counts * weights
    x /= np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-9)
    k = min(dimensions + 8, *x.shape)
    q = np.linalg.qr(x.T @ (x @ np.random.default_rng(seed).standard_normal((x.shape[1], k)).astype(np.float32)))[0]
    for _ in range(2):
        q = np.linalg.qr(x.T @ (x @ q))[0]
    _, _, vt = np.linalg.svd(x @ q, full_matrices=False)
    basis = (q @ vt.T)[:, :dimensions].astype(np.float32)
    model = LatentModel(weights, basis, np.zeros((0, 1), np.float32), labels.astype(np.float32), float(labels.mean()))
    model.vectors = model.project(counts).astype(np.float32)
    return model


def learn(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", max_labelled: int = MAX_LABELLED) -> LatentModel:
    """Model of the labelled rows, not held out, with the smallest hashes of their ids.

    The choice of ids reads the narrow label table; the texts are then found by a broadcast of those ids.
    """
    ids = labels.select(F.col(id_col).alias("_i"), F.col(label_col).alias("_y")).filter((crc_mod4("_i") != 2) & F.col("_i").isNotNull() & F.col("_y").isNotNull())
    ids = ids.groupBy("_i").agg(F.max("_y").cast("float").alias("_y")).orderBy(F.xxhash64("_i"), "_i").limit(max_labelled)

    @F.pandas_udf("at array<int>, value array<float>")
    def sparse(texts: pd.Series) -> pd.DataFrame:
        rows = [counts_of(x) for x in texts]
        at = [np.flatnonzero(r) for r in rows]
        return pd.DataFrame({"at": [a.astype(np.int32) for a in at], "value": [r[a] for r, a in zip(rows, at, strict=True)]})

    texts = docs.select(F.col(id_col).alias("_i"), F.col(text_col).alias("_t")).join(F.broadcast(ids), "_i").groupBy("_i").agg(F.min("_t").alias("_t"), F.first("_y").alias("_y"))
    got = texts.select("_i", "_y", sparse("_t").alias("_c")).select("_i", "_y", "_c.*").toPandas().sort_values("_i")
    counts = np.zeros((len(got), WIDTH), np.float32)
    for row, at, value in zip(counts, got["at"], got["value"], strict=True):
        row[at] = value
    return fit(counts, got["_y"].to_numpy(np.float32))


def scorer(docs: DataFrame, model: LatentModel):
    """A column function from text to the score."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("double")
    def score(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        own = held.value
        for texts in batches:
            out = [own.score(np.stack([counts_of(x if isinstance(x, str) else None) for x in texts[i : i + BLOCK]])) for i in range(0, len(texts), BLOCK)]
            yield pd.Series(np.concatenate(out) if out else [], dtype="float64")

    return score.asNondeterministic()


def classify_quality(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", threshold: float = THRESHOLD) -> DataFrame:
    """id, held_out, score (0 to 1) and predicted (score >= threshold) of every row."""
    model = learn(docs, labels, id_col, text_col, label_col)
    scored = docs.select(F.col(id_col), (crc_mod4(id_col) == 2).alias("held_out"), scorer(docs, model)(F.col(text_col)).alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))
