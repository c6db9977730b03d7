"""Language identification by a linear-chain conditional random field over words.

Every word carries affix, character n-gram and lexicon features; transitions between the labels of
neighbouring words are learned, so that text that switches language inside a document is labelled word
by word. Forward-backward gives each word's marginal probabilities; the document's language is the label
with the largest sum of marginals, its score that sum divided by the number of words.

Training happens on the driver over a bounded sample (`DOCS_PER_LABEL` documents of each label,
`WINDOW_WORDS` words of each, spliced into sequences that change language); prediction reads whole texts
in a narrow pass: no shuffle, no state but a bounded cache of word scores. A text is one chain whatever its length;
chains over `CHAIN_WORDS` words are handled piece by piece, with the messages carried over between the pieces.

Defined cases: null text, or text without any letter: `und`, score 0. Without any training rows all
documents are `und`. Repeated rows get equal results; ties go to the label that is first by code point. Rows whose
label is null are never trained on. Of a word all letters count, however many.
"""

from __future__ import annotations

import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import crc_mod4, free_name, unit_hash

DOCS_PER_LABEL = 400
WINDOW_WORDS = 240
SEQUENCES = 3000
HASH_BITS = 16
CHAIN_WORDS = 1 << 16
CACHE_WORDS = 200_000
BLOCK = 64
UNDETERMINED = "und"

LETTERS = re.compile(r"[^\W\d_]+")


def words_of(text: str) -> list[str]:
    return LETTERS.findall(text.lower())


def word_features(word: str, lexicon: dict[str, int]) -> list[int]:
    """Hashed ids of a word's features; ids below the label count are the lexicon's."""
    mask, crc = (1 << HASH_BITS) - 1, zlib.crc32
    out = [crc(b"W" + word.encode()) & mask]
    for n in (1, 2, 3):
        if len(word) >= n:
            out += [crc(f"P{word[:n]}".encode()) & mask, crc(f"S{word[-n:]}".encode()) & mask]
    padded = f"^{word}$"
    for n in (2, 3):
        out += [crc(padded[i : i + n].encode()) & mask for i in range(len(padded) - n + 1)]
    if word in lexicon:
        out.append((1 << HASH_BITS) + lexicon[word])
    return out


@dataclass
class ChainModel:
    labels: list[str]
    weights: np.ndarray  # features x labels
    transitions: np.ndarray  # labels x labels, in logs
    start: np.ndarray
    lexicon: dict[str, int]


class Emissions:
    """Scores of words under a model, with a bounded cache."""

    def __init__(self, model: ChainModel):
        self.model, self.ids, self.rows = model, {}, np.zeros((0, len(model.labels)))

    def __call__(self, words: list[str]) -> np.ndarray:
        if len(self.ids) > CACHE_WORDS:
            self.ids, self.rows = {}, self.rows[:0]
        ids = self.ids
        new = [w for w in dict.fromkeys(words) if w not in ids]
        if new:
            feats = [word_features(w, self.model.lexicon) for w in new]
            ends = np.cumsum([len(f) for f in feats])
            flat = np.fromiter((x for f in feats for x in f), np.int64, ends[-1])
            scores = np.add.reduceat(self.model.weights[flat], np.r_[0, ends[:-1]], axis=0)
            first = len(self.rows)
            ids.update((w, first + i) for i, w in enumerate(new))
            self.rows = np.concatenate([self.rows, scores])
        return self.rows[np.fromiter((ids[w] for w in words), np.int64, len(words))]


def scan(mats: np.ndarray, entry: np.ndarray) -> np.ndarray:
    """Normalised row vectors entry @ mats[0] @ ... @ mats[t] for every t, block by block.

    Products inside all blocks are formed side by side, then one vector per block is carried along; the
    result is exact, only the order of the multiplications changes.
    """
    t, k, _ = mats.shape
    blocks = -(-t // BLOCK)
    if pad := blocks * BLOCK - t:
        mats = np.concatenate([mats, np.broadcast_to(np.eye(k), (pad, k, k))])
    mats = np.ascontiguousarray(mats.reshape(blocks, BLOCK, k, k).transpose(1, 0, 2, 3))
    whole = mats[0]
    for step in mats[1:]:
        whole = sum(whole[:, :, i, None] * step[:, None, i, :] for i in range(k))
        whole = whole / whole.sum(axis=(1, 2), keepdims=True)
    at = np.empty((blocks, k))
    for b in range(blocks):
        at[b] = entry
        entry = entry @ whole[b]
        entry = entry / entry.sum()
    out = np.empty((BLOCK, blocks, k))
    for i, step in enumerate(mats):
        at = sum(at[:, j, None] * step[:, j, :] for j in range(k))
        at = at / at.sum(axis=1, keepdims=True)
        out[i] = at
    return out.transpose(1, 0, 2).reshape(blocks * BLOCK, k)[:t]


def chain_matrices(scores: np.ndarray, starts: np.ndarray, transitions: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Each word's step from the labels before it to its own, and its emissions."""
    emit = np.exp(scores - scores.max(axis=1, keepdims=True)) + 1e-30
    move, first = np.exp(transitions), np.exp(start - start.max())
    return np.where(starts[:, None, None], first[None, None, :], move[None]) * emit[:, None, :], emit


def messages(mats: np.ndarray, entry: np.ndarray | None = None, leave: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Forward and backward messages of every word, from those before the first and after the last one."""
    k = mats.shape[1]
    even = np.full(k, 1 / k)
    alpha = scan(mats, even if entry is None else entry)
    beta = np.empty_like(alpha)
    beta[-1] = even if leave is None else leave
    if len(mats) > 1:
        beta[:-1] = scan(mats[:0:-1].transpose(0, 2, 1), beta[-1])[::-1]
    return alpha, beta


def _normal(both: np.ndarray) -> np.ndarray:
    both = both + 1e-300
    return both / both.sum(axis=1, keepdims=True)


def marginals(scores: np.ndarray, starts: np.ndarray, transitions: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Each word's label probabilities; starts marks the words at which a new chain begins."""
    alpha, beta = messages(chain_matrices(scores, starts, transitions, start)[0])
    return _normal(alpha * beta)


def long_chain_sum(words: list[str], model: ChainModel, emissions: Emissions, piece: int = 0) -> np.ndarray:
    """Sum of the marginals of one chain, piece by piece: backward messages at the cuts first, then forward."""
    piece = piece or CHAIN_WORDS
    cuts = list(range(0, len(words), piece))

    def steps(at: int) -> np.ndarray:
        part = words[at : at + piece]
        starts = np.zeros(len(part), bool)
        starts[0] = at == 0
        return chain_matrices(emissions(part), starts, model.transitions, model.start)[0]

    leave = {cuts[-1]: np.full(len(model.labels), 1 / len(model.labels))}
    for before, at in zip(cuts[-2::-1], cuts[:0:-1], strict=True):
        leave[before] = scan(steps(at)[::-1].transpose(0, 2, 1), leave[at])[-1]
    entry, total = None, np.zeros(len(model.labels))
    for at in cuts:
        alpha, beta = messages(steps(at), entry, leave[at])
        total += _normal(alpha * beta).sum(axis=0)
        entry = alpha[-1]
    return total


def train_chain(texts: list[list[str]], labels: list[str], seed: int = 7, epochs: int = 4) -> ChainModel:
    """Fit by Adagrad on sequences spliced from word windows of labelled documents."""
    names = sorted(set(labels))
    k, n_feats = len(names), (1 << HASH_BITS) + len(names)
    index = {x: i for i, x in enumerate(names)}
    by_word: dict[str, Counter] = {}
    for ws, label in zip(texts, labels, strict=True):
        for w in ws:
            by_word.setdefault(w, Counter())[index[label]] += 1
    lexicon = {w: c.most_common(1)[0][0] for w, c in by_word.items() if (n := sum(c.values())) >= 5 and c.most_common(1)[0][1] >= 0.9 * n}
    model = ChainModel(names, np.zeros((n_feats, k)), np.zeros((k, k)), np.zeros(k), lexicon)
    docs = [(ws, index[x]) for ws, x in zip(texts, labels, strict=True) if ws]
    if k < 2 or not docs:
        return model
    rng = np.random.default_rng(seed)
    by_label = [[d for d in docs if d[1] == i] for i in range(k)]
    by_label = [x for x in by_label if x]
    sequences = []
    for _ in range(SEQUENCES):
        ws, ys = [], []
        for _ in range(int(rng.integers(1, 4))):
            group = by_label[rng.integers(len(by_label))]
            own, y = group[rng.integers(len(group))]
            n = int(rng.integers(3, 40))
            at = int(rng.integers(max(1, len(own) - n + 1)))
            ws += own[at : at + n]
            ys += [y] * len(own[at : at + n])
        sequences.append((ws, ys))
    feats = {w: np.array(word_features(w, lexicon)) for ws, _ in sequences for w in ws}
    sq = [np.full(x.shape, 1e-2) for x in (model.weights, model.transitions, model.start)]
    for epoch in range(epochs):
        order = rng.permutation(len(sequences))
        for lo in range(0, len(order), 100):
            part = [sequences[i] for i in order[lo : lo + 100]]
            words = [w for ws, _ in part for w in ws]
            gold = np.array([y for _, ys in part for y in ys])
            lens = np.array([len(ws) for ws, _ in part])
            starts = np.zeros(len(words), bool)
            starts[np.r_[0, np.cumsum(lens)[:-1]]] = True
            sizes = np.array([len(feats[w]) for w in words])
            flat = np.concatenate([feats[w] for w in words])
            scores = np.add.reduceat(model.weights[flat], np.r_[0, np.cumsum(sizes)[:-1]], axis=0)
            mats, _ = chain_matrices(scores, starts, model.transitions, model.start)
            alpha, beta = messages(mats)
            node = _normal(alpha * beta)
            grad = node.copy()
            grad[np.arange(len(gold)), gold] -= 1
            flat_rows = np.repeat(np.arange(len(words)), sizes)
            g_w = np.stack([np.bincount(flat, grad[flat_rows, i], n_feats) for i in range(k)], axis=1) / len(part)
            inner = np.flatnonzero(~starts)
            pair = alpha[inner - 1][:, :, None] * mats[inner] * beta[inner][:, None, :] + 1e-300
            pair /= pair.sum(axis=(1, 2), keepdims=True)
            g_t = pair.sum(axis=0)
            np.subtract.at(g_t, (gold[inner - 1], gold[inner]), 1)
            g_s = (node[starts] - np.eye(k)[gold[starts]]).mean(axis=0)
            for value, grads, total in ((model.weights, g_w, sq[0]), (model.transitions, g_t / len(part), sq[1]), (model.start, g_s, sq[2])):
                grads = grads + 1e-5 * value
                total += grads**2
                value -= 0.15 * grads / np.sqrt(total)
    return model


def _window(text: str, key: int) -> list[str]:
    """A run of words at a place that depends on the row, for training only."""
    ws = words_of(text)
    at = (key * 7919) % max(1, len(ws) - WINDOW_WORDS + 1)
    return ws[at : at + WINDOW_WORDS]


def learn(docs: DataFrame, train: Column, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", docs_per_label: int = DOCS_PER_LABEL, seed: int = 7) -> ChainModel | None:
    """Model of a bounded, seeded sample of the rows that `train` admits; None without any.

    Two jobs: counts per label over all rows, then the sampled texts (docs_per_label of each label).
    """
    rows = docs.select(F.col(id_col).alias("i"), F.col(text_col).alias("t"), F.col(lang_col).alias("y"), train.alias("ok")).filter(F.col("ok") & F.col("y").isNotNull() & F.col("t").isNotNull())
    counts = {r["y"]: r["n"] for r in rows.groupBy("y").agg(F.count("*").alias("n")).orderBy("y").collect()}
    if not counts:
        return None
    share = F.coalesce(F.create_map(*[x for y, n in counts.items() for x in (F.lit(y), F.lit(min(1.0, docs_per_label / n)))])[F.col("y")], F.lit(0.0))

    @F.pandas_udf("array<string>")
    def cut(texts: pd.Series, keys: pd.Series) -> pd.Series:
        return pd.Series([_window(t, int(k)) for t, k in zip(texts, keys, strict=True)])

    sample = rows.filter(unit_hash(F.concat_ws(":", F.col("i").cast("string"), F.lit(seed)), seed) < share).select("y", F.pmod(F.xxhash64("i"), F.lit(1 << 20)).alias("k"), "t").select("y", "k", cut("t", "k").alias("w"))
    got = sorted((r["y"], r["k"], list(r["w"])) for r in sample.collect())
    return train_chain([w for _, _, w in got], [y for y, _, _ in got], seed) if got else None


def _label_batch(texts: list[str | None], model: ChainModel, emissions: Emissions) -> tuple[list[str], list[float]]:
    names, scores = [UNDETERMINED] * len(texts), [0.0] * len(texts)
    words: list[str] = []
    spans: list[tuple[int, int, int]] = []

    def flush() -> None:
        if not words:
            return
        starts = np.zeros(len(words), bool)
        starts[[lo for _, lo, _ in spans]] = True
        m = marginals(emissions(words), starts, model.transitions, model.start)
        for i, lo, hi in spans:
            sums[i] = m[lo:hi].sum(axis=0)
        words.clear()
        spans.clear()

    sums: dict[int, np.ndarray] = {}
    for i, text in enumerate(texts):
        if not text or not any(map(str.isalpha, text)):
            continue
        own = words_of(text)
        if len(own) > CHAIN_WORDS:
            sums[i] = long_chain_sum(own, model, emissions)
            continue
        spans.append((i, len(words), len(words) + len(own)))
        words += own
        if len(words) >= CHAIN_WORDS:
            flush()
    flush()
    for i, total in sums.items():
        best = int(np.argmax(total))
        names[i], scores[i] = model.labels[best], float(min(1.0, total[best] / total.sum()))
    return names, scores


def predictor(docs: DataFrame, model: ChainModel | None):
    """A column function from text to struct<lang_pred string, score double>."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    @F.pandas_udf("lang_pred string, score double")
    def predict(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        own = held.value
        emissions = Emissions(own) if own else None
        for texts in batches:
            names, scores = _label_batch([x if isinstance(x, str) else None for x in texts], own, emissions) if own else ([UNDETERMINED] * len(texts), [0.0] * len(texts))
            yield pd.DataFrame({"lang_pred": names, "score": scores})

    return predict.asNondeterministic()


def identify_languages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """id, held_out, lang_pred and score of every row; labels of held-out rows are never learned from."""
    held_out = crc_mod4(id_col) == 2
    predict = predictor(docs, learn(docs, ~held_out, id_col, text_col, lang_col))
    return docs.select(F.col(id_col), held_out.alias("held_out"), predict(F.col(text_col)).alias("_r")).select(id_col, "held_out", "_r.lang_pred", "_r.score")


def keep_identified(docs: DataFrame, min_score: float = 0.0, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang") -> DataFrame:
    """Rows of docs, all columns, that have a language at a score of min_score or more; all but `und` by default.

    A text of several languages in even shares has a low score and is no less a text, so no score is asked for.
    """
    predict = predictor(docs, learn(docs, crc_mod4(id_col) != 2, id_col, text_col, lang_col))
    name = free_name(docs, "lang_of_row")
    return docs.withColumn(name, predict(F.col(text_col))).filter((F.col(f"{name}.lang_pred") != UNDETERMINED) & (F.col(f"{name}.score") >= min_score)).drop(name)
